"""Mixing sources to target weights by pivotal dependent rounding.

A source's target over its size is the rate at which its documents are copied: a whole number of copies and a fraction. Fractions are settled in pairs:
words move at random from one document's share to another's, so that the sum of words never changes, until one of the two shares is whole. Each leaf of a
reduction tree leaves at most one open share, and leaves meet in groups until one is open for each source; so a source's words miss its target by less than
one document. All chance is a hash of ids and seed, and leaves are dealt by id: reruns agree, also after lost executors.

Null text: size 0. Null source: a source of its own, last in order. Identical rows (id, source and text) are one item: of their copies the whole number is taken, and
only what is left of a single copy is open, so they miss no more than one row does. Rows of size 0 take nothing. An empty table gives an empty mix. A hot source has
more leaves, never larger ones. Other columns do not matter (where identical rows differ in them, any of these may be the one that is copied).
"""

from __future__ import annotations

import math
from functools import partial, reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HOT_KEYS, HOT_LEAST, durable, mix64, n_words

LEAF_ROWS, FAN_IN = 4096, 64
#: Up to so many sources, the table of sources (a few numbers each) is broadcast.
BROADCAST_SOURCES = 100_000

_OPEN = "id {id}, th long, source string, size long, repeats long, source_size long, target double, source_no long, leaf long, base long, copies long, share double"


def source_targets(items: DataFrame, weights: tuple[float, ...], share: float, most: float) -> DataFrame:
    """For each source (column source, with size and repeats): source_size, n, source_no, target. Weights repeat in order of source; targets sum to share times all
    sizes, none is above most times its source's size, and what that cuts off goes to the others by weight. Sources are sorted and numbered by ranges, and the common
    level of those below their bounds is found by sums alone, so there may be any number of them."""
    spark = items.sparkSession
    sums = items.groupBy("source").agg(F.sum(F.col("size") * F.col("repeats")).cast("long").alias("source_size"), F.count(F.lit(1)).alias("n"))
    by_name = F.col("source").asc_nulls_last()
    ranged = durable(sums.repartitionByRange(by_name).sortWithinPartitions(by_name).withColumn("mark", F.monotonically_increasing_id()))
    part, counts, before = F.shiftright("mark", 33), {}, []
    for r in ranged.groupBy(part.alias("part")).count().collect():  # a row for each partition at most
        counts[r["part"]] = r["count"]
    for k in sorted(counts):
        before.append((k, sum(counts[j] for j in counts if j < k)))
    starts = F.broadcast(spark.createDataFrame(before, "part long, before long"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.col("source_no"), F.lit(len(weights))) + 1).cast("int"))
    numbered = ranged.withColumn("part", part).join(starts, "part").withColumn("source_no", F.col("before") + F.col("mark").bitwiseAND(F.lit((1 << 33) - 1)))
    level = durable(numbered.withColumn("w", w).withColumn("cap", most * F.col("source_size")).select("source", "source_size", "n", "source_no", "w", "cap"))
    total = share * (level.agg(F.sum("source_size")).first()[0] or 0)
    line, full = 0.0, -1
    while True:  # the level rises as sources reach their bounds, at most once for each step, and often for many at a time
        free = F.col("cap") > line * F.col("w")
        cut, weight, n_full = level.agg(F.sum(F.when(~free, F.col("cap"))), F.sum(F.when(free, F.col("w"))), F.count(F.when(~free, 1))).first()
        if weight is None or n_full == full:
            break
        line, full = (total - (cut or 0.0)) / weight, n_full
    return level.select("source", "source_size", "n", "source_no", F.least(F.col("cap"), F.lit(line) * F.col("w")).alias("target") if weight is not None else F.col("cap").alias("target"))


def _chance(ids: np.ndarray, seed: int) -> np.ndarray:
    return (mix64(ids.astype(np.int64).view(np.uint64) + np.uint64(seed)) >> np.uint64(11)).astype(float) / (1 << 53)


def _settle(rows: pd.DataFrame, seed: int, last: bool) -> pd.DataFrame:
    """Shares of one group, settled in pairs from the largest down, so that what stays open at the end is small; at most one does, none if last."""
    rows = rows.assign(weight=rows["size"]).sort_values(["weight", "key"], ascending=False, kind="stable").reset_index(drop=True)
    u, share, copies, weight = _chance(rows["key"].to_numpy(), seed), rows["share"].to_numpy(dtype=float, copy=True), rows["copies"].to_numpy(dtype=np.int64, copy=True), rows["weight"].to_numpy(dtype=float)
    open_ = -1
    for i in range(len(rows)):
        if math.isnan(share[i]):
            continue
        if weight[i] == 0:
            share[i] = np.nan
            continue
        if open_ < 0:
            open_ = i
            continue
        a, b = open_, i
        k = weight[a] / weight[b]
        up, down = min(1 - share[a], share[b] / k), min(share[a], (1 - share[b]) / k)
        move = up if u[i] * (up + down) < down else -down
        share[a] += move
        share[b] -= move * k
        open_ = -1
        for x in (a, b):
            if share[x] < 1e-12 or share[x] > 1 - 1e-12:
                copies[x] += share[x] > 0.5
                share[x] = np.nan
            else:
                open_ = x
    if last and open_ >= 0:
        copies[open_] += u[open_] < share[open_]
        share[open_] = np.nan
    return rows.assign(copies=copies, share=share).drop(columns=["weight", "key"])


def _one(f):
    return lambda rows: f(rows)


def mix_sources(docs: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 7) -> DataFrame:
    """One row for each distinct (id, source, text): id, th (a hash of the text), source, size, repeats, source_size, target (its source's), base (copies of each of its
    rows) and extra (how many of its rows have one more)."""
    items = durable(
        docs.select(F.col(f"`{id_col}`").alias("id"), F.xxhash64(F.col(f"`{text_col}`")).alias("th"), F.col(f"`{source_col}`").cast("string").alias("source"), n_words(F.col(f"`{text_col}`")).alias("size"))
        .groupBy("id", "th", "source", "size").agg(F.count(F.lit(1)).alias("repeats"))
    )
    sources = durable(source_targets(items, weights, share, most))
    n_sources, largest = sources.agg(F.count(F.lit(1)), F.max("n")).first()
    sources = F.broadcast(sources) if n_sources <= BROADCAST_SOURCES else sources
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    joined = items.join(sources.withColumnRenamed("source", "its"), F.col("source").eqNullSafe(F.col("its"))).drop("its")
    more = F.col("repeats") * (rate - F.floor(rate))
    leaves = F.ceil(F.col("n") / LEAF_ROWS)
    start = joined.select(
        "id", "th", "source", "size", "repeats", "source_size", "target", "source_no",
        F.pmod(F.xxhash64("id", "th", F.lit(seed)), leaves).alias("leaf"), F.floor(rate).cast("long").alias("base"),
        F.floor(more).cast("long").alias("copies"), (more - F.floor(more)).alias("share"),
    )
    schema = _OPEN.format(id=dict(items.dtypes)["id"])
    levels = 1 + max(0, math.ceil(math.log(max(1, -(-(largest or 0) // LEAF_ROWS)), FAN_IN) - 1e-9))
    parts, todo = [], start
    for level in range(levels):
        keyed = todo.withColumn("key", F.xxhash64("id", "th", F.lit(level)))
        settle = partial(_settle, seed=seed + 1000 * level, last=level == levels - 1)
        done = durable(keyed.groupBy("source_no", "leaf").applyInPandas(_one(settle), schema))
        parts.append(done.where(F.isnan("share") | F.col("share").isNull()))
        todo = done.where(~F.isnan("share") & F.col("share").isNotNull()).withColumn("leaf", F.floor(F.col("leaf") / FAN_IN))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("id", "th", "source", "size", "repeats", "source_size", "target", "base", F.when(F.col("size") > 0, F.col("copies")).otherwise(0).cast("long").alias("extra"))


def mixed(docs: DataFrame, **how) -> DataFrame:
    """The rows of docs, each as often as the mix takes it, with the columns of docs."""
    id_col, text_col, source_col = how.get("id_col", "doc_id"), how.get("text_col", "text"), how.get("source_col", "source")
    mix = durable(mix_sources(docs, **how).select(F.col("id").alias("mx_id"), F.col("th").alias("mx_th"), F.col("source").alias("mx_source"), F.col("repeats").alias("mx_repeats"), F.when(F.col("size") > 0, F.col("base")).otherwise(0).alias("mx_base"), F.col("extra").alias("mx_extra")))
    on = {"mx_key_id": "mx_id", "mx_key_th": "mx_th", "mx_key_source": "mx_source"}
    left = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(f"`{id_col}`").alias("mx_key_id"), F.xxhash64(F.col(f"`{text_col}`")).alias("mx_key_th"), F.col(f"`{source_col}`").cast("string").alias("mx_key_source"))
    same = reduce(lambda a, b: a & b, (F.col(a).eqNullSafe(F.col(b)) for a, b in on.items()))
    wanted = mix.where("mx_base + mx_extra > 0")
    n, most_rows = mix.agg(F.sum("mx_repeats"), F.max("mx_repeats")).first()
    limit = max(HOT_LEAST, -(-(n or 0) // HOT_KEYS))
    if (most_rows or 0) <= limit:
        met = left.join(wanted, same)
    else:  # items of very many rows, HOT_KEYS at most, are broadcast
        hot = F.broadcast(mix.where(F.col("mx_repeats") > limit))
        met = left.join(hot, same, "left_anti").join(wanted.where(F.col("mx_repeats") <= limit), same).unionByName(left.join(hot, same))
    copied = met.selectExpr("row", "CASE WHEN mx_repeats = 1 THEN mx_base + mx_extra ELSE mx_base END AS mx_copies").where("mx_copies > 0")
    if (most_rows or 0) > 1:  # of an item of several rows, the further copies are all from one of them
        copied = copied.unionByName(met.where("mx_repeats > 1 AND mx_extra > 0").dropDuplicates([*on]).selectExpr("row", "mx_extra AS mx_copies"))
    return copied.select("row", F.explode(F.sequence(F.lit(1).cast("long"), "mx_copies")).alias("copy")).select("row.*")
