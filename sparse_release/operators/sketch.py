"""Count sketches of sparse counts, private and not."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.noise import alpha_of, geometric, sensitivity
from ..functions.prf import draw
from .summaries import SEEDED, Plan, all_noisy, noisy_at, weight_sums


def _placed(cells: DataFrame, w: int, d: int, seed, mode: str, extra: tuple[str, ...] = ()) -> DataFrame:
    """cell_id, row, bucket, sign and other columns, a row for each of d hashes."""
    up = cells.selectExpr("cell_id", *extra, f"explode(sequence(0, {d - 1})) AS row")
    h = draw(seed, "sketch", "row", "cell_id", mode=mode)
    return up.selectExpr("cell_id", *extra, "row", f"{h} AS h").selectExpr("cell_id", *extra, "row", f"CAST(shiftright(h, 1) % {w} AS INT) AS bucket", "CASE WHEN h % 2 = 0 THEN 1 ELSE -1 END AS sign")


def count_sketch(cells: DataFrame, w: int, d: int, seed: str | int = 1, mode: str = "md5", v: str = "v") -> DataFrame:
    """(row, bucket, v): sums of signed counts, for buckets that hold any cell."""
    return _placed(cells, w, d, seed, mode, (v,)).groupBy("row", "bucket").agg(F.sum(F.col("sign") * F.col(v)).cast("long").alias("v"))


def private_sketch(cells: DataFrame, w: int, d: int, eps: float, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """All w * d buckets, each with noise for a person who moves two buckets of each row."""
    grid = cells.sparkSession.range(w * d).selectExpr(f"CAST(id div {w} AS INT) AS row", f"CAST(id % {w} AS INT) AS bucket")
    noise = geometric(alpha_of(eps, sensitivity("sketch", rows=d)), seed, "row", "bucket", tag="sketch-noise", mode=mode)
    return grid.join(count_sketch(cells, w, d, seed, mode), ["row", "bucket"], "left").selectExpr("row", "bucket", f"coalesce(v, 0) + {noise} AS v")


def sketch_of_noisy(cells: DataFrame, plan: Plan, w: int, d: int) -> DataFrame:
    """The strawman: every cell's noise goes into the sketch."""
    return count_sketch(all_noisy(cells, plan), w, d, plan.seed, plan.mode, v="value")


def sketch_of_noisy_sums(cells: DataFrame, plan: Plan, w: int, asked: DataFrame) -> DataFrame:
    """As sketch_of_noisy of one row, for domains too large to draw cell by cell. Occupied cells and the asked ones (cell_id, distinct, of the domain) are hashed and noised one
    by one. Of the others no answer uses more than what falls into a bucket: how many do is a multinomial draw, as the hash is a random function, and what their noise comes
    to is one draw of the sum's law, which signs do not change. Buckets are drawn by groups, each with its own seed."""
    known = cells.where(f"cell_id >= 0 AND cell_id < {plan.m}").select("cell_id").unionByName(asked.select("cell_id")).distinct()
    noisy = durable(noisy_at(cells, plan, known))
    starts, alpha, spark = np.arange(0, w, SEEDED), plan.alpha, cells.sparkSession
    sizes = np.minimum(SEEDED, w - starts)
    seed = int(spark.range(1).selectExpr(draw(plan.key, "buckets", "0", mode=plan.mode)).first()[0])
    shares = np.random.default_rng(seed).multinomial(plan.m - noisy.count(), sizes / w)
    groups = spark.createDataFrame([(int(a), int(n), int(k)) for a, n, k in zip(starts, sizes, shares, strict=True)], "a long, n long, k long")  # a row for each group

    def drawn(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for a, n, k, s in part.itertuples(index=False):
                rng = np.random.default_rng(int(s))
                held = rng.multinomial(int(k), np.full(int(n), 1 / n))
                noise = weight_sums(rng, held, alpha)[0].astype(np.int64)
                yield pd.DataFrame({"bucket": (a + np.arange(n)).astype(np.int32), "v": noise})[held > 0]

    rest = groups.selectExpr("*", f"{draw(plan.key, 'bucket-sums', 'a', mode=plan.mode)} AS s").mapInPandas(drawn, "bucket int, v long").selectExpr("0 AS row", "bucket", "v")
    return rest.unionByName(count_sketch(noisy, w, 1, plan.seed, plan.mode, v="value")).groupBy("row", "bucket").agg(F.sum("v").cast("long").alias("v"))


def sketch_point(sketch: DataFrame, cells: DataFrame, w: int, d: int, seed: str | int = 1, how: str = "mean", mode: str = "md5") -> DataFrame:
    """(cell_id, estimate): mean or median of a cell's signed buckets."""
    at = _placed(cells.select("cell_id").distinct(), w, d, seed, mode).join(sketch, ["row", "bucket"], "left").selectExpr("cell_id", "CAST(sign * coalesce(v, 0) AS DOUBLE) AS x")
    return at.groupBy("cell_id").agg((F.avg("x") if how == "mean" else F.median("x")).alias("estimate"))


def sketch_sum(sketch: DataFrame, members: DataFrame, w: int, d: int, seed: str | int = 1, how: str = "mean", mode: str = "md5") -> DataFrame:
    """(qid, estimate) for subsets (qid, cell_id), as sums of point estimates."""
    return members.join(sketch_point(sketch, members, w, d, seed, how, mode), "cell_id").groupBy("qid").agg(F.sum("estimate").alias("estimate"))
