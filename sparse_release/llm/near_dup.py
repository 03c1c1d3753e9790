"""SimHash near-duplicates by a byte-position inverted index with count filtering.

A fingerprint has 8 bytes. Two that differ in at most 4 bits share at least 4 bytes in place, so every pair that shares fewer is left out by count, and the rest is
verified bit by bit. Postings of a single byte would hold one in 256 fingerprints each, and their pairs would grow with the square of the input; so the index is kept
over chosen triples of positions instead, TRIPLES, so chosen that any 4 shared places hold one of them whole: no pair with enough shared bytes is missed, and each
pair that meets there has its shared bytes tallied as before. Equal fingerprints are drawn together first, so copies cost nothing.

A posting list of over BLOCK fingerprints is dealt out again by the fourth byte that a pair in it must share; what is still as long, in pairs of blocks. A list of over
WIDE is left to its fingerprints' variants, all values within 2 bits of one: two fingerprints are within 4 bits of each other just if they have a variant in common, and
a variant has 2,081 owners at most, so the work grows with the list and not with its square. Only edges that join something new leave a batch, and components come from
alternating large-star and small-star rounds, all in tables (up to HELD edges in one process); keys with many rows (roots, hubs, fingerprints of many copies) are joined by broadcasting the one row that
the other side has for each. No cap anywhere.

With a bound on similarity given, a text's fingerprint is that of its set of `width`-word shingles, pairs that the index finds are checked by their whole sets (Jaccard
similarity of at least the bound), and shingle_join adds the links between texts whose fingerprints lie further apart than the index reaches.

Null or empty text: fingerprint 0, linked like any other. Rows with a null id get a component but never name one (null, if all of its rows have null ids). Repeated
rows are rows of the same group. An empty table gives an empty result. Other columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shingle_join
from .common import HOT_KEYS, HOT_LEAST, durable, fresh, join_unique, partitions

SHINGLE, SEED = 4, 42
#: Shingles whose bits are counted at once.
COUNTED = 1 << 16

MAX_BITS, LEAST_BYTES = 4, 4
#: Fingerprints of one posting list that one task compares with each other; length from which a list's fingerprints meet in their variants.
BLOCK, WIDE = 1024, 262_144
#: Edges whose components one process finds (16 bytes each); more are joined in rounds over tables.
HELD = 200_000
#: Rows (id and hash) that are sent to each task at most.
SENT = 500_000


def triples() -> list[tuple[int, ...]]:
    """Triples of 8 positions of which any 4 positions hold one: from groups of 3, 3 and 2 in a ring, those within a group, and two of a group with one of the next."""
    ring = [(0, 1, 2), (3, 4, 5), (6, 7)]
    inside = [g for g in ring if len(g) == 3]
    return inside + [(*pair, one) for k, g in enumerate(ring) for pair in combinations(g, 2) for one in ring[(k + 1) % 3]]


TRIPLES = triples()


def simhash(text: str | None, width: int = SHINGLE, seed: int = SEED) -> int:
    """64 bits, each 1 if it is set in over half of the hashes of all runs of `width` words (of the whole text, if shorter); 0 without words."""
    words = (text or "").encode().lower().split()  # of bytes: A-Z, and the six ASCII blanks
    if not words:
        return 0
    runs = zip(*(words[k:] for k in range(width)), strict=False) if len(words) >= width else [words]
    n = max(1, len(words) - width + 1)
    h = np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, runs), repeat(seed)), ">u8", n)
    set_ = np.zeros(64, np.int64)
    for at in range(0, n, COUNTED):
        bits = np.unpackbits(h[at : at + COUNTED].view(np.uint8).reshape(-1, 8), axis=1)
        set_ += bits.sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(2 * set_ > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str, text_col: str, width: int = SHINGLE) -> DataFrame:
    """id, th (a hash of the text) and fp (the fingerprint's bits as a signed long) of each row."""
    rows = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"), F.xxhash64(F.col(f"`{text_col}`")).alias("th"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((simhash(t.as_py(), width) for t in b.column(1)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(fp.view(np.int64))], ["id", "th", "fp"])

    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, th long, fp long")


def linked(a: np.ndarray, b: np.ndarray, max_bits: int = MAX_BITS) -> np.ndarray:
    """Which pairs pass the count of shared positional bytes, and then differ in few enough bits."""
    diff = a ^ b
    near = (diff.view(np.uint8).reshape(-1, 8) == 0).sum(axis=1) >= LEAST_BYTES
    near[near] = np.bitwise_count(diff[near]) <= max_bits
    return near


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges of a star in each component of the graph with edges (a, b): node, its component's smallest."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    u, v, root = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        low = np.minimum(root[u], root[v])
        new = root.copy()
        np.minimum.at(new, root[u], low)
        np.minimum.at(new, root[v], low)
        new = new[new[new]]
        if (new == root).all() and (root[u] == root[v]).all():
            break
        root = new
    own = np.flatnonzero(root != np.arange(len(nodes)))
    return nodes[own], nodes[root[own]]


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges among rows (group, side, fp) sorted by group; side 0 throughout: all pairs of the group; else pairs of sides 1 and 2."""
    held: list[np.ndarray] = []

    def edges(group: np.ndarray, side: np.ndarray, fp: np.ndarray) -> pa.RecordBatch:
        ends = np.searchsorted(group, group, side="right")
        at, found, step = np.arange(len(group)), [], 1
        while len(at := at[at + step < ends[at]]):
            other = at + step
            pair = (side[at] == 0) | (side[at] != side[other])
            x, y = at[pair], other[pair]
            ok = linked(fp[x], fp[y])
            found.append((fp[x[ok]], fp[y[ok]]))
            step += 1
        a, b = forest(*(np.concatenate([f[k] for f in found]) for k in (0, 1))) if found else (fp[:0], fp[:0])
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    rest = [np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.uint64)]
    for batch in batches:
        held = [np.concatenate((r, c)) for r, c in zip(rest, (batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_numpy().view(np.uint64)), strict=True)]
        cut = np.searchsorted(held[0], held[0][-1]) if len(held[0]) else 0  # the last group may go on; groups come in ascending order
        rest = [h[cut:] for h in held]
        yield edges(*(h[:cut] for h in held))
    yield edges(*rest)


def _byte(k: int) -> str:
    return f"(shiftrightunsigned(fp, {8 * k}) & 255)"


def _long_lists(postings: DataFrame, block: int) -> DataFrame | None:
    """k, n: lists (column key) of over block rows; None if there are none."""
    found = durable(postings.groupBy("key").count().where(f"count > {block}").selectExpr("key AS k", "count AS n"))
    return None if found.isEmpty() else found


def candidate_edges(fps: DataFrame, block: int = BLOCK, wide: int = WIDE) -> DataFrame:
    """Edges (a, b) that connect what links of at most MAX_BITS differing bits connect. fps: distinct fp (long)."""
    n = partitions(fps.sparkSession)
    keys = ", ".join(f"{t}L * 16777216L + {_byte(p)} * 65536L + {_byte(q)} * 256L + {_byte(r)}" for t, (p, q, r) in enumerate(TRIPLES))
    postings = fps.selectExpr("fp", f"explode(array({keys})) AS key")
    rows, edges = postings.selectExpr("key AS grp", "0 AS side", "fp"), None
    if (large := _long_lists(postings, block)) is not None:
        on = F.col("key") == F.col("k")
        rest = [[k for k in range(8) if k not in t] for t in TRIPLES]
        fourth = " ".join(f"WHEN {t} THEN array({', '.join(f'xxhash64(key, {k}, {_byte(k)})' for k in ks)})" for t, ks in enumerate(rest))
        finer = durable(postings.join(large, on, "left_semi").selectExpr("fp", f"explode(CASE key div 16777216L {fourth} END) AS key"))
        rows = rows.join(large, F.col("grp") == F.col("k"), "left_anti")
        if (still := _long_lists(finer, block)) is None:
            rows = rows.unionByName(finer.selectExpr("key AS grp", "0 AS side", "fp"))
        else:
            rows = rows.unionByName(finer.join(still, on, "left_anti").selectExpr("key AS grp", "0 AS side", "fp"))
            sized = join_unique(finer.join(still.where(f"n <= {wide}"), on, "left_semi"), still, {"key": "k"}).selectExpr("fp", "key", f"CAST(ceil(n / {block}) AS INT) AS blocks")
            dealt = sized.selectExpr("fp", "key", "blocks", "CAST(pmod(xxhash64(fp), blocks) AS INT) AS i").selectExpr("fp", "key", "i", "explode(sequence(0, blocks - 1)) AS j")
            rows = rows.unionByName(dealt.selectExpr("xxhash64(key, least(i, j), greatest(i, j)) AS grp", "CASE WHEN i = j THEN 0 WHEN i < j THEN 1 ELSE 2 END AS side", "fp"))
            edges = by_variants(finer.join(still.where(f"n > {wide}"), on, "left_semi").select("fp").distinct(), n)
    met = rows.repartition(n, "grp").sortWithinPartitions("grp").mapInArrow(_compare, "a long, b long")
    return met if edges is None else met.unionByName(edges)


def by_variants(fps: DataFrame, n: int) -> DataFrame:
    """Edges among distinct fps that have a variant within MAX_BITS / 2 bits in common, a star for each variant."""
    one = np.uint64(1) << np.arange(64, dtype=np.uint64)
    flips = np.array([0] + [int(np.bitwise_or.reduce(one[list(c)])) for k in range(1, MAX_BITS // 2 + 1) for c in combinations(range(64), k)], np.uint64)

    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = b.column(0).to_numpy().view(np.uint64)
            for at in range(0, len(fp), 64):
                some = fp[at : at + 64]
                yield pa.RecordBatch.from_arrays([pa.array((some[:, None] ^ flips).ravel().view(np.int64)), pa.array(np.repeat(some, len(flips)).view(np.int64))], ["variant", "fp"])

    def stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        variant = hub = None  # a variant's rows may go on in the next batch
        for b in batches:
            v, fp = b.column(0).to_numpy(), b.column(1).to_numpy()
            if not len(v):
                continue
            heads = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
            first = fp[heads]
            if variant == v[0]:
                first[0] = hub
            own = np.repeat(first, np.diff(np.append(heads, len(v))))
            variant, hub = v[-1], first[-1]
            yield pa.RecordBatch.from_arrays([pa.array(fp[fp != own]), pa.array(own[fp != own])], ["a", "b"])

    return fps.mapInArrow(spell, "variant long, fp long").repartition(n, "variant").sortWithinPartitions("variant").mapInArrow(stars, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """For edges (a, b): node and root (its component's smallest node), for each node that is not a root."""

    def cut(e: DataFrame) -> tuple[DataFrame, tuple]:
        e = durable(e.where("a != b").selectExpr("greatest(a, b) AS a", "least(a, b) AS b").distinct())
        return e, tuple(e.selectExpr("count(*)", "sum(CAST(xxhash64(a, b) AS DECIMAL(38)))").first())

    def met(e: DataFrame, least: DataFrame) -> DataFrame:
        return join_unique(e, least, {"a": "u"})

    e, mark = cut(edges)
    if 0 < mark[0] <= HELD:
        few = e.toArrow()
        return e.sparkSession.createDataFrame(pa.table(dict(zip(("node", "root"), map(pa.array, forest(*(few.column(c).to_numpy() for c in ("a", "b")))), strict=True))))
    while mark[0]:
        both = e.unionByName(e.selectExpr("b AS a", "a AS b"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).selectExpr("a AS u", "least(a, m) AS m")
        large = durable(met(both, least).where("b > a").selectExpr("b AS a", "m AS b").where("a != b").distinct())
        least = large.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "u")
        small = met(large, least).selectExpr("explode(array(struct(a AS a, m AS b), struct(b AS a, m AS b))) AS e").selectExpr("e.a", "e.b")
        e, new = cut(small)
        if new == mark:
            break
        mark = new
    return e.selectExpr("a AS node", "b AS root")


def index_pairs(sets: DataFrame, block: int = BLOCK) -> DataFrame:
    """Pairs (a, b) of names of sets (fp) whose fingerprints (sim) are equal or connected by the index: of each fingerprint's names the least stands for it."""
    heads = durable(sets.groupBy("sim").agg(F.min("fp").alias("head")))
    name = lambda c: heads.select(F.col("sim").alias(f"s_{c}"), F.col("head").alias(f"h_{c}"))
    alike = join_unique(sets, name("a"), {"sim": "s_a"}).where("fp != h_a").selectExpr("h_a AS a", "fp AS b")
    edges = candidate_edges(heads.selectExpr("sim AS fp"), block)
    apart = join_unique(join_unique(durable(edges), name("a"), {"a": "s_a"}), name("b"), {"b": "s_b"}).selectExpr("h_a AS a", "h_b AS b")
    return durable(alike.unionByName(apart).where("a != b").selectExpr("least(a, b) AS a", "greatest(a, b) AS b").distinct())


def grouped(docs: DataFrame, id_col: str, text_col: str, block: int, width: int = SHINGLE, similarity: float | None = None) -> tuple[DataFrame, DataFrame]:
    """Rows (id, th, fp), and for each fp its component: root, and the component's first row, by id (null last) and th."""
    texts = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"), F.xxhash64(F.col(f"`{text_col}`")).alias("th"))
    rows = durable(fingerprints(docs, id_col, text_col, width) if similarity is None else shingle_join.names(texts, width))
    first = F.min(F.struct(F.col("id").isNull().alias("nameless"), "id", "th")).alias("first")
    if similarity is None:
        fps = durable(rows.groupBy("fp").agg(first))
        edges = candidate_edges(fps.select("fp"), block)
    else:
        fps = durable(rows.groupBy("fp").agg(first, F.min("sim").alias("sim")))
        edges = shingle_join.similar_edges(texts.select("text", "th"), rows, width, similarity, near=index_pairs(fps.select("fp", "sim"), block))
    roots = components(edges)
    rooted = durable(fps.join(roots, F.col("fp") == F.col("node"), "left").selectExpr("fp", "first", "coalesce(root, fp) AS root"))
    firsts = rooted.groupBy("root").agg(F.min("first").alias("first")).withColumnRenamed("root", "r")
    return rows, durable(join_unique(rooted.drop("first"), firsts, {"root": "r"}).selectExpr("fp AS f", "root", "first"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """For each row: id, fp (fingerprint, as a signed long), component_id (smallest id that links reach, its own included)."""
    rows, named = grouped(docs, id_col, text_col, block)
    return join_unique(rows, named, {"fp": "f"}).select(F.col("id").alias(id_col), "fp", F.col("first.id").alias("component_id"))


def representatives(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, width: int = SHINGLE, similarity: float | None = None) -> DataFrame:
    """One row of docs for each component, the first by id (null last), then by the text's hash; with the columns of docs. similarity: least Jaccard similarity of a link (else: bits)."""
    rows, named = grouped(docs, id_col, text_col, block, width, similarity)
    k, h, n = fresh(docs, "nd_id", "nd_th", "nd_n")
    # ids and hashes are of rows; so few repeat whole that a row of each with its number is joined, and hot ones are drawn together before they move
    counts = durable(rows.groupBy("id", "th").agg(F.min("fp").alias("fp"), F.count(F.lit(1)).alias("count")))
    again = durable(counts.where("count > 1").select(F.col("id").alias("nd_again_id"), F.col("th").alias("nd_again_th"), F.col("count").alias(n)))
    # rows that go are fewer than those that stay: texts need not move while the former are few enough to be sent to each task
    won = F.col("id").eqNullSafe(F.col("first.id")) & (F.col("th") == F.col("first.th"))
    lost = durable(join_unique(counts.drop("count"), named, {"fp": "f"}).where(~won).selectExpr("id AS nd_lost_id", "th AS nd_lost_th"))
    keyed = docs.select(*[F.col(f"`{c}`") for c in docs.columns], F.col(f"`{id_col}`").alias(k), F.xxhash64(F.col(f"`{text_col}`")).alias(h))
    goes = F.col(k).eqNullSafe(F.col("nd_lost_id")) & (F.col(h) == F.col("nd_lost_th"))
    kept = keyed.join(F.broadcast(lost) if lost.count() <= SENT else lost, goes, "left_anti")
    if not again.isEmpty():
        same = F.col(k).eqNullSafe(F.col("nd_again_id")) & (F.col(h) == F.col("nd_again_th"))
        rare, hot = (again.where(c).drop(n) for c in (f"`{n}` <= {HOT_LEAST}", f"`{n}` > {HOT_LEAST}"))
        several = kept.join(rare, same, "left_semi").unionByName(kept.join(F.broadcast(hot) if hot.count() <= HOT_KEYS else hot, same, "left_semi")).dropDuplicates([k, h])
        lone = kept.join(again.drop(n), same, "left_anti") if hot.isEmpty() else kept.join(F.broadcast(hot) if hot.count() <= HOT_KEYS else hot, same, "left_anti").join(rare, same, "left_anti")
        kept = lone.unionByName(several)
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns])


def spelled(fp: str = "fp") -> F.Column:
    """A fingerprint as 16 hexadecimal digits."""
    return F.lower(F.lpad(F.hex(F.col(fp)), 16, "0"))
