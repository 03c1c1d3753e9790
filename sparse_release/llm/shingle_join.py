"""Links between texts whose sets of word shingles have a Jaccard similarity of at least a bound, none lost.

Two such sets, each put in one common order, share at least SHARED shingles (or all they share) among their first n - ceil(bound * n) + SHARED; so postings are kept
of these alone, and only pairs that meet so often are compared. Rare shingles come
first in the order, by a sample of about SAMPLE texts, which decides costs only. Pairs that meet in a posting list are compared by their whole sets. A list of over
CROWD sets is compared by sketches: parities of the shingles in about FINE times as many bits as the set has shingles. Two sketches differ in no more bits than their sets
differ in shingles, so a pair with too many different bits, as they are or folded to an eighth, is left out without loss. The others are compared by their whole sets:
in rounds first, each set and its nearest of another class, so that a round has no more pairs than the lists have rows; once a round links few, all that are not in one
class by then. Only sketches, a byte to two for each shingle, are dealt out to the lists; blocks of a list meet in pairs. Sets that are alike
meet in most of their lists, so each comes with the FIRST smallest keys of its long lists: a list hands on no pair that shares a smaller key among these, as that key's list
has the pair too. No cap anywhere.

Candidates that a caller has already (near_dup: of its fingerprints' index) are compared first; pairs and lists that lie within one class of what these link need no
comparison any more.

Shingles are 64-bit hashes of runs of `width` words (ASCII letters in lower case); a shorter text is one shingle, a text without words is the empty set, and equal
sets are one node. The node's name is a hash of its set.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, join_unique, partitions, window_hashes, word_hashes, word_spans

SEED, AT_ONCE, SAMPLE, SHARED = 42, 256, 20_000, 4
#: Sets of a posting list that are paired at once; sets of one block of a longer list; pairs that a task hands on at once.
CROWD, BLOCK, PAIRS = 64, 4096, 65_536
#: Smallest keys of long lists that come with a set; words of a sketch for one of its folded form; links of a round from which another one follows (decides costs only).
FIRST, FINE, LINKED = 8, 8, 10_000
#: Shingles whose bits are counted at once.
COUNTED = 1 << 16


def shingle_sets(texts: list[str | None], width: int) -> list[np.ndarray]:
    """Each text's distinct shingles, in ascending order."""
    raw = [(t or "").encode().lower() for t in texts]
    buf, bounds = np.frombuffer(b"".join(raw), np.uint8), np.concatenate(([0], np.cumsum([len(r) for r in raw])))
    starts, ends, firsts = word_spans(buf, bounds)
    hashes, at = window_hashes(word_hashes(buf, starts, ends, SEED), firsts, width, SEED)
    cuts, out = np.searchsorted(at, firsts), []
    for k, r in enumerate(raw):
        n = firsts[k + 1] - firsts[k]
        out.append(np.unique(hashes[cuts[k] : cuts[k + 1]]) if n >= width else np.array([xxhash.xxh64_intdigest(b" ".join(r.split()), SEED)] if n else [], np.uint64))
    return out


def named(s: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(s.tobytes(), SEED)


def _read(b: pa.RecordBatch, column: int, width: int) -> Iterator[tuple[int, list[np.ndarray]]]:
    for at in range(0, b.num_rows, AT_ONCE):
        yield at, shingle_sets(b.column(column).slice(at, AT_ONCE).to_pylist(), width)


def bits(s: np.ndarray) -> int:
    """The fingerprint of a set: 64 bits, each 1 if it is set in over half of its shingles; 0 for the empty set."""
    total = np.zeros(64, np.int64)
    for at in range(0, len(s), COUNTED):
        total += np.unpackbits(s[at : at + COUNTED].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(2 * total > len(s)).tobytes(), "big")


def _longs(x) -> pa.Array:
    return pa.array(np.asarray(x, np.uint64).view(np.int64))


def names(rows: DataFrame, width: int) -> DataFrame:
    """rows: id, text, th. id, th, fp (the set's name) and sim (its fingerprint), both as signed longs, of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            both = [(named(s), bits(s)) for _, sets in _read(b, 1, width) for s in sets]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), _longs([x for x, _ in both]), _longs([y for _, y in both])], ["id", "th", "fp", "sim"])

    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, th long, fp long, sim long")


def common_shingles(texts: DataFrame, n: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that several texts of a sample hold, ascending, and how many hold each. The sample's size does not grow with the table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, sets in _read(b, 0, width):
                yield pa.RecordBatch.from_arrays([_longs(np.concatenate(sets))], ["h"])

    some = texts.where(F.expr(f"pmod(th, {max(1, n // SAMPLE)}) = 0")).dropDuplicates(["th"]).select("text")
    found = some.mapInArrow(run, "h long").groupBy("h").count().where("count > 1").toArrow()
    h, c = found.column("h").to_numpy().view(np.uint64), found.column("count").to_numpy()
    order = np.argsort(h)
    return h[order], c[order]


def prefix(s: np.ndarray, bound: Fraction, common: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The shingles of a set that are posted."""
    h, c = common
    count = np.zeros(len(s), np.int64)
    if len(h):
        at = np.minimum(np.searchsorted(h, s), len(h) - 1)
        count = np.where(h[at] == s, c[at], 0)
    return s[np.lexsort((s, count))[: len(s) + int(-bound * len(s) // 1) + SHARED]]


def _meetings(bound: Fraction, crowd: int):
    """Of rows (key, fp, n) sorted by key and fp: pairs (and how often they must meet), and of lists of over `crowd` sets the rows themselves (key, fp; need 0)."""
    p, q = bound.numerator, bound.denominator

    def pairs(key: np.ndarray, fp: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        if len(key):  # equal sets post alike
            new = np.append(True, (key[1:] != key[:-1]) | (fp[1:] != fp[:-1]))
            key, fp, n = key[new], fp[new], n[new]
        start = np.searchsorted(key, key)
        size = np.searchsorted(key, key, side="right") - start
        listed = np.flatnonzero(size > crowd)
        found, at, step = [], np.flatnonzero((size > 1) & (size <= crowd)), 1
        while len(at := at[at + step < start[at] + size[at]]):
            other = at + step
            ok = q * np.minimum(n[at], n[other]) >= p * np.maximum(n[at], n[other])
            need = np.minimum(SHARED, -(-p * np.maximum(n[at[ok]], n[other[ok]]) // q))
            found.append((np.minimum(fp[at[ok]], fp[other[ok]]), np.maximum(fp[at[ok]], fp[other[ok]]), need))
            step += 1
        a, b, need = (np.concatenate([f[k] for f in found] + [x]) for k, x in enumerate((key[listed], fp[listed], np.zeros(len(listed), np.int64))))
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(need)], ["a", "b", "need"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = [np.empty(0, np.int64)] * 3
        for b in batches:
            held = [np.concatenate((r, b.column(k).to_numpy())) for k, r in enumerate(rest)]
            cut = np.searchsorted(held[0], held[0][-1]) if len(held[0]) else 0  # the last list may go on
            rest = [h[cut:] for h in held]
            yield pairs(*(h[:cut] for h in held))
        yield pairs(*rest)

    return run


def _binaries(c: pa.Array) -> list[np.ndarray]:
    """The sets of a column, in place."""
    at, data = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1] // 8, c.buffers()[2]
    words = np.frombuffer(data, np.uint64, data.size // 8) if data else np.empty(0, np.uint64)
    return [words[at[k] : at[k + 1]] for k in range(len(c))]


def _similar(bound: Fraction):
    p, q = bound.numerator, bound.denominator

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for s, t in zip(_binaries(b.column(2)), _binaries(b.column(3)), strict=True):
                both = len(np.intersect1d(s, t, assume_unique=True))
                ok.append(q * both >= p * (len(s) + len(t) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], ["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return run


def _compared(pairs: DataFrame, sets: DataFrame, bound: Fraction) -> DataFrame:
    """Those of the pairs (a, b) whose whole sets (f, hs) are similar enough."""
    x, y = (sets.select(F.col("f").alias(f"f_{c}"), F.col("hs").alias(h)) for c, h in (("a", "x"), ("b", "y")))
    met = join_unique(join_unique(pairs.select("a", "b"), x, {"a": "f_a"}).select("a", "b", "x"), y, {"b": "f_b"})
    return met.select("a", "b", "x", "y").mapInArrow(_similar(bound), "a long, b long")


def sketch_words(n: int) -> int:
    """Words of 64 bits of the sketch of a set of n shingles: a power of two, FINE times what gives at least three bits for four shingles."""
    return FINE << max(0, (-(-3 * n // 256) - 1).bit_length())


def sketch(s: np.ndarray) -> np.ndarray:
    """Bit k tells whether an odd number of the set's shingles have the remainder k."""
    n = 64 * sketch_words(len(s))
    odd = np.bincount((s & np.uint64(n - 1)).astype(np.int64), minlength=n) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


def _met_before(key: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Which pairs of rows (smallest keys of a set each, none twice) share a key below this one."""
    return ((x[:, :, None] == y[:, None, :]) & (x < key)[:, :, None]).any(axis=(1, 2))


def _candidates(bound: Fraction, key: int, side: np.ndarray, own: np.ndarray, n: np.ndarray, bits: list[np.ndarray], low: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Pairs (of places) of a list's sets, ordered by size, of different classes (own) whose sizes and sketches allow the bound and that share no smaller key (low), and the
    share of different bits; side as in near_dup. No place comes twice as first, or as second, of the pairs yielded at once."""
    p, q = bound.numerator, bound.denominator
    words = np.array([len(x) for x in bits])
    for w in np.unique(words):
        some = np.flatnonzero((words == w) | (words == 2 * w))  # a set of at most q / p times the size has no longer ones; folded, they are of w words
        m = np.stack([bits[k] if len(bits[k]) == w else bits[k][:w] ^ bits[k][w:] for k in some])
        folded = np.bitwise_xor.reduce(m.reshape(len(some), FINE, -1), axis=1)
        size, c, d = n[some], own[some], side[some]

        def near(x: np.ndarray, y: np.ndarray, m: np.ndarray, size: np.ndarray = size) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            gap, at_once = np.empty(len(x), np.int64), PAIRS // m.shape[1] + 1
            for k in range(0, len(x), at_once):
                gap[k : k + at_once] = np.bitwise_count(m[x[k : k + at_once]] ^ m[y[k : k + at_once]]).sum(axis=1, dtype=np.int64)
            ok = (p + q) * gap <= (q - p) * (size[x] + size[y])
            return x[ok], y[ok], gap[ok] / (size[x[ok]] + size[y[ok]])

        at, step = np.arange(int((words == w).sum())), 1
        ends = np.searchsorted(size, q * size[at] // p, side="right")
        while len(at := at[at + step < ends[at]]):
            other = at + step
            ok = (c[at] != c[other]) & ((d[at] == 0) | (d[at] != d[other]))
            x, y, _ = near(at[ok], other[ok], folded)
            x, y, gap = near(x, y, m)
            new = ~_met_before(key, low[some[x]], low[some[y]])
            yield some[x[new]], some[y[new]], gap[new]
            step += 1


def _lists(bound: Fraction, lone: bool):
    """Candidates among rows (grp, side, fp, own, n, key, bits, low) sorted by grp and n: of each set the one with its nearest (lone), or all."""

    def pairs(side: np.ndarray, fp: np.ndarray, own: np.ndarray, n: np.ndarray, key: np.ndarray, bits: list[np.ndarray], low: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        batch = lambda a, b: pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])
        lows = np.full((len(low), max(map(len, low))), key[0])  # one that is not below the key counts for nothing
        for k, x in enumerate(low):
            lows[k, : len(x)] = x
        met = _candidates(bound, key[0], side, own, n, bits, lows)
        if lone:
            mate, best = np.full(len(fp), -1), np.full(len(fp), np.inf)
            for x, y, gap in met:
                for a, b in ((x, y), (y, x)):
                    less = gap < best[a]
                    mate[a[less]], best[a[less]] = b[less], gap[less]
            a = np.flatnonzero(mate >= 0)
            yield batch(fp[a], fp[mate[a]])
            return
        held, count = [], 0
        for x, y, _ in met:
            held.append((fp[x], fp[y]))
            count += len(x)
            if count >= PAIRS:
                yield batch(*(np.concatenate([h[k] for h in held]) for k in (0, 1)))
                held, count = [], 0
        if count:
            yield batch(*(np.concatenate([h[k] for h in held]) for k in (0, 1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers, bits, low = [np.empty(0, np.int64)] * 6, [], []
        for b in batches:
            numbers = [np.concatenate((r, b.column(k).to_numpy())) for k, r in enumerate(numbers)]
            bits += [x.copy() for x in _binaries(b.column(6))]
            low += [x.astype(np.int64) for x in b.column(7).to_numpy(zero_copy_only=False)]
            heads = np.flatnonzero(np.append(True, numbers[0][1:] != numbers[0][:-1])) if len(bits) else []
            for lo, hi in zip(heads[:-1], heads[1:], strict=True):
                yield from pairs(*(r[lo:hi] for r in numbers[1:]), bits[lo:hi], low[lo:hi])
            if len(heads):  # the last list may go on
                numbers, bits, low = [r[heads[-1] :] for r in numbers], bits[heads[-1] :], low[heads[-1] :]
        if bits:
            yield from pairs(*numbers[1:], bits, low)

    return run


def similar_edges(docs: DataFrame, rows: DataFrame, width: int, similarity: float, crowd: int = CROWD, block: int = BLOCK, near: DataFrame | None = None) -> DataFrame:
    """Edges (a, b) of fps that connect what pairs of at least this similarity connect. docs: text and th (its hash); rows: id, th and fp of each row; near: candidates
    (a, b) that are compared first."""
    from .near_dup import components

    spark, bound = docs.sparkSession, Fraction(str(similarity))
    n = partitions(spark)
    one = durable(rows.groupBy("fp").agg(F.min("th").alias("t")))  # a text of each set
    common = spark.sparkContext.broadcast(common_shingles(docs, rows.count(), width))

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, sets in _read(b, 0, width):
                own = {named(s): s for s in sets}
                posted = [prefix(s, bound, common.value) if len(s) else s for s in own.values()]
                size = [len(x) for x in posted]
                yield pa.RecordBatch.from_arrays([_longs(np.concatenate(posted)), _longs(np.repeat(np.array([*own], np.uint64), size)), pa.array(np.repeat([len(s) for s in own.values()], size))], ["key", "fp", "n"])

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, sets in _read(b, 0, width):
                yield pa.RecordBatch.from_arrays([_longs([named(s) for s in sets]), pa.array([s.tobytes() for s in sets], pa.binary())], ["f", "hs"])

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, sets in _read(b, 0, width):
                yield pa.RecordBatch.from_arrays([_longs([named(s) for s in sets]), pa.array([len(s) for s in sets], pa.int64()), pa.array([sketch(s).tobytes() for s in sets], pa.binary())], ["f", "n", "bits"])

    def texts_of(nodes: DataFrame) -> DataFrame:
        """A text of each set among nodes (node)."""
        wanted = durable(one.join(nodes.distinct(), F.col("fp") == F.col("node"), "left_semi").select("t"))
        few = F.broadcast(wanted) if wanted.count() <= 500_000 else wanted  # longs
        return docs.join(few, F.col("th") == F.col("t"), "left_semi").dropDuplicates(["th"]).select("text")

    def sets_of(pairs: DataFrame) -> DataFrame:
        return durable(texts_of(pairs.selectExpr("explode(array(a, b)) AS node")).mapInArrow(whole, "f long, hs binary"))

    def classed(rows: DataFrame, column: str, classes: DataFrame, name: str) -> DataFrame:
        return join_unique(rows, classes.select(F.col("node").alias("c_n"), F.col("root").alias("c_r")), {column: "c_n"}, "left").select(*rows.columns, F.coalesce("c_r", column).alias(name))

    postings = docs.select("text").mapInArrow(post, "key long, fp long, n long")
    meetings = postings.repartition(n, "key").sortWithinPartitions("key", "fp").mapInArrow(_meetings(bound, crowd), "a long, b long, need long")
    met = durable(meetings.groupBy("a", "b", "need").count().where("count >= need").drop("count"))
    apart, lists = met.where("need > 0").select("a", "b"), met.where("need = 0").selectExpr("a AS key", "b AS fp")
    sets = sets_of(apart if near is None else apart.unionByName(near))
    if near is not None:
        near = durable(_compared(near, sets, bound))
        classes = components(near)
        apart = durable(classed(classed(apart, "a", classes, "r_a"), "b", classes, "r_b").where("r_a != r_b").select("a", "b"))
    found = _compared(apart, sets, bound)
    if near is not None:
        found = found.unionByName(near)
    if lists.isEmpty():
        return found
    found, sketches = durable(found), None
    lone = True
    while True:
        rows = classed(lists, "fp", components(found), "own")
        several = rows.groupBy("key").agg(F.min("own").alias("low"), F.max("own").alias("high"), F.count(F.lit(1)).alias("count")).where("low != high").selectExpr("key AS k", f"CAST(ceil(count / {block}) AS INT) AS blocks")
        rows = durable(rows.join(several, F.col("key") == F.col("k")).select("key", "fp", "own", "blocks"))
        if sketches is None:
            low = lists.groupBy("fp").agg(F.expr(f"slice(sort_array(collect_list(key)), 1, {FIRST})").alias("low")).withColumnRenamed("fp", "l_f")
            made = texts_of(rows.selectExpr("fp AS node")).mapInArrow(sketched, "f long, n long, bits binary")
            sketches = durable(made.join(low, F.col("f") == F.col("l_f")).select("f", "n", "bits", "low"))
        dealt = rows.selectExpr("*", "CAST(pmod(xxhash64(fp), blocks) AS INT) AS i").selectExpr("*", "explode(sequence(0, blocks - 1)) AS j")
        parts = dealt.selectExpr("xxhash64(key, least(i, j), greatest(i, j)) AS grp", "CASE WHEN i = j THEN 0L WHEN i < j THEN 1L ELSE 2L END AS side", "fp", "own", "key")
        held = parts.join(sketches, F.col("fp") == F.col("f")).select("grp", "side", "fp", "own", "n", "key", "bits", "low").repartition(n, "grp").sortWithinPartitions("grp", "n", "fp")
        pairs = durable(held.mapInArrow(_lists(bound, lone), "a long, b long").distinct())
        if pairs.isEmpty():
            return found
        alike = durable(_compared(pairs, sets_of(pairs), bound))
        found = found.unionByName(alike)
        if not lone:
            return found
        lone = alike.count() > LINKED
