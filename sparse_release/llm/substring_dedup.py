"""Substring deduplication by fixed-block anchors.

A repeat of `window` words holds, wherever it lies, one whole block of `block` words of the other text's grid if window >= 2 * block - 1. So only blocks on each
text's grid are indexed, every rolling window of `block` words probes the index, and hits are widened to the `window`-word runs that hold them; runs that also
begin in a text of smaller id are removed, and neighbouring ones join to maximal repeats.

How it is dealt out: texts lie in chunks of some hundred, by a hash of id and text. A chunk sends each index bucket one row of packed hashes (each hash once for a
chunk, so groups of copies are drawn together before anything moves) and gets one row of bits back; texts themselves move once. The first exchange uses short hashes,
which let through a few runs too many. The second decides: a run is 96 bits, 64 and 32 of two hashes that share neither word hashes nor factors, with the smallest
id of the chunk that holds it. Widening a hit against each text that holds its block would take as many comparisons as a group of copies has pairs, since which text
of the group goes on for a whole window is not known before; the index of runs answers for all of them at once.

Null text: no words. Null id: the row is kept whole and makes no other smaller. Rows with equal ids do not count as smaller than each other. Texts shorter than a
window are kept; texts of any length are treated whole. An empty table gives an empty result. Other columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BLANK_RE, n_words, partitions, window_hashes, word_hashes, word_spans

#: Rows of a chunk.
CHUNK_ROWS = 256
#: Index buckets for each shuffle partition; a task holds one at a time.
BUCKETS = 2

_RESULT = "id long, n_words long, removed array<struct<start:long,end:long>>, kept_text string, copies long"


def in_chunks(rows: DataFrame, chunk_rows: int) -> DataFrame:
    """rows (id, text) dealt into chunks of about so many by hashes of both, with `copies`. Where an id has more rows than a chunk, rows that are equal become one, with their number."""
    crowded = not rows.groupBy("id").count().where(F.col("count") > chunk_rows).isEmpty()
    rows = rows.groupBy("id", "text").agg(F.count(F.lit(1)).alias("copies")) if crowded else rows.withColumn("copies", F.lit(1).cast("long"))
    chunks = max(1, -(-rows.count() // chunk_rows))
    return rows.withColumn("chunk", F.pmod(F.xxhash64("id", "text"), F.lit(chunks)).cast("long"))


class Chunk:
    """Words of some texts and their hashes; texts in order of id."""

    def __init__(self, rows: pa.Table, window: int, block: int) -> None:
        rows = rows.sort_by("id")
        self.ids, self.window, self.block = rows.column("id").to_numpy(), window, block
        text = rows.column("text").combine_chunks().fill_null("").cast(pa.large_binary())
        off = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
        self.buf = np.frombuffer(text.buffers()[2] or b"", np.uint8)[off[0] : off[-1]]
        self.bounds = off - off[0]
        starts, ends, self.firsts = word_spans(self.buf, self.bounds)
        self.spans = starts, ends
        self.words = word_hashes(self.buf, starts, ends, 1)

    def doc_of(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.firsts, at, side="right") - 1

    def anchors(self, buckets: int) -> None:
        """Distinct rolling block hashes in order of bucket and hash, and where each occurs."""
        h, at = window_hashes(self.words, self.firsts, self.block, 3)
        bucket = ((h >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
        order = np.lexsort((h, bucket))
        self.at, h, self.bucket = at[order], h[order], bucket[order]
        self.new = np.ones(len(h), bool)
        self.new[1:] = h[1:] != h[:-1]
        self.heads = np.flatnonzero(self.new)
        self.h = h[self.heads]

    def split(self, bucket: np.ndarray) -> Iterator[tuple[int, slice]]:
        """Slices of equal bucket."""
        cut = np.flatnonzero(np.diff(bucket, prepend=-1))
        for a, b in zip(cut, [*cut[1:], len(bucket)][: len(cut)], strict=True):
            yield int(bucket[a]), slice(int(a), int(b))

    def candidates(self, live: np.ndarray) -> None:
        """Runs of `window` words that hold a live block: where they start, and their hashes."""
        hit = np.zeros(len(self.words) + 1, np.int64)
        hit[self.at[live[np.cumsum(self.new) - 1]] + 1] = 1
        hit = np.cumsum(hit)
        low, at = window_hashes(self.words, self.firsts, self.window, 11)
        span = self.window - self.block + 1
        some = hit[at + span] > hit[at]
        high, _ = window_hashes(word_hashes(self.buf, *self.spans, 2), self.firsts, self.window, 12)
        self.run_at, self.run_h, self.run_x = at[some], low[some], (high[some] >> np.uint64(32)).astype(np.uint32)

    def runs(self, buckets: int) -> None:
        bucket = (self.run_h % np.uint64(buckets)).astype(np.int64)
        owner = self.ids[self.doc_of(self.run_at)] if len(self.run_at) else np.empty(0, np.int64)
        order = np.lexsort((owner, self.run_x, self.run_h, bucket))
        self.run_at, self.run_h, self.run_x, self.owner, bucket = (x[order] for x in (self.run_at, self.run_h, self.run_x, owner, bucket))
        self.run_new = np.ones(len(order), bool)
        self.run_new[1:] = (self.run_h[1:] != self.run_h[:-1]) | (self.run_x[1:] != self.run_x[:-1])
        self.run_heads = np.flatnonzero(self.run_new)
        self.run_bucket = bucket[self.run_heads]


def _owners(ids: bytes, which: bytes, n: int) -> np.ndarray:
    """Ids of n runs from a table of ids and places in it."""
    return np.frombuffer(ids, np.int64)[np.frombuffer(which, f"u{len(which) // n}")]


def _bits(x: np.ndarray) -> bytes:
    return np.packbits(x).tobytes()


def _unbits(x: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(x, np.uint8), count=n).astype(bool)


def _replies(rows: pa.Table, size: int) -> np.ndarray:
    """Bits for all distinct hashes of a chunk, from the rows that came back: first place, count, bits."""
    out = np.zeros(size, bool)
    for at, n, bits in zip(*(rows.column(c).to_pylist() for c in ("place", "n", "bits")), strict=True):
        out[at : at + n] = _unbits(bits, n)
    return out


def dedup_substrings(docs: DataFrame, window: int = 13, block: int = 7, id_col: str = "doc_id", text_col: str = "text", chunk_rows: int = CHUNK_ROWS) -> DataFrame:
    """id, n_words, removed (word ranges, ends exclusive), kept_text (the other words, joined by one space)."""
    if window < 2 * block - 1:
        raise ValueError("a window must hold a whole block wherever the grid lies: window >= 2 * block - 1")
    n_parts = partitions(docs.sparkSession)
    buckets = BUCKETS * n_parts
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text_col}`").alias("text"))
    placed = in_chunks(rows.where("id IS NOT NULL"), chunk_rows)
    texts = placed.repartition(n_parts, "chunk")  # one exchange, reused by the three passes below

    def ask(key: tuple, rows: pa.Table) -> pa.Table:
        c = Chunk(rows, window, block)
        c.anchors(buckets)
        doc = c.doc_of(c.at)
        ids = c.ids[doc] if len(doc) else np.empty(0, np.int64)
        on_grid = (c.at - c.firsts[doc]) % block == 0
        if len(c.heads):
            indexed = np.logical_or.reduceat(on_grid, c.heads)
            several = np.minimum.reduceat(ids, c.heads) != np.maximum.reduceat(ids, c.heads)
        short, out = (c.h & np.uint64(0xFFFFFFFF)).astype(np.uint32), []
        for bucket, s in c.split(c.bucket[c.heads]):
            out.append((bucket, s.start, short[s].tobytes(), _bits(indexed[s]), _bits(several[s])))
        return _table(key[0].as_py(), out, ("bucket", "place", "hashes", "indexed", "several"), (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary()))

    asked = texts.groupBy("chunk").applyInArrow(ask, "chunk long, bucket int, place long, hashes binary, indexed binary, several binary")

    def meet(rows: pa.Table) -> pa.Table:
        hs = [np.frombuffer(x.as_py(), np.uint32) for x in rows.column("hashes")]
        n = [len(x) for x in hs]
        h, chunk = np.concatenate(hs), np.repeat(np.arange(len(n), dtype=np.int32), n)
        indexed, several = (np.concatenate([_unbits(x.as_py(), k) for x, k in zip(rows.column(c), n, strict=True)]) for c in ("indexed", "several"))
        order = np.argsort(h, kind="stable")
        heads = np.flatnonzero(np.diff(h[order].astype(np.int64), prepend=-1))
        at = chunk[order]
        live = np.logical_or.reduceat(indexed[order], heads) & (np.logical_or.reduceat(several[order], heads) | (np.minimum.reduceat(at, heads) != np.maximum.reduceat(at, heads)))
        bits = np.empty(len(h), bool)
        bits[order] = np.repeat(live, np.diff(np.append(heads, len(h))))
        return _reply(rows, n, bits, 0)

    live = asked.groupBy("bucket").applyInArrow(meet, "chunk long, step int, place long, n long, bits binary")

    def ask_runs(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if left.num_rows and right.num_rows:
            c = _with_candidates(left, right)
            c.runs(buckets)
            h, x = c.run_h[c.run_heads], c.run_x[c.run_heads]
            for bucket, s in c.split(c.run_bucket):
                ids, which = np.unique(c.owner[c.run_heads[s]], return_inverse=True)
                out.append((bucket, s.start, h[s].tobytes(), x[s].tobytes(), ids.tobytes(), which.astype(np.min_scalar_type(len(ids))).tobytes()))
        return _table(key[0].as_py(), out, ("bucket", "place", "hashes", "more", "ids", "which"), (pa.int32(), pa.int64(), *[pa.binary()] * 4))

    def _with_candidates(left: pa.Table, right: pa.Table) -> Chunk:
        c = Chunk(left, window, block)
        c.anchors(buckets)
        c.candidates(_replies(right.filter(pa.compute.equal(right.column("step"), 0)), len(c.h)))
        return c

    asked_runs = texts.groupBy("chunk").cogroup(live.groupBy("chunk")).applyInArrow(ask_runs, "chunk long, bucket int, place long, hashes binary, more binary, ids binary, which binary")

    def first_seen(rows: pa.Table) -> pa.Table:
        hs = [np.frombuffer(x.as_py(), np.uint64) for x in rows.column("hashes")]
        n = [len(x) for x in hs]
        h, x = np.concatenate(hs), np.concatenate([np.frombuffer(x.as_py(), np.uint32) for x in rows.column("more")])
        own = np.concatenate([_owners(*c, k) for *c, k in zip(rows.column("ids").to_pylist(), rows.column("which").to_pylist(), n, strict=True)])
        order = np.lexsort((own, x, h))
        h, x, own = h[order], x[order], own[order]
        heads = np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (x[1:] != x[:-1]))))
        later = np.empty(len(h), bool)
        later[order] = own > np.repeat(own[heads], np.diff(np.append(heads, len(h))))
        return _reply(rows, n, later, 1)

    earlier = asked_runs.groupBy("bucket").applyInArrow(first_seen, "chunk long, step int, place long, n long, bits binary")

    def cut(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("id")
        if right.num_rows:
            c = _with_candidates(left, right)
            c.runs(buckets)
            known = _replies(right.filter(pa.compute.equal(right.column("step"), 1)), len(c.run_heads))
            group = np.cumsum(c.run_new) - 1
            gone = c.run_at[known[group] | (c.owner > c.owner[c.run_heads][group])] if len(c.run_at) else c.run_at
            edge = np.zeros(len(c.words) + 1, np.int64)
            np.add.at(edge, gone, 1)
            np.add.at(edge, gone + window, -1)
            covered, firsts = np.cumsum(edge[:-1]) > 0, c.firsts
        n, removed, kept = [], [], []
        for k, text in enumerate(left.column("text").combine_chunks().fill_null("").cast(pa.large_binary())):
            words, spans = text.as_py().split(), []
            n.append(len(words))
            if right.num_rows and (mask := covered[firsts[k] : firsts[k + 1]]).any():
                ends = np.flatnonzero(np.diff(np.concatenate(([0], mask.view(np.int8), [0])))).tolist()
                spans = [{"start": a, "end": b} for a, b in zip(ends[::2], ends[1::2], strict=True)]
                parts, at = [], 0
                for s in spans:
                    parts += words[at : s["start"]]
                    at = s["end"]
                words = parts + words[at:]
            removed.append(spans)
            kept.append(b" ".join(words).decode())
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        return pa.table([left.column("id").combine_chunks(), pa.array(n, pa.int64()), pa.array(removed, kind), pa.array(kept, pa.string()), left.column("copies").combine_chunks()], names=["id", "n_words", "removed", "kept_text", "copies"])

    done = texts.groupBy("chunk").cogroup(live.unionByName(earlier).groupBy("chunk")).applyInArrow(cut, _RESULT)
    done = done.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).drop("copies", "copy")
    nameless = rows.where("id IS NULL").select(
        "id", n_words(F.col("text")).alias("n_words"), F.array().cast("array<struct<start:long,end:long>>").alias("removed"),
        F.array_join(F.filter(F.split(F.coalesce("text", F.lit("")), BLANK_RE), lambda w: w != ""), " ").alias("kept_text"),
    )
    return done.unionByName(nameless).withColumnRenamed("id", id_col)


def _table(chunk: int, rows: list[tuple], names: tuple[str, ...], kinds: tuple) -> pa.Table:
    cols = list(zip(*rows, strict=True)) if rows else [()] * len(names)
    return pa.table([pa.array([chunk] * len(rows), pa.int64()), *[pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)]], names=["chunk", *names])


def _reply(rows: pa.Table, n: list[int], bits: np.ndarray, step: int) -> pa.Table:
    """A bucket's answer to each chunk that has a bit set."""
    out, at = [], 0
    for k, place, chunk in zip(n, rows.column("place").to_pylist(), rows.column("chunk").to_pylist(), strict=True):
        if bits[at : at + k].any():
            out.append((chunk, step, place, k, _bits(bits[at : at + k])))
        at += k
    cols = list(zip(*out, strict=True)) if out else [()] * 5
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
    return pa.table([pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)], names=["chunk", "step", "place", "n", "bits"])
