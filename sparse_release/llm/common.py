"""What the operators share: the word rule, durable cuts of lineage, packed word arithmetic."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterable
from functools import reduce

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of characters other than the six ASCII blanks (Java regex).
WORD_RE = r"[^ \t-\r]+"
BLANK_RE = r"[ \t-\r]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where the session names none and runs in one process (tests)."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="ckpt-"))
    return sc.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """df, computed once and kept in the shared folder, so that a lost executor costs no recomputation."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def durable_table(df: DataFrame) -> DataFrame:
    """As durable, but as compressed Parquet: for wide rows."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Names like these that no column of df has (column names are compared without case)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


#: A key counts as hot if it has over 1 / HOT_KEYS of a table's rows, and HOT_LEAST at least; so there are never more than HOT_KEYS of them.
HOT_KEYS, HOT_LEAST = 10_000, 256


def hot_keys(rows: DataFrame, keys: list[str], least: int = HOT_LEAST) -> DataFrame | None:
    """The hot values of these columns, HOT_KEYS at most; None if there are none."""
    counts = rows.groupBy(*keys).count()
    n = rows.count()
    if n <= least:
        return None
    found = counts.where(F.col("count") > max(least, -(-n // HOT_KEYS))).drop("count")
    hot = found.collect()
    return rows.sparkSession.createDataFrame(hot, found.schema) if hot else None


def join_unique(large: DataFrame, small: DataFrame, on: dict[str, str], how: str = "inner", least: int = HOT_LEAST) -> DataFrame:
    """large joined (inner or left) with small, which has one row for each key at most; nulls equal nulls. on: columns of large to columns of small, no name in both.
    The rows that small has for hot keys of large, HOT_KEYS at most, are broadcast, so no task gets all of a hot key's rows."""
    alike = lambda names: _all(F.col(a).eqNullSafe(F.col(b)) for a, b in names.items())
    hot = hot_keys(large, [*on], least)
    if hot is None:
        return large.join(small, alike(on), how)
    names = {k: f"hot_{j}" for j, k in enumerate(on)}
    hot = F.broadcast(hot.toDF(*names.values()))
    few = small.join(hot, _all(F.col(b).eqNullSafe(F.col(names[a])) for a, b in on.items()), "left_semi")
    top = large.join(hot, alike(names), "left_semi").join(F.broadcast(few), alike(on), how)
    return large.join(hot, alike(names), "left_anti").join(small, alike(on), how).unionByName(top)


def _all(conditions: Iterable[Column]) -> Column:
    return reduce(lambda a, b: a & b, conditions)


def n_words(text) -> Column:
    """Count of words of a text column; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD_RE)), F.lit(0)).cast("long")


_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection on 64-bit words that spreads every bit (public-domain finaliser)."""
    x = x.astype(np.uint64)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def word_spans(buf: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of texts laid end to end in buf (bytes; text k is buf[bounds[k]:bounds[k+1]]): word starts, word ends, first word of each text."""
    solid = ~_BLANK[buf]
    flank = np.empty(len(buf) + 1, bool)
    flank[0] = flank[-1] = False
    flank[1:-1] = solid[1:] & ~solid[:-1]
    if len(buf):
        flank[0] = solid[0]
    inner = bounds[(bounds < len(buf)) & (bounds >= 0)]
    flank[inner] = solid[inner]  # a text begins a new word
    starts = np.flatnonzero(flank[: len(buf)])
    stop = np.zeros(len(buf) + 1, bool)
    stop[:-1] = ~solid
    stop[bounds] = True
    stops = np.flatnonzero(stop)
    ends = stops[np.searchsorted(stops, starts, side="right")] if len(starts) else starts
    return starts, ends, np.searchsorted(starts, bounds)


#: Words of up to so many bytes are hashed and compared in vectorised steps of eight bytes, longer ones each by itself.
SHORT_WORD = 64
_FIRST_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(9)], np.uint64)


def _eights(buf: np.ndarray) -> np.ndarray:
    """The eight bytes from each place of buf on (zeros beyond its end), as little-endian numbers."""
    padded = np.concatenate((buf, np.zeros(8, np.uint8)))
    return np.ndarray(len(buf) + 1, "<u8", buffer=padded.tobytes(), strides=(1,))


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit hash of each word: eight bytes at a time are mixed into a state that starts from length and seed. Words of up to eight bytes and equal length never share one."""
    n, eights = ends - starts, _eights(buf)
    out = mix64(n.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))
    live, at = np.flatnonzero(n <= SHORT_WORD), 0
    while len(live):
        left = n[live] - at
        out[live] = mix64(out[live] ^ (eights[starts[live] + at] & _FIRST_BYTES[np.minimum(left, 8)]))
        live, at = live[left > 8], at + 8
    for k in np.flatnonzero(n > SHORT_WORD).tolist():
        out[k] = xxhash.xxh64_intdigest(buf[starts[k] : ends[k]].tobytes(), seed)
    return out


def spelled_alike(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Whether each word has the very bytes of word other[k]."""
    n, eights = ends - starts, _eights(buf)
    same = n == n[other]
    live, at = np.flatnonzero(same & (n <= SHORT_WORD)), 0
    while len(live):
        left = n[live] - at
        differ = (eights[starts[live] + at] ^ eights[starts[other[live]] + at]) & _FIRST_BYTES[np.minimum(left, 8)]
        same[live[differ != 0]] = False
        live, at = live[(left > 8) & (differ == 0)], at + 8
    for k in np.flatnonzero(same & (n > SHORT_WORD)).tolist():
        j = other[k]
        same[k] = k == j or buf[starts[k] : ends[k]].tobytes() == buf[starts[j] : ends[j]].tobytes()
    return same


def window_hashes(words: np.ndarray, firsts: np.ndarray, width: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of `width` words that lie in one text; and each run's first word. firsts: first word of each text, then the end."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    factor, total = np.uint64((0xD6E8FEB86659FD93 + 2 * seed) & 0xFFFFFFFFFFFFFFFF | 1), np.zeros(n, np.uint64)
    for k in range(width):
        total *= factor
        total += words[k : k + n]
    ok = np.ones(len(words) + 1, bool)
    for k in range(1, width):
        ok[np.maximum(firsts[1:] - k, 0)] = False  # a run from here would leave its text
    at = np.flatnonzero(ok[:n])
    return mix64(total[at]), at
