"""Synthetic counts and query workloads, as plans over spark.range with hashed draws; and the same as a Python data source, batch and stream."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from ..functions.prf import draw, uniform
from ..operators.summaries import top_priorities


def _normal(seed, tag: str, key: str, mode: str) -> str:
    return f"sqrt(-2D * ln({uniform(seed, tag + 'a', key, mode=mode)})) * cos({2 * math.pi!r}D * {uniform(seed, tag + 'b', key, mode=mode)})"


def synthetic(spark: SparkSession, m: int, rho: float = 0.1, mean: float = 100, sd: float = 20, seed: str | int = 1, places: str = "uniform", mode: str = "xxhash64", keys: DataFrame | None = None) -> DataFrame:
    """(cell_id, v): rho * m occupied cells with rounded normal counts of at least 1. places: uniform (exactly that many), or clustered (about 20 centres). keys: a table's
    distinct keys (id), m of them; uniform places are drawn among these, and for clustered ones each key is a draw of a place (all that are met)."""
    n = round(rho * m)
    value = f"CAST(greatest(1, round({mean!r}D + {sd!r}D * {_normal(seed, 'size', 'cell_id', mode)})) AS BIGINT) AS v"
    if places == "uniform":
        ranked = (spark.range(m) if keys is None else keys).selectExpr("id AS cell_id", f"{draw(seed, 'place', 'id', mode=mode)} AS priority")
        return top_priorities(ranked, n)[0].selectExpr("cell_id", value)
    # draws around 20 centres, with enough spare ones that n distinct cells are left
    center = f"CAST(floor({uniform(seed, 'center', 'k', mode=mode)} * {m}D) AS BIGINT)"
    drawn = (spark.range(math.ceil(n * 1.6) + 64) if keys is None else keys).selectExpr("id", f"{draw(seed, 'which', 'id', mode=mode)} % 20 AS k")
    at = drawn.selectExpr("id", f"pmod({center} + CAST(round({m * 0.006!r}D * {_normal(seed, 'spread', 'id', mode)}) AS BIGINT), {m}) AS cell_id")
    if keys is not None:
        return at.select("cell_id").distinct().selectExpr("cell_id", value)
    first = at.groupBy("cell_id").agg(F.min("id").alias("id")).selectExpr("cell_id", "-CAST(id AS DOUBLE) AS priority")
    return top_priorities(first, n)[0].selectExpr("cell_id", value)


def range_queries(spark: SparkSession, m: int, sizes: list[int], per_size: int = 400, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """(qid, size, lo, hi) of ranges [lo, hi) at drawn places."""
    fit = [s for s in sizes if s <= m]
    sized = spark.range(per_size).selectExpr("id", f"explode(array({', '.join(f'{s}L' for s in fit)})) AS size") if fit else spark.range(0).selectExpr("id", "id AS size")
    lo = f"CAST(floor({uniform(seed, 'range', 'size', 'id', mode=mode)} * CAST({m} - size + 1 AS DOUBLE)) AS BIGINT)"
    return sized.selectExpr("size * 1000000L + id AS qid", "size", f"{lo} AS lo").selectExpr("qid", "size", "lo", "lo + size AS hi")


def subset_queries(spark: SparkSession, m: int, sizes: list[int], per_size: int = 20, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """(qid, size, cell_id) of sets of distinct cells, drawn by a bijection of the domain for each query, so none is drawn twice."""
    fit = [s for s in sizes if s <= m]
    q = spark.range(per_size).selectExpr("id", f"explode(array({', '.join(f'{s}L' for s in fit)})) AS size")
    # steps of an odd multiplier prime to m walk through every cell once
    primes = [p for p in (1_000_003, 1_299_709, 7_368_787, 15_485_863, 32_452_843) if m % p]
    start, step = draw(seed, "subset", "size", "id", mode=mode), f"element_at(array({', '.join(f'{p}L' for p in primes)}), CAST({draw(seed, 'step', 'size', 'id', mode=mode)} % {len(primes)} AS INT) + 1)"
    return q.selectExpr("size * 1000000L + id AS qid", "size", f"{start} % {m} AS start", f"{step} AS step", "explode(sequence(0L, size - 1)) AS k").selectExpr("qid", "size", f"pmod(start + (k * step) % {m}, {m}) AS cell_id")


class SyntheticSource(DataSource):
    """spark.read.format("sparse_release_synthetic").option("m", ...): occupied cells with uniform places and counts; options m, rho, mean, sd, seed, parts."""

    @classmethod
    def name(cls) -> str:
        return "sparse_release_synthetic"

    def schema(self) -> str:
        return "cell_id long, v long"

    def reader(self, schema):
        return _Reader(dict(self.options))

    def simpleStreamReader(self, schema):
        return _Stream(dict(self.options))


def _rows(options: dict[str, str], part: int, parts: int):
    import numpy as np

    m, rho = int(options.get("m", 1_000_000)), float(options.get("rho", 0.1))
    rng = np.random.default_rng((int(options.get("seed", 1)), part))
    lo, hi = m * part // parts, m * (part + 1) // parts
    at = lo + np.flatnonzero(rng.random(hi - lo) < rho) if hi - lo <= 1 << 22 else np.unique(rng.integers(lo, hi, round(rho * (hi - lo))))
    v = np.maximum(1, np.rint(rng.normal(float(options.get("mean", 100)), float(options.get("sd", 20)), len(at)))).astype(int)
    return zip(at.tolist(), v.tolist(), strict=True)


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.options = options

    def partitions(self):
        return [InputPartition(k) for k in range(int(self.options.get("parts", 4)))]

    def read(self, partition):
        yield from _rows(self.options, partition.value, int(self.options.get("parts", 4)))


class _Stream(SimpleDataSourceStreamReader):
    """One part of the domain for each batch, until all are read."""

    def __init__(self, options: dict[str, str]) -> None:
        self.options, self.parts = options, int(options.get("parts", 4))

    def initialOffset(self) -> dict:
        return {"part": 0}

    def read(self, start: dict):
        part = start["part"]
        if part >= self.parts:
            return iter([]), start
        return iter(list(_rows(self.options, part, self.parts))), {"part": part + 1}

    def readBetweenOffsets(self, start: dict, end: dict):
        for part in range(start["part"], end["part"]):
            yield from _rows(self.options, part, self.parts)

    def commit(self, end: dict) -> None:
        pass
