"""Functions for SQL sessions: draws, noise, and the dyadic cover as a table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .prf import BITS


def dyadic_nodes(lo: int, hi: int, h: int) -> Iterator[tuple[int, int]]:
    """The fewest nodes (level, pos) that make up [lo, hi)."""
    lo, hi = max(lo, 0), min(hi, 1 << h)
    for level in range(h + 1):
        if lo >= hi:
            return
        if lo & 1:
            yield level, lo
            lo += 1
        if hi & 1:
            hi -= 1
            yield level, hi
        lo, hi = lo >> 1, hi >> 1


@udtf(returnType="level int, pos bigint")
class DyadicCover:
    def eval(self, lo: int, hi: int, h: int) -> Iterator[tuple[int, int]]:
        yield from dyadic_nodes(lo, hi, h)


def register(spark: SparkSession) -> None:
    """prf_uniform(seed, tag, key), geo_noise(alpha, seed, key) and noise_moments as SQL functions, evaluated by the engine itself; dyadic_cover(lo, hi, h) as a table function."""
    digest = "CAST(conv(substring(md5(CAST(concat_ws(':', seed, tag, k) AS BINARY)), 1, 13), 16, 10) AS BIGINT)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION prf_uniform(seed STRING, tag STRING, k STRING) RETURNS DOUBLE RETURN ({digest} + 0.5D) / {float(1 << BITS)!r}D")
    step = "CAST(floor(ln(prf_uniform(seed, '{}', k)) / ln(alpha)) AS BIGINT)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION geo_noise(alpha DOUBLE, seed STRING, k STRING) RETURNS BIGINT RETURN {step.format('noise+')} - {step.format('noise-')}")
    spark.udtf.register("dyadic_cover", DyadicCover)
