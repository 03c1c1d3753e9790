"""Measures of accuracy and cost."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def errors(truth: DataFrame, estimate: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, size, truth, estimate, abs_error, rel_error); relative errors are null where the truth is 0."""
    sizes = queries.select("qid", "size").distinct()
    rows = sizes.join(truth.select("qid", F.col("truth").cast("double").alias("truth")), "qid", "left").join(estimate.select("qid", "estimate"), "qid", "left").fillna({"truth": 0.0, "estimate": 0.0})
    gap = F.abs(F.col("truth") - F.col("estimate"))
    return rows.select("qid", "size", "truth", "estimate", gap.alias("abs_error"), F.when(F.col("truth") != 0, gap / F.abs("truth")).alias("rel_error"))


def by_size(rows: DataFrame, *keys: str) -> DataFrame:
    """For each size: queries, those with truth 0, mean absolute error, median relative error, bias and its variance."""
    gap = F.col("estimate") - F.col("truth")
    return rows.groupBy(*keys, "size").agg(
        F.count(F.lit(1)).alias("n_queries"), F.sum((F.col("truth") == 0).cast("long")).alias("n_zero_truth"), F.round(F.avg("abs_error"), 6).alias("abs_error"),
        F.round(F.median("rel_error"), 9).alias("median_rel_error"), F.round(F.avg(gap), 6).alias("bias"), F.round(F.var_samp(gap), 6).alias("gap_variance"),
    )


def crossing(a: DataFrame, b: DataFrame) -> DataFrame:
    """The least size at which scheme b's mean absolute error is below a's (null if none): size."""
    both = a.select("size", F.col("abs_error").alias("ea")).join(b.select("size", F.col("abs_error").alias("eb")), "size")
    return both.agg(F.min(F.when(F.col("eb") < F.col("ea"), F.col("size"))).alias("size"))


def gain(before: DataFrame, after: DataFrame) -> DataFrame:
    """(size, gain): share of the error that a change took away."""
    both = before.select("size", F.col("abs_error").alias("e0")).join(after.select("size", F.col("abs_error").alias("e1")), "size")
    return both.select("size", F.when(F.col("e0") != 0, 1 - F.col("e1") / F.col("e0")).alias("gain"))


def composition(summary: DataFrame, cells: DataFrame) -> DataFrame:
    """How many rows of a summary stand for occupied and for empty cells. For tests only: never publish it."""
    mark = summary.join(cells.select("cell_id", F.lit(1).alias("own")), "cell_id", "left")
    return mark.agg(F.coalesce(F.sum(F.coalesce("own", F.lit(0))), F.lit(0)).cast("long").alias("occupied"), F.coalesce(F.sum(1 - F.coalesce("own", F.lit(0))), F.lit(0)).cast("long").alias("empty"))


def value_histogram(summary: DataFrame, cap: int = 1 << 30) -> DataFrame:
    """(value, n) of a summary, for comparing laws."""
    return summary.groupBy(F.greatest(F.least(F.col("value"), F.lit(cap)), F.lit(-cap)).alias("value")).agg(F.count(F.lit(1)).alias("n"))


def sizes(n_out: int, n: int, m: int) -> dict[str, float]:
    """Output rows, and their ratio to occupied and to all cells."""
    return {"rows": n_out, "per_occupied": n_out / max(n, 1), "per_cell": n_out / m}


def throughput(df: DataFrame, n: int) -> dict[str, float]:
    """Seconds to make a release, and occupied input cells per second."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    took = time.perf_counter() - began
    return {"seconds": took, "cells_per_second": n / took}
