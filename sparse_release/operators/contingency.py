"""Sparse contingency counts and what is said of them."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import alpha_of, geometric
from ..functions.prf import uniform
from .domain import Domain


def contingency(df: DataFrame, domain: Domain, measure: Column | None = None) -> DataFrame:
    """Occupied cells: cell_id and v, a count or the sum of a measure. One shuffle, after partial counts."""
    rows = domain.encode(df)
    total = F.count(F.lit(1)) if measure is None else F.sum(measure)
    return rows.groupBy("cell_id").agg(total.alias("v")).where("v != 0")


def count_cube(df: DataFrame, dims: list[str], sets: list[list[str]] | None = None, spark_sql: str = "count(*)") -> DataFrame:
    """Counts for several groupings at once (all subsets if none are named): dims (null where not grouped), grouping (its bits), v. An individual counts in every set."""
    view = f"cube_{abs(hash((tuple(dims), str(sets))))}"
    df.createOrReplaceTempView(view)
    by = f"CUBE ({', '.join(dims)})" if sets is None else f"{', '.join(dims)} GROUPING SETS ({', '.join('(' + ', '.join(s) + ')' for s in sets)})"
    return df.sparkSession.sql(f"SELECT {', '.join(dims)}, CAST(grouping_id({', '.join(dims)}) AS BIGINT) AS grouping, {spark_sql} AS v FROM {view} GROUP BY {by}")


def density(cells: DataFrame, m: int) -> DataFrame:
    """One row: m, n, rho, blow_up (1 / rho), total, mean, sd, share of counts up to 2. For the owner; noise it before it is published."""
    n, v = F.count(F.lit(1)), F.col("v")
    return cells.agg(
        F.lit(m).cast("long").alias("m"), n.alias("n"), F.round(n / F.lit(float(m)), 9).alias("rho"), F.round(F.lit(float(m)) / n, 6).alias("blow_up"), F.coalesce(F.sum(v), F.lit(0)).cast("long").alias("total"),
        F.round(F.avg(v), 6).alias("mean"), F.round(F.stddev_samp(v), 6).alias("sd"), F.round(F.avg((v <= 2).cast("double")), 6).alias("share_to_2"),
    )


def bound_contributions(df: DataFrame, person: str, rows: int, key: str, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """At most `rows` rows of each person, drawn by a keyed hash of `key`, so that sensitivity is `rows`. Rows are ranked by partial top lists, not gathered whole."""
    drawn = df.withColumn("_u", F.expr(uniform(seed, "bound", person, key, mode=mode)))
    rank = F.row_number().over(Window.partitionBy(person).orderBy("_u", key))
    return drawn.withColumn("_rank", rank).where(F.col("_rank") <= rows).drop("_rank", "_u")


def private_totals(cells: DataFrame, eps: float, release: str, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """n and total with noise; half the budget each."""
    alpha = alpha_of(eps / 2)
    sums = cells.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("total"))
    return sums.selectExpr(*(f"greatest({c} + {geometric(alpha, seed, repr(release), tag=f'total-{c}', mode=mode)}, 0) AS {c}" for c in ("n", "total")))


def blocks_of(m: int, blocks: int) -> int:
    """Cells of a block, if [0, m) is cut in so many."""
    return max(1, math.ceil(m / blocks))
