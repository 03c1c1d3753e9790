"""Answers from a summary: points, ranges, subsets, predicates, marginals, heavy cells; and how sure they are."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .domain import Domain

#: Cells of a block for prefix sums and range joins.
BLOCK = 1 << 12
#: Height of the hierarchy over groups of blocks: 2^(12 + 12 + TOP) cells.
TOP = 39


def est_point(summary: DataFrame, cells: DataFrame, absent: float = 0.0) -> DataFrame:
    """(cell_id, estimate) for asked cells: released values as they are, closer for single cells than unbiased weights."""
    return cells.select("cell_id").join(summary.select("cell_id", F.col("value").cast("double").alias("estimate")), "cell_id", "left").fillna({"estimate": absent})


def est_range(summary: DataFrame, queries: DataFrame, weight: str = "weight", absent: float = 0.0, block: int = BLOCK) -> DataFrame:
    """(qid, estimate) for ranges [lo, hi): a range is the blocks it covers whole, from block sums added up in order, and the cells at its two ends, found by equal
    block numbers. No range is compared with every row."""
    rows = summary.selectExpr("cell_id", f"CAST({weight} AS DOUBLE) AS w", f"cell_id div {block} AS b")
    return est_blocks(rows, rows.groupBy("b").agg(F.sum("w").alias("w"), F.count(F.lit(1)).cast("double").alias("n")), queries, absent, block)


def ends_of(queries: DataFrame, block: int = BLOCK) -> DataFrame:
    """Numbers (b) of the blocks in which ranges [lo, hi) begin or end."""
    return queries.where("lo < hi").selectExpr(f"explode(array(CAST(lo AS BIGINT) div {block}, (CAST(hi AS BIGINT) - 1) div {block})) AS b").distinct()


def est_blocks(rows: DataFrame, sums: DataFrame, queries: DataFrame, absent: float = 0.0, block: int = BLOCK) -> DataFrame:
    """As est_range, from the rows (cell_id, w, b) of the blocks that ends_of names, others do not matter, and sums (b, w, n) of all blocks."""
    q = queries.selectExpr("qid", "CAST(lo AS BIGINT) AS lo", "CAST(hi AS BIGINT) AS hi")
    ends = q.selectExpr("qid", "lo", "hi", f"explode(array_distinct(array(lo div {block}, (hi - 1) div {block}))) AS b").where("lo < hi")
    at_ends = ends.join(rows, "b").where("cell_id >= lo AND cell_id < hi").groupBy("qid").agg(F.sum("w").alias("w"), F.count(F.lit(1)).cast("double").alias("n"))
    # prefix sums over blocks in two levels, so that no task orders all blocks
    two = sums.withColumn("g", F.expr(f"b div {block}"))
    heads = two.groupBy("g").agg(F.sum("w").alias("w"), F.sum("n").alias("n"))
    inner = q.selectExpr("qid", f"lo div {block} + 1 AS b0", f"(hi - 1) div {block} AS b1").where("b0 < b1")
    fine = inner.selectExpr("qid", "b0", "b1", f"explode(array_distinct(array(b0 div {block}, (b1 - 1) div {block}))) AS g").join(two, "g").where("b >= b0 AND b < b1").groupBy("qid").agg(F.sum("w").alias("w"), F.sum("n").alias("n"))
    # whole groups of blocks by their dyadic sums: a few rows for a query, however long it is
    from .hierarchy import dyadic_cover

    tree = heads.selectExpr(f"explode(sequence(0, {TOP})) AS level", "g", "w", "n").selectExpr("level", "shiftright(g, level) AS pos", "w", "n").groupBy("level", "pos").agg(F.sum("w").alias("w"), F.sum("n").alias("n"))
    wide = inner.selectExpr("qid", f"b0 div {block} + 1 AS lo", f"(b1 - 1) div {block} AS hi").where("lo < hi")
    coarse = dyadic_cover(wide, TOP).join(tree, ["level", "pos"]).groupBy("qid").agg(F.sum("w").alias("w"), F.sum("n").alias("n"))
    total = at_ends.unionByName(fine).unionByName(coarse).groupBy("qid").agg(F.sum("w").alias("w"), F.sum("n").alias("n"))
    return q.join(total, "qid", "left").selectExpr("qid", f"coalesce(w, 0D) + {float(absent)!r}D * (hi - lo - coalesce(n, 0D)) AS estimate")


def est_dense(noisy: DataFrame, queries: DataFrame, clamp: bool = False) -> DataFrame:
    """Range answers from all noisy cells (cell_id, value): signed for large ranges, where noise cancels; clamped at 0 for small ones."""
    return est_range(noisy.selectExpr("cell_id", "greatest(value, 0) AS value") if clamp else noisy, queries, "value")


def est_subset(summary: DataFrame, members: DataFrame, weight: str = "weight", absent: float = 0.0) -> DataFrame:
    """(qid, estimate) for sets of cells (qid, cell_id); a cell named twice counts once."""
    asked = members.select("qid", "cell_id").distinct()
    return asked.join(summary.select("cell_id", F.col(weight).cast("double").alias("w")), "cell_id", "left").groupBy("qid").agg(F.sum(F.coalesce("w", F.lit(absent))).alias("estimate"))


def est_where(summary: DataFrame, domain: Domain, condition: str, weight: str = "weight") -> DataFrame:
    """One row, estimate: the sum over cells whose decoded coordinates satisfy a condition."""
    return domain.decode(summary).where(condition).agg(F.coalesce(F.sum(F.col(weight).cast("double")), F.lit(0.0)).alias("estimate"))


def est_group_by(summary: DataFrame, domain: Domain, dims: list[str], weight: str = "weight") -> DataFrame:
    """Marginals over decoded dimensions."""
    return domain.decode(summary).groupBy(*dims).agg(F.sum(F.col(weight).cast("double")).alias("estimate"))


def est_top(summary: DataFrame, k: int, weight: str = "weight") -> DataFrame:
    """The k heaviest cells, ties to the smaller."""
    return summary.orderBy(F.col(weight).desc(), "cell_id").limit(k)


def est_variance(summary: DataFrame, members: DataFrame, tau: float, noise_variance: float = 0.0) -> DataFrame:
    """(qid, variance): an unbiased estimate of the sampling variance of subset sums, and the noise of all cells asked for."""
    asked = members.select("qid", "cell_id").distinct().join(summary.select("cell_id", "value"), "cell_id", "left")
    own = F.when(F.col("value").isNull(), 0.0).otherwise(tau * F.greatest(F.lit(0.0), F.lit(float(tau)) - F.abs("value")))
    return asked.groupBy("qid").agg((F.sum(own) + noise_variance * F.count(F.lit(1))).alias("variance"))


def exact_range(cells: DataFrame, queries: DataFrame) -> DataFrame:
    return est_range(cells, queries, "v").withColumnRenamed("estimate", "truth")


def exact_subset(cells: DataFrame, members: DataFrame) -> DataFrame:
    return est_subset(cells, members, "v").withColumnRenamed("estimate", "truth")


def prefix_sums(cells: DataFrame, v: str = "v", block: int = BLOCK) -> DataFrame:
    """cell_id and the sum of all cells up to it, in two levels: within blocks, and over block sums."""
    rows = cells.selectExpr("cell_id", f"{v} AS v", f"cell_id div {block} AS b")
    within = rows.withColumn("p", F.sum("v").over(Window.partitionBy("b").orderBy("cell_id")))
    heads = rows.groupBy("b").agg(F.sum("v").alias("s")).withColumn("g", F.expr(f"b div {block}"))
    tops = heads.groupBy("g").agg(F.sum("s").alias("s"))
    before_top = tops.withColumn("t", F.coalesce(F.sum("s").over(Window.orderBy("g").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("g", "t")  # a row for each block^2 cells
    before = heads.withColumn("h", F.coalesce(F.sum("s").over(Window.partitionBy("g").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).join(before_top, "g")
    return within.join(before.select("b", "h", "t"), "b").selectExpr("cell_id", "p + h + t AS prefix")
