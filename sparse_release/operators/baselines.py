"""What the summaries are compared with: full noisy hierarchies, and synthetic data from a Dirichlet-multinomial model."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.prf import draw, uniform
from .hierarchy import hier_release
from .summaries import Plan, full_geometric


def full_dyadic(cells: DataFrame, h: int, plan: Plan) -> DataFrame:
    """Every node of the tree with noise."""
    return hier_release(cells, h, plan, lambda c, p: full_geometric(c, p).selectExpr("*", "CAST(value AS DOUBLE) AS weight"))


def full_haar(cells: DataFrame, h: int, plan: Plan) -> DataFrame:
    """Every Haar coefficient with noise."""
    return hier_release(cells, h, plan, lambda c, p: full_geometric(c, p).selectExpr("*", "CAST(value AS DOUBLE) AS weight"), "haar")


def haar_weighted(cells: DataFrame, h: int, eps: float, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """Haar means with Laplace noise by level: a coefficient's noise shrinks with its support, so that each level costs the same share of the budget. Told in sums, as the
    other hierarchies are, every level has noise of one scale (levels over budget): a mean's scale times its support is the same for all."""
    from .hierarchy import haar

    grid = cells.sparkSession.range(1 << h).selectExpr("id AS cell_id")
    from .hierarchy import haar_of

    level, pos = haar_of(h)
    nodes = grid.selectExpr(f"CAST({level} AS INT) AS level", f"CAST({pos} AS BIGINT) AS pos").join(haar(cells, h), ["level", "pos"], "left")
    support = f"CASE WHEN level = {h + 1} THEN {float(1 << h)!r}D ELSE CAST(shiftleft(1L, level) AS DOUBLE) END"
    half = f"({uniform(seed, 'haar', 'level', 'pos', mode=mode)} - 0.5D)"
    noise = f"(-signum({half}) * ln(1D - 2D * abs({half}))) * {float(h + 1)!r}D / ({float(eps)!r}D * ({support}))"
    return nodes.selectExpr("level", "pos", f"(coalesce(v, 0) / ({support}) + {noise}) * ({support}) AS weight")


def pseudo_count(n_out: int, eps: float) -> float:
    """The least prior count of a cell under which n_out draws keep the guarantee without exceptions."""
    return n_out / math.expm1(eps)


def urn(rng: np.random.Generator, rows: int, prior: float, radix: int, at: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places and how many of so many rows fall there, under a multinomial whose weights are Dirichlet with the prior for each place and counts v at some."""
    ups = np.cumsum(v)
    total = int(ups[-1]) if len(ups) else 0
    mass, order = prior * radix + total, np.arange(rows)
    place = rng.integers(0, radix, rows)
    of_counts = rng.random(rows) * mass >= prior * radix
    if total and of_counts.any():
        place[of_counts] = at[np.searchsorted(ups, rng.integers(0, total, int(of_counts.sum())), side="right")]
    source = np.where(rng.random(rows) * (mass + order) < mass, order, (rng.random(rows) * order).astype(np.int64))  # the row that it repeats, or itself
    while (source[source] != source).any():
        source = source[source]
    return np.unique(place[source], return_counts=True)


def dirichlet_synthetic(cells: DataFrame, group_radix: int, other_radix: int, eps: float, delta: float, per_group: int, seed: str | int = 1, mode: str = "md5", by_last: bool = True) -> DataFrame:
    """Synthetic rows for each group (the last dimension if by_last): posterior weights from counts and a common prior, a multinomial draw of as many rows as asked.

    The draws of weights and rows are made together, as Polya's urn: each row is new, from the prior or the counts, or repeats an earlier one; that has the same law, and costs
    what the counts and the rows cost, not the other dimension.

    Illustrative: pseudo_count is what a pure guarantee asks for; that a prior lowered by delta's fourth root keeps one but for a chance delta is not proved here. A group's
    counts and rows lie in one task."""
    spark = cells.sparkSession
    prior = max(1.0 / other_radix, pseudo_count(per_group, eps) * delta ** (1 / 4))
    group, other = (f"cell_id % {group_radix}", f"cell_id div {group_radix}") if by_last else (f"cell_id div {other_radix}", f"cell_id % {other_radix}")
    seeds = spark.range(group_radix).selectExpr("id AS g", f"{draw(seed, 'dirichlet', 'id', mode=mode)} AS s")
    rows = cells.selectExpr(f"{group} AS g", f"{other} AS o", "CAST(v AS BIGINT) AS v")

    def draws(one: pd.DataFrame, have: pd.DataFrame) -> pd.DataFrame:
        rng, g = np.random.default_rng(int(one["s"].iloc[0])), int(one["g"].iloc[0])
        at, got = urn(rng, per_group, prior, other_radix, have["o"].to_numpy(np.int64), have["v"].to_numpy(np.int64))
        return pd.DataFrame({"cell_id": at * group_radix + g if by_last else g * other_radix + at, "value": got})

    out = seeds.groupBy("g").cogroup(rows.groupBy("g")).applyInPandas(draws, "cell_id long, value long")
    return out.withColumn("weight", F.col("value").cast("double"))


def exponential_top1(candidates: DataFrame, eps: float, sensitivity: float = 1.0, seed: str | int = 1, mode: str = "md5") -> DataFrame:
    """The candidate (key, score) chosen by the exponential mechanism, as the largest of scores with Gumbel noise."""
    g = f"-ln(-ln({uniform(seed, 'gumbel', 'key', mode=mode)}))"
    noisy = candidates.selectExpr("key", "score", f"CAST(score AS DOUBLE) * {eps / (2 * sensitivity)!r}D + {g} AS _n")
    return noisy.orderBy(F.col("_n").desc(), "key").limit(1).select("key", "score")
