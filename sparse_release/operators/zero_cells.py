"""Which empty cells a release keeps: a binomial number at uniform places, drawn without visiting the others. Three ways with one law.

skip: each block of cells walks over its empty cells in geometric gaps; plain SQL, so other engines can repeat it draw by draw.
block: each block draws its own binomial and that many places; the sum over blocks and their union have the law of the whole. Nothing is coordinated.
reject: draws places in the whole domain, drops repeats and occupied ones, and keeps the first k; the classical way, with two trips to the driver.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.prf import draw, uniform
from .contingency import blocks_of

#: Standard deviations that a block's walk is laid out beyond what it is expected to keep.
MARGIN = 12
#: Occupied and kept cells that a block should have; blocks at least; a block with CROWD times as many occupied ones is cut in SPLIT, again and again.
ROWS, LEAST_BLOCKS, CROWD, SPLIT = 200_000, 64, 4, 16


def walk_length(width: int, p: float) -> int:
    """Steps of a walk that passes the end of a block of so many empty cells, but for a chance below any that counts."""
    return math.ceil(width * p + MARGIN * math.sqrt(width * p) + 30)


def cut_blocks(cells: DataFrame, m: int, blocks: int) -> tuple[DataFrame, DataFrame]:
    """Blocks (block: a number, lo, size) that make up [0, m): equal ones, of which crowded ones are cut further; and occupied cells (cell_id, lo). What is crowded has more
    than a ten-thousandth of all occupied cells, so there are never many such at a time."""
    width, limit = blocks_of(m, blocks), CROWD * ROWS
    leaves = cells.sparkSession.range(math.ceil(m / width)).selectExpr("id AS block", f"id * {width} AS lo", f"least({width}, {m} - id * {width}) AS size")
    occupied = cells.selectExpr("cell_id", f"cell_id div {width} * {width} AS lo")
    if width <= limit:
        return leaves, occupied
    limit = max(limit, cells.count() // 10_000)
    while True:
        found = occupied.groupBy("lo").count().where(f"count > {limit}")
        hot = leaves.join(found, "lo").where("size > 1").selectExpr("lo", f"CAST(ceil(size / {SPLIT}) AS BIGINT) AS part").collect()
        if not hot:
            return leaves, occupied
        table = F.broadcast(cells.sparkSession.createDataFrame(hot, "lo long, part long"))
        pieces = "CASE WHEN part IS NULL THEN array(struct(block, lo, size)) ELSE transform(sequence(0L, (size - 1) div part), k -> struct(-1 - lo - k * part AS block, lo + k * part AS lo, least(part, size - k * part) AS size)) END"
        leaves = leaves.join(table, "lo", "left").selectExpr(f"explode({pieces}) AS x").select("x.*")
        occupied = occupied.join(table, "lo", "left").selectExpr("cell_id", "CASE WHEN part IS NULL THEN lo ELSE lo + (cell_id - lo) div part * part END AS lo")


def _skip(cells: DataFrame, m: int, p: float, seed, blocks: int, mode: str) -> DataFrame:
    leaves, occupied = cut_blocks(cells, m, blocks)
    by_place = Window.partitionBy("lo").orderBy("cell_id")
    # An occupied cell stands before the empty cell whose rank is its own place less the occupied ones before it.
    taken = occupied.withColumn("key", F.col("cell_id") - F.col("lo") - (F.row_number().over(by_place) - 1)).selectExpr("lo", "key", "1 AS taken", "CAST(NULL AS BIGINT) AS draw_no")
    # a gap longer than the block ends the walk, however long
    gap = "1" if p >= 1 else f"CAST(least(floor(ln({uniform(seed, 'gap', 'block', 'i', mode=mode)}) / {math.log1p(-p)!r}D), CAST(size AS DOUBLE)) AS BIGINT) + 1"
    steps = f"CAST(ceil(size * {p!r}D + {MARGIN} * sqrt(size * {p!r}D) + 30) AS BIGINT)" if p < 1 else "size"
    sizes = leaves.join(occupied.groupBy("lo").count(), "lo", "left").selectExpr("block", "lo", "size", "size - coalesce(count, 0) AS empty")
    walks = sizes.selectExpr("block", "lo", "size", "empty", f"explode(sequence(0L, {steps})) AS i").selectExpr("lo", "empty", "i", f"{gap} AS gap")
    ranked = walks.withColumn("key", F.sum("gap").over(Window.partitionBy("lo").orderBy("i")) - 1).where("key < empty").selectExpr("lo", "key", "0 AS taken", "lo + i AS draw_no")
    order = Window.partitionBy("lo").orderBy("key", F.col("taken").desc()).rowsBetween(Window.unboundedPreceding, 0)
    placed = taken.unionByName(ranked).withColumn("before", F.sum("taken").over(order))
    return placed.where("taken = 0").selectExpr("CAST(lo + key + before AS BIGINT) AS cell_id", "CAST(draw_no AS BIGINT) AS draw_no")


def _block(cells: DataFrame, m: int, p: float, seed, blocks: int, mode: str) -> DataFrame:
    leaves, occupied = cut_blocks(cells, m, blocks)
    seeds = leaves.selectExpr("lo", "size", f"{draw(seed, 'block', 'block', mode=mode)} AS s")

    def places(block: pd.DataFrame, taken: pd.DataFrame) -> pd.DataFrame:
        rng, lo = np.random.default_rng(int(block["s"].iloc[0])), int(block["lo"].iloc[0])
        at = np.sort(taken["cell_id"].to_numpy(np.int64)) - lo
        empty = int(block["size"].iloc[0]) - len(at)
        k = rng.binomial(empty, min(p, 1.0)) if empty > 0 else 0
        if 3 * k > empty:
            rank = np.sort(rng.permutation(empty)[:k])
        else:  # distinct ranks by drawing again for repeats, in memory of the order of k
            rank = np.empty(0, np.int64)
            while len(rank) < k:
                rank = np.unique(np.concatenate((rank, rng.integers(0, empty, k - len(rank)))))
        place = rank + np.searchsorted(at - np.arange(len(at)), rank, side="right")
        return pd.DataFrame({"cell_id": lo + place, "draw_no": lo + np.arange(len(place), dtype=np.int64)})

    return seeds.groupBy("lo").cogroup(occupied.groupBy("lo")).applyInPandas(places, "cell_id long, draw_no long")


def _reject(cells: DataFrame, m: int, p: float, seed, blocks: int, mode: str) -> DataFrame:
    spark, n = cells.sparkSession, cells.count()
    k = int(np.random.default_rng(int(spark.range(1).selectExpr(draw(seed, "k", "0", mode=mode)).first()[0])).binomial(m - n, min(p, 1.0))) if m > n else 0
    want = math.ceil(k * m / max(1, m - n) * 1.1) + 64
    while True:
        # one draw has 52 bits; large domains take two, so that every cell can be met, and all alike
        small = f"CAST(floor({uniform(seed, 'place', 'id', mode=mode)} * {m}D) AS BIGINT)"
        wide = f"CAST((CAST({draw(seed, 'place', 'id', mode=mode)} AS DECIMAL(38, 0)) * {1 << 52} + CAST({draw(seed, 'place-low', 'id', mode=mode)} AS DECIMAL(38, 0))) % {m} AS BIGINT)"
        drawn = spark.range(want).selectExpr("id AS draw_no", f"{small if m <= 1 << 32 else wide} AS cell_id")
        fresh = drawn.groupBy("cell_id").agg(F.min("draw_no").alias("draw_no")).join(cells.select("cell_id"), "cell_id", "left_anti")
        if fresh.count() >= k:
            # the kth draw number, found by a top list when k is small and by a count per range of draws otherwise
            width = max(1, want // 4096)
            counts = sorted((r["r"], r["count"]) for r in fresh.groupBy(F.expr(f"draw_no div {width}").alias("r")).count().collect())
            full, have = 0, 0
            for r, c in counts:
                if have + c > k:
                    break
                full, have = (r + 1) * width, have + c
            last = fresh.where(f"draw_no >= {full}").orderBy("draw_no").limit(k - have)
            return fresh.where(f"draw_no < {full}").unionByName(last).select("cell_id", "draw_no")
        want *= 2  # the same draws, and more


WAYS = {"skip": _skip, "block": _block, "reject": _reject}


def zero_cells(cells: DataFrame, m: int, p: float, seed: str | int, way: str = "skip", blocks: int | None = None, mode: str = "md5") -> DataFrame:
    """cell_id and draw_no (a number no other kept cell has) of the empty cells kept with chance p each. cells: the occupied ones, distinct. blocks: of the domain; by default
    as many as give each about ROWS cells, LEAST_BLOCKS at least (the draws depend on it, so it follows the data alone)."""
    if not 0 <= p <= 1:
        raise ValueError("p must be a chance")
    if p == 0:
        return cells.sparkSession.range(0).selectExpr("id AS cell_id", "id AS draw_no")
    if blocks is None and way != "reject":
        n = cells.count()
        blocks = max(LEAST_BLOCKS, math.ceil((n + (m - n) * p) / ROWS))
    return WAYS[way](cells, m, p, seed, max(1, min(blocks or 1, m)), mode)
