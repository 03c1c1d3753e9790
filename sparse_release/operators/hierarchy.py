"""Dyadic and Haar hierarchies over a line of 2^h cells, their range answers, and consistency of a filtered hierarchy.

A node is (level, pos): level 0 are the cells, level h the root. Releases treat nodes as cells of a larger domain, with one number for each node.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.laws import KeepLaw
from .summaries import Plan, adjusted, high_pass, reduced, top_priorities


def height(m: int) -> int:
    """Levels above the cells of a line of m cells, padded to a power of two."""
    return max(0, (m - 1).bit_length())


def node_id(h: int, level: str = "level", pos: str = "pos") -> str:
    """SQL: nodes numbered level by level from the cells up, 0 to 2^(h+1) - 2."""
    return f"(CAST({1 << (h + 1)} AS BIGINT) - shiftleft(1L, {h + 1} - {level}) + {pos})"


def node_of(h: int, name: str = "cell_id") -> tuple[str, str]:
    """SQL of level and pos for a node's number."""
    left = f"({1 << (h + 1)} - {name})"  # over 2^(h - level), up to 2^(h + 1 - level)
    level = f"({h} - CAST(length(bin({left} - 1)) AS INT) + 1)"
    return level, f"({name} - {1 << (h + 1)} + shiftleft(1L, {h + 1} - {level}))"


#: Levels that are added up in one shuffle; the topmost of them, far fewer nodes, feeds the next.
STEP = 6


def levels_of(cells: DataFrame, h: int, step: int = STEP) -> list[tuple[range, DataFrame]]:
    """Occupied nodes (level, pos, v), some levels at a time: no shuffle has more than step + 1 rows for each node of its lowest level, and low levels are read once."""
    rows, parts = cells.selectExpr("cell_id AS pos", "CAST(v AS BIGINT) AS v"), []
    for low in range(0, h + 1, step):
        top = min(low + step, h)
        up = rows.selectExpr(f"explode(sequence({low}, {top})) AS level", "pos", "v").selectExpr("level", f"shiftright(pos, level - {low}) AS pos", "v")
        sums = up.groupBy("level", "pos").agg(F.sum("v").cast("long").alias("v"))
        if top == h:
            parts.append((range(low, h + 1), sums))
            break
        sums = durable(sums)
        parts.append((range(low, top), sums.where(f"level < {top}")))
        rows = sums.where(f"level = {top}").select("pos", "v")
    return parts


def dyadic(cells: DataFrame, h: int, step: int = STEP) -> DataFrame:
    """Occupied nodes (level, pos, v) of all levels, as levels_of makes them."""
    return reduce(DataFrame.unionByName, [part for _, part in levels_of(cells, h, step)])


def dyadic_at_once(cells: DataFrame, h: int) -> DataFrame:
    """As dyadic, in one shuffle of h + 1 rows for each cell: better for low hierarchies."""
    up = cells.selectExpr(f"explode(sequence(0, {h})) AS level", "cell_id", "v").selectExpr("level", "shiftright(cell_id, level) AS pos", "v")
    return up.groupBy("level", "pos").agg(F.sum("v").cast("long").alias("v"))


def haar(cells: DataFrame, h: int, nodes: DataFrame | None = None) -> DataFrame:
    """Whole-number Haar coefficients (level 1 to h: left half less right half; level h + 1: the total), zeros left out. A person moves one on each level by 1.
    nodes: the dyadic ones, if they are kept already."""
    nodes = durable(dyadic(cells, h)) if nodes is None else nodes  # added up in steps, so a coefficient takes its two halves only
    halves = nodes.where(f"level < {h}").selectExpr("CAST(level + 1 AS INT) AS level", "shiftright(pos, 1) AS pos", "CASE WHEN pos % 2 = 1 THEN -v ELSE v END AS v")
    total = nodes.where(f"level = {h}").selectExpr(f"{h + 1} AS level", "0L AS pos", "v")
    return durable(halves.groupBy("level", "pos").agg(F.sum("v").cast("long").alias("v")).unionByName(total).where("v != 0"))  # a release reads it several times


def haar_id(h: int) -> str:
    """SQL: coefficients numbered 0 to 2^h - 1, the total last."""
    return f"CASE WHEN level = {h + 1} THEN {(1 << h) - 1} ELSE CAST({1 << h} AS BIGINT) - shiftleft(1L, {h + 1} - level) + pos END"


def haar_of(h: int, name: str = "cell_id") -> tuple[str, str]:
    left = f"({1 << h} - {name})"
    level = f"(CASE WHEN {name} = {(1 << h) - 1} THEN {h + 1} ELSE {h} - CAST(length(bin(greatest({left} - 1, 1))) AS INT) + 1 END)"
    return level, f"(CASE WHEN {name} = {(1 << h) - 1} THEN 0 ELSE {name} - {1 << h} + shiftleft(1L, {h + 1} - {level}) END)"


Release = Callable[[DataFrame, Plan], DataFrame]


def hier_release(cells: DataFrame, h: int, plan: Plan, release: Release, kind: str = "dyadic", nodes: DataFrame | None = None) -> DataFrame:
    """A hierarchy's nodes (level, pos, value, weight) under any release of cells; noise is for as many levels as are published. nodes: the occupied dyadic ones, if they
    are kept already."""
    if kind == "haar":
        nodes = haar(cells, h, nodes)
    elif nodes is None:
        nodes = dyadic(cells, h)
    number, back, m = (node_id(h), node_of(h), (1 << (h + 1)) - 1) if kind == "dyadic" else (haar_id(h), haar_of(h), 1 << h)
    out = release(nodes.selectExpr(f"{number} AS cell_id", "v"), replace(plan, m=m, sensitivity=plan.sensitivity * (h + 1)))
    return out.selectExpr(f"CAST({back[0]} AS INT) AS level", f"CAST({back[1]} AS BIGINT) AS pos", "value", "weight")


def dyadic_cover(queries: DataFrame, h: int) -> DataFrame:
    """(qid, level, pos) of the fewest nodes that make up each range [lo, hi): at most one at either end of a level. Bit tests only, no rows but the cover's."""
    # At a level, lo and hi are rounded inwards to its grid; an end node belongs if it is not its parent's first (or last) half.
    up, down = "shiftright(lo + shiftleft(1L, l) - 1, l)", "shiftright(hi, l)"
    left, right = (f"CASE WHEN {up} < {down} AND {end} % 2 = 1 THEN {node} END" for end, node in ((up, up), (down, f"{down} - 1")))
    each = f"explode(flatten(transform(sequence(0, {h}), l -> transform(filter(array({left}, {right}), p -> p IS NOT NULL), p -> struct(l AS level, p AS pos))))) AS n"
    return queries.selectExpr("qid", "CAST(lo AS BIGINT) AS lo", "CAST(hi AS BIGINT) AS hi").where("lo < hi").selectExpr("qid", each).selectExpr("qid", "n.level AS level", "CAST(n.pos AS BIGINT) AS pos")


def answer_dyadic(nodes: DataFrame, queries: DataFrame, h: int, value: str = "weight") -> DataFrame:
    """(qid, estimate) for each query, 0 where no node of its cover is in the summary."""
    found = dyadic_cover(queries, h).join(nodes.select("level", "pos", F.col(value).alias("w")), ["level", "pos"]).groupBy("qid").agg(F.sum("w").alias("w"))
    return queries.select("qid").join(found, "qid", "left").selectExpr("qid", "coalesce(CAST(w AS DOUBLE), 0D) AS estimate")


def haar_path(queries: DataFrame, h: int) -> DataFrame:
    """(qid, level, pos, factor): what each coefficient adds to a range [lo, hi). Only nodes at the range's ends and the total count."""
    def inside(a: str, b: str) -> str:
        return f"greatest(0L, least(hi, {b}) - greatest(lo, {a}))"
    start, half = "shiftleft(pos, level)", "shiftleft(1L, level - 1)"
    ends = f"explode(array_distinct(flatten(transform(sequence(1, {h}), l -> array(struct(l AS level, shiftright(lo, l) AS pos), struct(l AS level, shiftright(hi - 1, l) AS pos)))))) AS n" if h else "explode(array(struct(1 AS level, 0L AS pos))) AS n"
    q = queries.selectExpr("qid", "CAST(lo AS BIGINT) AS lo", "CAST(hi AS BIGINT) AS hi").where("lo < hi")
    rows = q.selectExpr("qid", "lo", "hi", ends).selectExpr("qid", "lo", "hi", "n.level AS level", "n.pos AS pos")
    signed = rows.selectExpr("qid", "level", "pos", f"CAST({inside(start, f'{start} + {half}')} - {inside(f'{start} + {half}', f'{start} + 2 * {half}')} AS DOUBLE) / CAST(2 * {half} AS DOUBLE) AS factor")
    total = q.selectExpr("qid", f"{h + 1} AS level", "0L AS pos", f"CAST(hi - lo AS DOUBLE) / {float(1 << h)!r}D AS factor")
    return signed.where("factor != 0").unionByName(total)


def answer_haar(coefficients: DataFrame, queries: DataFrame, h: int, value: str = "weight") -> DataFrame:
    found = haar_path(queries, h).join(coefficients.select("level", "pos", F.col(value).alias("w")), ["level", "pos"]).groupBy("qid").agg(F.sum(F.col("factor") * F.col("w")).alias("w"))
    return queries.select("qid").join(found, "qid", "left").selectExpr("qid", "coalesce(w, 0D) AS estimate")


def prune(nodes: DataFrame, h: int, every: int = 4) -> DataFrame:
    """Nodes all of whose ancestors are in the summary too, from the root down: a node stays if its parent stays. A parent is asked for by two nodes at most, so no key is hot."""
    nodes, out, front = durable(nodes), [], None
    for level in range(h, -1, -1):
        here = nodes.where(f"level = {level}")
        if front is not None:
            here = here.join(front, F.shiftright("pos", 1) == F.col("up"), "left_semi")
        if (h - level) % every == every - 1:
            here = durable(here)
        out.append(here)
        front = here.selectExpr("pos AS up")
    return reduce(DataFrame.unionByName, out)


def consistent_filter(cells: DataFrame, h: int, plan: Plan, cut: int, every: int = 4, parts: list[tuple[range, DataFrame]] | None = None) -> DataFrame:
    """The pruned two-sided filter of the dyadic counts, made from the root down: nodes have noise of their own, so only children of what stays need be drawn. The same
    draws as filtering all nodes and pruning, at the cost of what stays. parts: levels_of, if they
    are kept already."""
    full = replace(plan, m=(1 << (h + 1)) - 1, sensitivity=plan.sensitivity * (h + 1))
    kept_parts, out = [(levels, durable(part)) for levels, part in levels_of(cells, h)] if parts is None else parts, []
    front = cells.sparkSession.range(1).selectExpr(f"{h} AS level", "0L AS pos")
    for level in range(h, -1, -1):
        nodes = next(part for levels, part in kept_parts if level in levels)
        known = front.join(nodes.where(f"level = {level}"), ["level", "pos"], "left").selectExpr("level", "pos", f"{node_id(h)} AS cell_id", "coalesce(v, 0) AS v")
        kept = known.selectExpr("level", "pos", f"CAST(v AS BIGINT) + {full.noise()} AS value").where(f"abs(value) >= {cut}")
        if (h - level) % every == every - 1:
            kept = durable(kept)
        out.append(kept)
        front = kept.selectExpr(f"{level - 1} AS level", "explode(array(2 * pos, 2 * pos + 1)) AS pos")
    return reduce(DataFrame.unionByName, out).selectExpr("CAST(level AS INT) AS level", "CAST(pos AS BIGINT) AS pos", "value", "CAST(value AS DOUBLE) AS weight")


def filter_prune_priority(cells: DataFrame, h: int, plan: Plan, cut: int, s: int, pruned: DataFrame | None = None) -> tuple[DataFrame, float]:
    """A filtered hierarchy, made consistent, then a priority sample of s nodes: (level, pos, value, weight), and its threshold. pruned: the consistent one, if it is made already."""
    pruned = prune(hier_release(cells, h, plan, lambda c, p: high_pass(c, p, cut)), h) if pruned is None else pruned
    full = replace(plan, m=(1 << (h + 1)) - 1)
    ranked = pruned.selectExpr("level", "pos", "value", f"{node_id(h)} AS cell_id").selectExpr("*", f"abs(value) / {full.u('keep')} AS priority")
    kept, tau = top_priorities(durable(ranked), s)  # read several times
    return kept.selectExpr("level", "pos", "value", f"signum(value) * greatest(CAST(abs(value) AS DOUBLE), {tau!r}D) AS weight"), tau


def filter_threshold_nodes(cells: DataFrame, h: int, plan: Plan, cut: int, tau: float) -> DataFrame:
    """Filter and threshold sample of the hierarchy in one step, without writing the filtered nodes out."""
    return hier_release(cells, h, plan, lambda c, p: adjusted(reduced(c, KeepLaw(p.alpha, cut, tau), p), tau))


def dyadic_nd(rows: DataFrame, heights: dict[str, int], v: str = "v") -> DataFrame:
    """Counts of all grid nodes in several dimensions: for each dimension its level and position (<name>_level, <name>_pos), and v. Sensitivity is the product of levels."""
    up = rows
    for name, h in heights.items():
        up = up.selectExpr("*", f"explode(sequence(0, {h})) AS {name}_level").selectExpr("*", f"shiftright(CAST({name} AS BIGINT), {name}_level) AS {name}_pos")
    by = [f"{n}_{x}" for n in heights for x in ("level", "pos")]
    return up.groupBy(*by).agg(F.sum(v).cast("long").alias("v"))


def nd_ids(heights: dict[str, int]) -> tuple[str, int, list[str]]:
    """Grid nodes numbered by mixed radix over each dimension's own node numbers: SQL of the number, how many there are, and SQL that gives levels and positions back."""
    number, back, radix = "0L", [], 1
    for name, h in heights.items():
        number = f"({number} * {(1 << (h + 1)) - 1} + {node_id(h, f'{name}_level', f'{name}_pos')})"
    for name, h in reversed(heights.items()):
        own = (1 << (h + 1)) - 1
        level, pos = node_of(h, f"((cell_id div {radix}) % {own})")
        back = [f"CAST({level} AS INT) AS {name}_level", f"CAST({pos} AS BIGINT) AS {name}_pos", *back]
        radix *= own
    return number, radix, back


def release_nd(rows: DataFrame, heights: dict[str, int], plan: Plan, release: Release, v: str = "v") -> DataFrame:
    """Grid nodes of several dimensions (<name>_level, <name>_pos, value, weight) under any release of cells: an individual is in one node of every combination of levels,
    so noise is for the product of the dimensions' levels. rows: a column for each dimension, and counts."""
    number, m, back = nd_ids(heights)
    if m >= 1 << 63:
        raise ValueError("more grid nodes than a long can number")
    levels = prod(h + 1 for h in heights.values())
    cells = durable(dyadic_nd(rows, heights, v).selectExpr(f"{number} AS cell_id", "v"))
    out = release(cells, replace(plan, m=m, sensitivity=plan.sensitivity * levels))
    return out.selectExpr(*back, "value", "weight")


def answer_nd(nodes: DataFrame, boxes: DataFrame, heights: dict[str, int], value: str = "v") -> DataFrame:
    """(qid, estimate) for boxes (qid, and <name>_lo, <name>_hi for each dimension): the product of the dimensions' covers."""
    cover = boxes.select("qid")
    for name, h in heights.items():
        one = dyadic_cover(boxes.selectExpr("qid", f"{name}_lo AS lo", f"{name}_hi AS hi"), h).selectExpr("qid", f"level AS {name}_level", f"pos AS {name}_pos")
        cover = cover.join(one, "qid")
    found = cover.join(nodes, [c for c in cover.columns if c != "qid"]).groupBy("qid").agg(F.sum(value).alias("w"))
    return boxes.select("qid").join(found, "qid", "left").selectExpr("qid", "coalesce(CAST(w AS DOUBLE), 0D) AS estimate")
