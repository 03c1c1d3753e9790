"""Reduced private releases: high-pass filter, threshold sample, priority sample, and filter with either; by the direct route, and as all noisy cells reduced.

Both routes give summaries of one law. The direct one costs what the occupied cells and the summary cost, whatever the domain's size.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.laws import KeepLaw, laplace_keep, pick_tau, solve_tau
from ..functions.noise import alpha_of, geometric, laplace, tail
from ..functions.prf import draw, uniform
from .zero_cells import zero_cells

#: Beyond so many cells the materialised route asks for an explicit word.
MATERIALISED_CELLS = 1 << 31
#: Cells of a block that one row lays out, where every cell is drawn.
LAID = 1 << 12
#: Blocks whose noise is added up from one seed.
SEEDED = 1 << 14
#: Points of a law that are listed in a plan at most.
LISTED_CUTS = 4096


@dataclass(frozen=True)
class Plan:
    """What a release is made with. route: direct or materialised; way: how empty cells are drawn; release: a name that changes when the data do."""

    m: int
    eps: float
    sensitivity: float = 1.0
    seed: str | int = 1
    release: str = "r"
    route: str = "direct"
    way: str = "skip"
    blocks: int | None = None
    mode: str = "md5"
    allow_large: bool = False

    @property
    def alpha(self) -> float:
        return alpha_of(self.eps, self.sensitivity)

    @property
    def key(self) -> str:
        return f"{self.seed}/{self.release}"

    def noise(self) -> str:
        return geometric(self.alpha, self.key, "cell_id", mode=self.mode)

    def u(self, tag: str) -> str:
        return uniform(self.key, tag, "cell_id", mode=self.mode)


def noisy_occupied(cells: DataFrame, plan: Plan) -> DataFrame:
    return cells.selectExpr("cell_id", f"CAST(v AS BIGINT) + {plan.noise()} AS value")


def all_noisy(cells: DataFrame, plan: Plan) -> DataFrame:
    """Every cell of the domain with noise: the plain mechanism, as dense as the domain. Empty cells are laid out by blocks, so that only occupied ones and a row for each
    block move, not one for each cell."""
    if plan.m > MATERIALISED_CELLS and not plan.allow_large:
        raise ValueError(f"{plan.m} cells would be written out; use the direct route")
    own = cells.where(f"cell_id >= 0 AND cell_id < {plan.m}").select("cell_id", "v")
    taken = own.groupBy(F.expr(f"cell_id div {LAID}").alias("b")).agg(F.collect_list("cell_id").alias("taken"))
    blocks = cells.sparkSession.range(math.ceil(plan.m / LAID)).withColumnRenamed("id", "b").join(taken, "b", "left")
    laid = f"sequence(b * {LAID}, least((b + 1) * {LAID}, {plan.m}) - 1)"
    empty = blocks.selectExpr(f"explode(CASE WHEN taken IS NULL THEN {laid} ELSE array_except({laid}, taken) END) AS cell_id")
    return noisy_occupied(own.selectExpr("cell_id", "coalesce(v, 0) AS v"), plan).unionByName(empty.selectExpr("cell_id", f"CAST(0 AS BIGINT) + {plan.noise()} AS value"))


def noisy_at(cells: DataFrame, plan: Plan, asked: DataFrame) -> DataFrame:
    """Of all_noisy, the asked cells (cell_id, distinct, of the domain): the same draws, without the others."""
    return noisy_occupied(asked.join(cells.select("cell_id", "v"), "cell_id", "left").selectExpr("cell_id", "coalesce(v, 0) AS v"), plan)


def weight_sums(rng: np.random.Generator, empty: np.ndarray, alpha: float, law: KeepLaw | None = None, tau: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """What the weights of the kept ones of so many empty cells come to, and how many are kept: one draw for each sum, of the law it has under all_noisy. Kept are a binomial
    number, half of them negative by another; up to the threshold a weight is the threshold, and so many geometric tails beyond it add up to a negative binomial draw.
    Without a law every cell is kept, and its weight is its noise."""
    p = -math.expm1(math.log(alpha))
    tails = lambda n: np.where(n > 0, rng.negative_binomial(np.maximum(n, 1), p), 0)
    if law is None:
        return (tails(empty) - tails(empty)).astype(float), empty
    if law.sides != 2:
        raise ValueError("sums are drawn for two sides")
    kept, start = rng.binomial(empty, min(law.keep(), 1.0)), max(law.top + 1, law.lo)
    up = rng.binomial(kept, 0.5)
    total = np.zeros(len(empty))
    for sign, n in ((1, up), (-1, kept - up)):
        far = rng.binomial(n, min(law.at_least(start), 1.0))
        total += sign * (float(tau) * (n - far) + (start * far + tails(far)))
    return total, kept


def empty_sums(cells: DataFrame, plan: Plan, block: int, law: KeepLaw | None = None, tau: float = 0.0) -> DataFrame:
    """(b, w, n) for every block of the domain: the weights of its kept empty cells added up, and how many they are, by weight_sums. A group of blocks has its own seed."""
    blocks, m, alpha = math.ceil(plan.m / block), plan.m, plan.alpha
    seeds = cells.sparkSession.range(math.ceil(blocks / SEEDED)).selectExpr("id AS g", f"{draw(plan.key, f'sums-{block}', 'id', mode=plan.mode)} AS s")
    taken = cells.where(f"cell_id >= 0 AND cell_id < {m}").groupBy(F.expr(f"cell_id div {block}").alias("b")).count().selectExpr(f"b div {SEEDED} AS g", "b", "count")

    def drawn(one: pd.DataFrame, have: pd.DataFrame) -> pd.DataFrame:
        g = int(one["g"].iloc[0])
        b = np.arange(g * SEEDED, min((g + 1) * SEEDED, blocks))
        empty = np.minimum(block, m - b * block)
        empty[have["b"].to_numpy(np.int64) - g * SEEDED] -= have["count"].to_numpy(np.int64)
        w, n = weight_sums(np.random.default_rng(int(one["s"].iloc[0])), empty, alpha, law, tau)
        return pd.DataFrame({"b": b, "w": w, "n": n})

    return seeds.groupBy("g").cogroup(taken.groupBy("g")).applyInPandas(drawn, "b long, w double, n long")


def full_geometric(cells: DataFrame, plan: Plan, nonneg: bool = False) -> DataFrame:
    noisy = all_noisy(cells, plan)
    return noisy.selectExpr("cell_id", "greatest(value, 0) AS value") if nonneg else noisy


def full_laplace(cells: DataFrame, m: int, eps: float, seed: str | int = 1, sensitivity: float = 1.0, mode: str = "md5") -> DataFrame:
    """The plain mechanism for real values."""
    full = cells.sparkSession.range(m).withColumnRenamed("id", "cell_id").join(cells.select("cell_id", "v"), "cell_id", "left")
    return full.selectExpr("cell_id", f"CAST(coalesce(v, 0) AS DOUBLE) + {laplace(sensitivity / eps, seed, 'cell_id', mode=mode)} AS value")


def _fits(law: KeepLaw) -> str:
    return f"value >= {law.lo}" if law.sides == 1 else f"abs(value) >= {law.lo}"


def _kept(noisy: DataFrame, law: KeepLaw, plan: Plan) -> DataFrame:
    """Noisy cells that the law keeps. The draw is carried, since a priority sample goes on with it."""
    rows = noisy.where(_fits(law))
    if law.tau <= 1:
        return rows.selectExpr("cell_id", "value", "CAST(NULL AS DOUBLE) AS u")
    return rows.selectExpr("cell_id", "value", f"{plan.u('keep')} AS u").where(f"u < least(abs(value) / {float(law.tau)!r}D, 1D)")


def magnitude(law: KeepLaw, plan: Plan) -> str:
    """SQL for a kept empty cell's magnitude: how many cut points lie above a draw, and a plain tail beyond the last."""
    far = tail(law.alpha, plan.u("tail"))
    if law.top - law.lo >= LISTED_CUTS:
        return _bisected(law, plan, far)
    cuts = law.cuts()
    if not cuts:
        return f"{law.lo} + {far}"
    h = draw(plan.key, "size", "cell_id", mode=plan.mode)
    # a search in two steps: which stretch of cut points, then where in it
    step = max(1, math.isqrt(len(cuts)))
    array = lambda xs: "array(" + ", ".join(f"{x}L" for x in xs) + ")"
    stretches = "array(" + ", ".join(array(cuts[k : k + step]) for k in range(0, len(cuts), step)) + ")"
    heads = array(cuts[::step])
    passed = f"size(filter({heads}, c -> {h} < c))"
    found = f"CASE WHEN {passed} = 0 THEN 0 ELSE ({passed} - 1) * {step} + size(filter({stretches}[{passed} - 1], c -> {h} < c)) END"
    whole = law.lo + len(cuts)
    return f"CASE WHEN {h} < {cuts[-1]}L THEN {whole} + {far} ELSE {law.lo} + {found} END"


def _bisected(law: KeepLaw, plan: Plan, far: str) -> str:
    """As magnitude, by halving between the cut and the threshold with the law itself, where a list of its points would make the plan too long."""
    a, t, u = law.alpha, law.top, plan.u("size")
    moment = f"(pow({a!r}D, x.c) * (x.c * {1 - a!r}D + {a!r}D) / {(1 - a) ** 2!r}D)"
    reach = f"(({moment} - {law._moment(t + 1)!r}D) / {float(law.tau)!r}D + {law._mass(t + 1)!r}D)"
    steps = math.ceil(math.log2(t + 1 - law.lo)) + 1
    middle = "(s.a + s.b) div 2L"
    found = f"""aggregate(sequence(1, {steps}), struct({law.lo}L AS a, {t + 1}L AS b), (s, i) -> CASE WHEN s.b - s.a <= 1 THEN s
        WHEN transform(array(struct({middle} AS c)), x -> {reach} > {law.reach(law.lo)!r}D * {u})[0] THEN struct({middle} AS a, s.b AS b) ELSE struct(s.a AS a, {middle} AS b) END).a"""
    return f"CASE WHEN {u} < {law.at_least(t + 1)!r}D THEN {t + 1} + {far} ELSE {found} END"


def empty_part(cells: DataFrame, law: KeepLaw, plan: Plan) -> DataFrame:
    """Empty cells that are kept, with values of the right law."""
    places = zero_cells(cells, plan.m, law.keep(), plan.key, plan.way, plan.blocks, plan.mode)
    return valued(places.select("cell_id"), law, plan)


def valued(rows: DataFrame, law: KeepLaw, plan: Plan) -> DataFrame:
    """rows (cell_id, and others) and the value of a kept empty cell: a sign and a magnitude. What magnitude says in SQL is looked up here in Arrow batches, as higher-order
    functions are interpreted and hash the cell again for each point of the law."""
    sign, far, fields = "1" if law.sides == 1 else f"CASE WHEN {plan.u('sign')} < 0.5D THEN -1 ELSE 1 END", tail(law.alpha, plan.u("tail")), rows.schema.simpleString()[7:-1]
    listed = law.top - law.lo < LISTED_CUTS
    cuts = np.array(law.cuts()[::-1] if listed else [], np.int64)
    if listed and not len(cuts):
        return rows.selectExpr("*", f"CAST({sign} * ({law.lo} + {far}) AS BIGINT) AS value")
    drawn = draw(plan.key, "size", "cell_id", mode=plan.mode) if listed else plan.u("size")

    def found(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            h, far, sign = (part.pop(c).to_numpy() for c in ("_h", "_far", "_sign"))
            if listed:
                above = len(cuts) - np.searchsorted(cuts, h, side="right")
                size = law.lo + above + np.where(above == len(cuts), far, 0)
            else:
                size = law.magnitude(h, far)
            yield part.assign(value=sign * size)

    asked = rows.selectExpr("*", f"{drawn} AS _h", f"CAST({far} AS BIGINT) AS _far", f"CAST({sign} AS BIGINT) AS _sign")
    return asked.mapInPandas(found, f"{fields},value:bigint")


def reduced(cells: DataFrame, law: KeepLaw, plan: Plan) -> DataFrame:
    """cell_id, value, u (the draw that kept it; null if none was needed) under any law and route."""
    if plan.route == "materialised":
        return _kept(all_noisy(cells, plan), law, plan)
    if plan.route != "direct":
        raise ValueError("route must be direct or materialised")
    u = "CAST(NULL AS DOUBLE)" if law.tau <= 1 else f"{plan.u('rank')} * least(abs(value) / {float(law.tau)!r}D, 1D)"
    return _kept(noisy_occupied(cells, plan), law, plan).unionByName(empty_part(cells, law, plan).selectExpr("cell_id", "value", f"{u} AS u"))


def high_pass(cells: DataFrame, plan: Plan, cut: int, sides: int = 2) -> DataFrame:
    """Noisy values of at least the cut (in magnitude, if two-sided): cell_id, value, weight."""
    if cut < 1:
        raise ValueError("a cut is a whole number from 1; without one, use full_geometric")
    return reduced(cells, KeepLaw(plan.alpha, cut, 1.0, sides), plan).selectExpr("cell_id", "value", "CAST(value AS DOUBLE) AS weight")


def threshold_sample(cells: DataFrame, plan: Plan, tau: float, sides: int = 2) -> DataFrame:
    """Cells kept with chance |value| / tau; weights are unbiased."""
    return adjusted(reduced(cells, KeepLaw(plan.alpha, 0, tau, sides), plan), tau)


def filter_threshold(cells: DataFrame, plan: Plan, cut: int, tau: float, sides: int = 2) -> DataFrame:
    """A threshold sample of what a cut leaves; with tau up to the cut, the filter alone."""
    return adjusted(reduced(cells, KeepLaw(plan.alpha, cut, tau if tau > cut else 1.0, sides), plan), tau if tau > cut else 0.0)


def kept_at(noisy: DataFrame, law: KeepLaw | None, plan: Plan, tau: float = 0.0) -> DataFrame:
    """Of noisy cells, those that the law keeps, with weights; all without one."""
    return adjusted(noisy if law is None else _kept(noisy, law, plan), tau)


def adjusted(rows: DataFrame, tau: float, raw: bool = False) -> DataFrame:
    """With weights sign(value) * max(|value|, tau); raw ones, biased but closer for single cells, are the values."""
    weight = "CAST(value AS DOUBLE)" if raw else f"signum(value) * greatest(CAST(abs(value) AS DOUBLE), {float(tau)!r}D)"
    return rows.selectExpr("cell_id", "value", f"{weight} AS weight")


def top_priorities(rows: DataFrame, s: int, direct_limit: int = 100_000) -> tuple[DataFrame, float]:
    """The s rows of highest priority, ties to the smaller cell, and the next priority (0 if there is none). Large s: counts per range narrow the place of the last
    row down, so that no task gathers s rows."""
    if s <= 0:
        raise ValueError("a sample has at least one row")
    if s < direct_limit:
        tau = rows.orderBy(F.col("priority").desc(), "cell_id").limit(s + 1).agg(F.count(F.lit(1)), F.min("priority")).first()
        return rows.orderBy(F.col("priority").desc(), "cell_id").limit(s), float(tau[1]) if tau[0] > s else 0.0
    lo, hi, above, inside = float("-inf"), float("inf"), 0, rows
    while True:
        # rows of a slice, by approximate quantiles: a few numbers come to the driver
        size, marks = inside.agg(F.count(F.lit(1)), F.percentile_approx("priority", [k / 64 for k in range(1, 64)], 10_000)).first()
        if size <= direct_limit:
            break
        edges = sorted({lo, *marks, hi})
        if len(edges) <= 2:
            break
        counts = {r["slice"]: r["count"] for r in inside.groupBy(F.expr(f"size(filter(array({', '.join(f'{e!r}D' for e in edges[1:-1])}), e -> priority >= e))").alias("slice")).count().collect()}
        for k in range(len(edges) - 2, -1, -1):
            if above + counts.get(k, 0) >= s + 1 or k == 0:
                lo, hi = edges[k], edges[k + 1]
                break
            above += counts.get(k, 0)
        inside = durable(inside.where((F.col("priority") >= lo) & (F.col("priority") < hi)))  # a small part of what was read before
    rest = inside.orderBy(F.col("priority").desc(), "cell_id").limit(s - above)
    nxt = inside.orderBy(F.col("priority").desc(), "cell_id").limit(s - above + 1).agg(F.count(F.lit(1)), F.min("priority")).first()
    sure = rows.where(F.col("priority") >= hi) if hi != float("inf") else rows.limit(0)
    return sure.unionByName(rest), float(nxt[1]) if nxt[0] > s - above else 0.0


def guess_tau(cells: DataFrame, plan: Plan, s: int, cut: int = 0, slack: float = 1.2) -> float:
    """A first threshold that should leave slack * s candidates; it shapes the cost only, not the sample's law."""
    # magnitudes by their first 12 bits: some 100,000 rows at most, whatever the values
    x = F.abs("value")
    step = F.pow(F.lit(2.0), F.greatest(F.lit(0), F.floor(F.log2(F.greatest(x, F.lit(1)))) - 11)).cast("long")
    sizes = [(r["x"], r["count"]) for r in noisy_occupied(cells, plan).groupBy((x - x % step).alias("x")).count().collect()]
    return solve_tau(sizes, plan.m, sum(c for _, c in sizes), plan.alpha, slack * s + 3 * math.sqrt(s) + 5, cut)


def priority_sample(cells: DataFrame, plan: Plan, s: int, cut: int = 0, tau0: float | None = None) -> tuple[DataFrame, float]:
    """A sample of s rows and its threshold (the next priority): cell_id, value, weight, r, priority; drop the last two before publishing.

    Candidates come from a threshold sample; a candidate's r is uniform up to its chance of being one. If a guess leaves too few, a lower one extends the same outcome:
    occupied cells keep their draws, empty candidates stay, and empty cells that were none are drawn for the band between the thresholds only."""
    if plan.route == "materialised":
        law = KeepLaw(plan.alpha, cut, 1.0)
        rows = all_noisy(cells, plan).where(_fits(law)).selectExpr("cell_id", "value", f"{plan.u('keep')} AS r")
        kept, tau = top_priorities(durable(rows.selectExpr("*", "abs(value) / r AS priority")), s)
        return _prioritised(kept, tau), tau
    tau0 = tau0 or guess_tau(cells, plan, s, cut)
    law = _candidate_law(plan, cut, tau0)
    empty = durable(_ranked(empty_part(cells, law, plan), law, plan))
    while True:
        own = _kept(noisy_occupied(cells, plan), law, plan).selectExpr("cell_id", "value", f"coalesce(u, {plan.u('keep')}) AS r")
        rows = durable(own.unionByName(empty).selectExpr("*", "abs(value) / r AS priority"))  # read several times, and noise is dear
        kept, tau = top_priorities(rows, s)
        if tau > 0 or law.tau <= 1:
            return _prioritised(kept, tau), tau
        lower = _candidate_law(plan, cut, law.tau / 2)
        empty, law = durable(empty.unionByName(_band(cells, empty, law, lower, plan))), lower


def _candidate_law(plan: Plan, cut: int, tau: float) -> KeepLaw:
    return KeepLaw(plan.alpha, cut, max(tau, 1.0) if tau > cut else 1.0)


def _chance_of(law: KeepLaw) -> str:
    return "1D" if law.tau <= 1 else f"least(abs(value) / {float(law.tau)!r}D, 1D)"


def _ranked(rows: DataFrame, law: KeepLaw, plan: Plan) -> DataFrame:
    return rows.selectExpr("cell_id", "value", f"{plan.u('rank' if law.tau > 1 else 'keep')} * {_chance_of(law)} AS r")


def _band(cells: DataFrame, empty: DataFrame, law: KeepLaw, lower: KeepLaw, plan: Plan) -> DataFrame:
    """Empty cells that the lower threshold keeps and the higher one did not, given which the higher one kept. A candidate of the lower one is of the band if its r is at
    least the higher one's chance. Each of the other empty cells is of the band with chance (p1 - p0) / (1 - p0); its value and r are the first of the band among draws
    of the lower law, of which so many are laid out that none being so is out of the question."""
    p0, p1, own = law.keep(), lower.keep(), replace(plan, release=f"{plan.release}/band-{lower.tau!r}")
    rest = cells.select("cell_id").unionByName(empty.select("cell_id"))
    places = zero_cells(rest, plan.m, (p1 - p0) / (1 - p0), own.key, plan.way, plan.blocks, plan.mode)
    tries = math.ceil(42 / math.log(p1 / p0))
    drawn = places.selectExpr("cell_id AS place", f"explode(sequence(0, {tries - 1})) AS t").selectExpr("place", "t", "xxhash64(place, t) AS cell_id")
    sized = valued(drawn, lower, own)
    ranked = sized.selectExpr("place", "t", "value", f"{own.u('rank')} * {_chance_of(lower)} AS r").where(f"r >= {_chance_of(law)}")
    first = ranked.groupBy("place").agg(F.min(F.struct("t", "value", "r")).alias("x"))
    return first.selectExpr("place AS cell_id", "x.value AS value", "x.r AS r")


def _prioritised(kept: DataFrame, tau: float) -> DataFrame:
    return kept.selectExpr("cell_id", "value", f"signum(value) * greatest(CAST(abs(value) AS DOUBLE), {tau!r}D) AS weight", "r", "priority")


def filter_priority(cells: DataFrame, plan: Plan, cut: int, s: int, tau0: float | None = None) -> tuple[DataFrame, float]:
    """A priority sample of what a two-sided cut leaves."""
    return priority_sample(cells, plan, s, cut, tau0)


def uniform_sample(cells: DataFrame, plan: Plan, fraction: float) -> DataFrame:
    """Cells drawn alike and then noised: the strawman, since few of them are occupied."""
    chosen = plan.u("uniform")
    if plan.route == "materialised":
        rows = all_noisy(cells, plan).where(f"{chosen} < {fraction!r}D")
    else:
        empty = zero_cells(cells, plan.m, fraction, plan.key, plan.way, plan.blocks, plan.mode).selectExpr("cell_id", f"{plan.noise()} AS value")
        rows = noisy_occupied(cells, plan).where(f"{chosen} < {fraction!r}D").unionByName(empty)
    return rows.selectExpr("cell_id", "value", f"value / {fraction!r}D AS weight")


def laplace_filter(cells: DataFrame, m: int, eps: float, cut: float, seed: str | int = 1, sensitivity: float = 1.0, way: str = "skip", blocks: int | None = None, mode: str = "md5") -> DataFrame:
    """High-pass filter for real values with Laplace noise, direct."""
    b = sensitivity / eps
    kept = cells.selectExpr("cell_id", f"CAST(v AS DOUBLE) + {laplace(b, seed, 'cell_id', mode=mode)} AS value").where(f"abs(value) >= {float(cut)!r}D")
    sign = f"CASE WHEN {uniform(seed, 'sign', 'cell_id', mode=mode)} < 0.5D THEN -1 ELSE 1 END"
    size = f"{float(cut)!r}D - {b!r}D * ln({uniform(seed, 'tail', 'cell_id', mode=mode)})"
    empty = zero_cells(cells, m, math.exp(-cut / b), seed, way, blocks, mode).selectExpr("cell_id", f"{sign} * ({size}) AS value")
    return kept.unionByName(empty)


def laplace_sample(cells: DataFrame, m: int, eps: float, tau: float, cut: float = 0.0, seed: str | int = 1, sensitivity: float = 1.0, way: str = "skip", blocks: int | None = None, mode: str = "md5") -> DataFrame:
    """Threshold sample of real values with Laplace noise, after a cut if one is given: cell_id, value, weight. With tau up to the cut, the filter alone.

    Behind a cut, empty cells that pass it are thinned. Without one, a kept magnitude has density min(x, tau) exp(-x / scale): the sum of two exponential draws, taken
    with chance min(1, tau / x), first of so many that none being taken is out of the question."""
    b, u = sensitivity / eps, lambda tag, key="cell_id": uniform(seed, tag, key, mode=mode)
    if tau <= cut:
        return laplace_filter(cells, m, eps, cut, seed, sensitivity, way, blocks, mode).selectExpr("cell_id", "value", "value AS weight")
    keep = f"{u('keep')} < least(abs(value) / {float(tau)!r}D, 1D)"
    if cut > 0:
        rows = laplace_filter(cells, m, eps, cut, seed, sensitivity, way, blocks, mode).where(keep)
    else:
        own = cells.selectExpr("cell_id", f"CAST(v AS DOUBLE) + {laplace(b, seed, 'cell_id', mode=mode)} AS value").where(keep)
        places = zero_cells(cells, m, laplace_keep(b, 0.0, tau), seed, way, blocks, mode)
        drawn = places.selectExpr("cell_id AS place", f"explode(sequence(0, {math.ceil(42 * b / tau)})) AS t").selectExpr("place", "t", "concat_ws('/', place, t) AS cell_id")
        sized = drawn.selectExpr("place", "t", "cell_id", f"-{b!r}D * (ln({u('one')}) + ln({u('two')})) AS x").where(f"{u('take')} * x < {float(tau)!r}D")
        first = sized.groupBy("place").agg(F.min(F.struct("t", "x")).alias("y")).selectExpr("place AS cell_id", "y.x AS x")
        rows = own.unionByName(first.selectExpr("cell_id", f"CASE WHEN {u('sign')} < 0.5D THEN -x ELSE x END AS value"))
    return rows.selectExpr("cell_id", "value", f"signum(value) * greatest(abs(value), {float(tau)!r}D) AS weight")


def raise_cut(summary: DataFrame, target: int) -> tuple[DataFrame, int]:
    """A finished filter summary with the least higher cut that leaves at most `target` rows. Only published values are read."""
    have, lo, cut = 0, 1, int(summary.agg(F.max(F.abs("value"))).first()[0] or 0) + 1
    while cut > lo:  # magnitudes from cut on are kept; the slice below that holds the last one is counted ever finer
        step = -(-(cut - lo) // 4096)
        x = F.abs("value")
        counts = {r["k"]: r["count"] for r in summary.where((x >= lo) & (x < cut)).groupBy(((F.lit(cut - 1) - x) / step).cast("long").alias("k")).count().collect()}
        k = 0
        while k * step < cut - lo and have + counts.get(k, 0) <= target:
            have, k = have + counts.get(k, 0), k + 1
        top = cut - k * step
        if step == 1 or top <= lo:
            cut = max(top, lo)
            break
        lo, cut = max(lo, top - step), top
    values = summary.where(f"abs(value) >= {int(cut)}")
    return values, int(values.agg(F.min(F.abs("value"))).first()[0] or cut)


def lower_cut(cells: DataFrame, summary: DataFrame, plan: Plan, cut: int, lower: int) -> DataFrame:
    """A finished two-sided filter summary (cell_id, value) as the lower cut would have left the same outcome: occupied cells keep their noise, empty cells that passed stay,
    and those that did not are drawn for the band between the cuts only."""
    if not 1 <= lower < cut:
        raise ValueError("the lower cut lies between 1 and the cut")
    p0, p1 = KeepLaw(plan.alpha, cut).keep(), KeepLaw(plan.alpha, lower).keep()
    own = replace(plan, release=f"{plan.release}/from-{cut}-to-{lower}")
    occupied = noisy_occupied(cells, plan).where(f"abs(value) >= {lower}")
    empty = summary.select("cell_id", "value").join(cells.select("cell_id"), "cell_id", "left_anti")
    rest = cells.select("cell_id").unionByName(empty.select("cell_id"))
    places = zero_cells(rest, plan.m, (p1 - p0) / (1 - p0), own.key, plan.way, plan.blocks, plan.mode)
    # a magnitude of the band: a geometric tail from the lower cut on, given that it ends below the upper one
    size = f"{lower} + CAST(floor(ln(1D - {own.u('size')} * {1 - plan.alpha ** (cut - lower)!r}D) / {math.log(plan.alpha)!r}D) AS BIGINT)"
    sign = f"CASE WHEN {own.u('sign')} < 0.5D THEN -1 ELSE 1 END"
    band = places.selectExpr("cell_id", f"CAST({sign} * least({size}, {cut - 1}) AS BIGINT) AS value")
    return occupied.unionByName(empty).unionByName(band)


def ensure_size(cells: DataFrame, plan: Plan, cut: int, least: int, again: bool = False, tries: int = 20) -> tuple[DataFrame, int]:
    """A filter summary of at least `least` rows. By default the cut goes down over the same outcome, band by band; with `again`, the same cut is run anew under other draws,
    which conditions the law on the outcome."""
    out = durable(high_pass(cells, plan, cut).select("cell_id", "value"))
    for k in range(1, tries):
        if out.count() >= least or (cut == 1 and not again):
            break
        if again:
            out = durable(high_pass(cells, replace(plan, release=f"{plan.release}/{k}"), cut).select("cell_id", "value"))
        else:
            lower = max(1, cut - max(1, cut // 4))
            out, cut = durable(lower_cut(cells, out, plan, cut, lower)), lower
    return out.selectExpr("cell_id", "value", "CAST(value AS DOUBLE) AS weight"), cut
