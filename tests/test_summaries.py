"""Summaries: both routes have one law; samples are unbiased; edges."""

import math
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from sparse_release.functions.laws import KeepLaw
from sparse_release.operators import accuracy as A
from sparse_release.operators import estimators as E
from sparse_release.operators import summaries as S
from sparse_release.operators.zero_cells import zero_cells
from sparse_release.sources.synthetic import range_queries, subset_queries, synthetic

M = 20_000
PLAN = S.Plan(m=M, eps=0.3, mode="xxhash64")


@pytest.fixture(scope="module")
def cells(spark):
    return synthetic(spark, M, 0.05, 30, 8).persist()


def mean_sd(xs):
    m = sum(xs) / len(xs)
    return m, math.sqrt(sum((x - m) ** 2 for x in xs) / max(1, len(xs) - 1))


@pytest.mark.parametrize("way", ["skip", "block", "reject"])
def test_zero_cells(spark, cells, way):
    p, n = 0.02, cells.count()
    sizes = []
    for seed in range(8):
        z = zero_cells(cells, M, p, seed, way, 16, "xxhash64").persist()
        assert z.select("cell_id").distinct().count() == z.count() == z.select("draw_no").distinct().count()
        assert z.join(cells, "cell_id", "left_semi").count() == 0 and z.where(f"cell_id < 0 OR cell_id >= {M}").count() == 0
        sizes.append(z.count())
        z.unpersist()
    mean, _ = mean_sd(sizes)
    sd = math.sqrt((M - n) * p * (1 - p))
    assert abs(mean - (M - n) * p) < 5 * sd / math.sqrt(len(sizes)) and max(sizes) - min(sizes) < 12 * sd


@pytest.mark.parametrize("way", ["skip", "block", "reject"])
def test_zero_cells_edges(spark, way):
    none, full = spark.createDataFrame([], "cell_id long, v long"), spark.range(10).selectExpr("id AS cell_id", "1L AS v")
    assert zero_cells(full, 10, 0.9, 1, way).count() == 0
    assert sorted(r.cell_id for r in zero_cells(none, 10, 1.0, 1, way).collect()) == list(range(10))
    assert zero_cells(none, 1, 1.0, 1, way).count() == 1 and zero_cells(none, 10, 0.0, 1, way).count() == 0


LAWS = {"filter1": KeepLaw(PLAN.alpha, 6, 1.0, 1), "filter2": KeepLaw(PLAN.alpha, 6), "threshold": KeepLaw(PLAN.alpha, 0, 9.5), "both": KeepLaw(PLAN.alpha, 4, 9.0)}


@pytest.mark.parametrize("name", LAWS)
def test_routes_have_one_law(cells, name):
    law, sizes, values = LAWS[name], {"direct": [], "materialised": []}, {"direct": [], "materialised": []}
    for seed in range(5):
        for route in sizes:
            rows = S.reduced(cells, law, replace(PLAN, seed=seed, route=route, way="block")).persist()
            sizes[route].append(rows.count())
            values[route].append(rows.agg(F.avg(F.abs("value"))).first()[0])
            if seed == 0:
                kept = rows.join(cells, "cell_id", "left_semi").select("cell_id", "value")
                values[f"own-{route}"] = sorted(tuple(r) for r in kept.collect())
            rows.unpersist()
    assert values["own-direct"] == values["own-materialised"]  # the occupied part is the same, draw by draw
    (a, _), (b, _) = mean_sd(sizes["direct"]), mean_sd(sizes["materialised"])
    p, empty = law.keep(), M - cells.count()
    assert abs(a - b) < 5 * math.sqrt(2 * empty * p * (1 - p) / 5)
    assert abs(mean_sd(values["direct"])[0] - mean_sd(values["materialised"])[0]) < 0.35


def test_magnitudes_follow_the_law(spark):
    none = spark.createDataFrame([], "cell_id long, v long")
    for law in LAWS.values():
        rows = S.empty_part(none, law, replace(PLAN, m=60_000, way="block")).persist()
        n = rows.count()
        assert abs(n - 60_000 * law.keep()) < 5 * math.sqrt(60_000 * law.keep())
        for x in (law.lo + 1, law.lo + 3, law.lo + 8, 15):
            got, p = rows.where(f"abs(value) >= {x}").count() / n, law.at_least(x)
            assert abs(got - p) < 5 * math.sqrt(max(p * (1 - p), 1e-6) / n) + 1e-9
        if law.sides == 2:
            assert abs(rows.where("value > 0").count() / n - 0.5) < 3 / math.sqrt(n)
        rows.unpersist()


def test_samples_are_unbiased(cells):
    total, gaps = cells.agg(F.sum("v")).first()[0], {"threshold": [], "priority": [], "uniform": []}
    for seed in range(6):
        plan = replace(PLAN, seed=seed, way="block")
        made = {"threshold": S.threshold_sample(cells, plan, 40.0), "priority": S.priority_sample(cells, plan, 1500)[0], "uniform": S.uniform_sample(cells, plan, 0.2)}
        for k, s in made.items():
            gaps[k].append(s.agg(F.sum("weight")).first()[0] - total)
    for k, g in gaps.items():
        mean, sd = mean_sd(g)
        assert abs(mean) < 4 * sd / math.sqrt(len(g)) + 0.03 * total, k


def test_priority_sample_is_a_threshold_sample(cells):
    rows, tau = S.priority_sample(cells, PLAN, 700)
    rows = rows.persist()
    assert rows.count() == 700 and rows.where(f"priority <= {tau!r}D").count() == 0
    assert rows.where("abs(weight) + 1e-9 < abs(value)").count() == 0 and rows.where(f"abs(weight) + 1e-9 < {tau!r}D").count() == 0
    assert rows.where("r <= 0 OR r > 1").count() == 0
    few, none = S.filter_priority(cells, PLAN, 200, 50)
    assert none == 0.0 and few.count() < 50


def test_hand_priorities(spark):
    rows = spark.createDataFrame([(0, 50, 0.5), (1, -30, 0.9), (2, 20, 0.4), (3, 10, 0.5)], "cell_id long, value long, r double").selectExpr("*", "abs(value) / r AS priority")
    kept, tau = S.top_priorities(rows, 2)
    assert sorted(r.cell_id for r in kept.collect()) == [0, 2] and tau == pytest.approx(100 / 3)


def test_large_top_lists(spark):
    rows = spark.range(5000).selectExpr("id AS cell_id", "CAST(pmod(xxhash64(id), 800) AS DOUBLE) AS priority").persist()
    want = sorted(((-r.priority, r.cell_id) for r in rows.collect()))
    for s in (1, 37, 900, 4999, 5000):
        kept, tau = S.top_priorities(rows, s, direct_limit=1 if s == 1 else 50)
        assert sorted((-r.priority, r.cell_id) for r in kept.collect()) == want[:s]
        assert tau == (-want[s][0] if s < 5000 else 0.0)


def test_edges(spark, cells):
    none = spark.createDataFrame([], "cell_id long, v long")
    assert S.high_pass(none, replace(PLAN, m=100), 1000).count() == 0
    full = spark.range(50).selectExpr("id AS cell_id", "CAST(40 AS BIGINT) AS v")
    assert S.high_pass(full, replace(PLAN, m=50, eps=20.0), 5).count() == 50
    assert S.filter_threshold(cells, PLAN, 9, 5.0).exceptAll(S.high_pass(cells, PLAN, 9)).count() == 0
    for bad in (lambda: S.high_pass(cells, PLAN, 0), lambda: S.Plan(m=1, eps=0).alpha, lambda: S.reduced(cells, LAWS["both"], replace(PLAN, route="x")), lambda: S.all_noisy(cells, replace(PLAN, m=1 << 40)), lambda: S.priority_sample(cells, PLAN, 0), lambda: zero_cells(cells, M, 1.5, 1)):
        with pytest.raises(ValueError):
            bad()
    cut, at = S.raise_cut(S.high_pass(cells, PLAN, 5), 400)
    assert cut.count() <= 400 and at > 5
    big, at = S.ensure_size(cells, PLAN, 30, 1000)
    assert big.count() >= 1000 and at < 30 and S.ensure_size(cells, PLAN, 5, 10, again=True)[1] == 5


def test_direct_route_ignores_the_domain(spark):
    few = spark.range(200).selectExpr("id * 1000003 AS cell_id", "100L AS v")
    out = S.high_pass(few, S.Plan(m=10**12, eps=0.3, mode="xxhash64", way="block", blocks=64), 60)
    assert 100 < out.count() < 30_000


def test_reruns_and_partitions_agree(cells):
    a = S.threshold_sample(cells, PLAN, 20.0)
    assert a.exceptAll(S.threshold_sample(cells.repartition(7), PLAN, 20.0)).count() == 0
    assert a.exceptAll(S.threshold_sample(cells, replace(PLAN, release="other"), 20.0)).count() > 0


def test_privacy_of_neighbours(spark):
    """A histogram of one cell's outcome moves by at most e^eps when one row is taken away."""
    eps, n = 1.0, 60_000
    seen = {}
    for v in (3, 2):
        one = spark.range(n).selectExpr("id AS cell_id", f"{v}L AS v")
        rows = S.noisy_occupied(one, S.Plan(m=n, eps=eps, seed=v)).where("abs(value) >= 2").groupBy("value").count().collect()
        seen[v] = {r.value: r["count"] / n for r in rows}
    for x in set(seen[3]) & set(seen[2]):
        a, b = seen[3][x], seen[2][x]
        if min(a, b) * n > 400:
            assert abs(math.log(a / b)) < eps + 5 * math.sqrt(1 / (a * n) + 1 / (b * n))


def test_estimators(spark, cells):
    data = {r.cell_id: r.v for r in cells.collect()}
    q = range_queries(spark, M, [1, 100, 5000, M], 10)
    got = {r.qid: r.truth for r in E.exact_range(cells, q).collect()}
    assert all(got[r.qid] == sum(v for c, v in data.items() if r.lo <= c < r.hi) for r in q.collect())
    small = {r.qid: r.estimate for r in E.est_range(cells, q, "v", block=16).collect()}
    assert small == got
    sets = subset_queries(spark, M, [10, 500], 5)
    members = sets.collect()
    assert len({(r.qid, r.cell_id) for r in members}) == len(members) == 5 * 510
    sums = {}
    for r in members:
        sums[r.qid] = sums.get(r.qid, 0) + data.get(r.cell_id, 0)
    assert {r.qid: r.truth for r in E.exact_subset(cells, sets.unionByName(sets)).collect()} == sums
    prefix, run = {r.cell_id: r.prefix for r in E.prefix_sums(cells, block=16).collect()}, 0
    for c in sorted(data):
        run += data[c]
        assert prefix[c] == run
    errors = A.by_size(A.errors(E.exact_range(cells, q), E.est_range(cells, q, "v"), q)).collect()
    assert all(r.abs_error == 0 for r in errors)
    assert E.est_point(cells.selectExpr("cell_id", "v AS value"), spark.range(5).withColumnRenamed("id", "cell_id"), 0.5).count() == 5


def test_extended_candidates_have_the_law(spark):
    """A first guess far too high is extended in bands; sizes and magnitudes are those of a good first guess."""
    none = spark.createDataFrame([], "cell_id long, v long")
    seen = {8.0: [], 400.0: []}
    for seed in range(3):
        for tau0 in seen:
            rows, tau = S.priority_sample(none, replace(PLAN, m=80_000, seed=seed, way="block"), 4000, tau0=tau0)
            got = rows.agg(F.count("*"), F.countDistinct("cell_id"), F.avg(F.abs("value"))).first()
            assert got[0] == got[1] == 4000
            seen[tau0].append((tau, got[2]))
    for k, slack in ((0, 4.0), (1, 0.3)):
        a, b = (mean_sd([x[k] for x in seen[t]])[0] for t in seen)
        assert abs(a - b) < slack


@pytest.mark.parametrize("cut", [0.0, 4.0])
def test_laplace_samples(spark, cut):
    """Empty cells' numbers and magnitudes, against plain integrals."""
    from sparse_release.functions.laws import laplace_keep

    none, m, b, tau = spark.createDataFrame([], "cell_id long, v long"), 60_000, 1 / 0.3, 8.0
    got = S.laplace_sample(none, m, 0.3, tau, cut, mode="xxhash64", way="block").agg(F.count("*"), F.avg(F.abs("value")), F.avg(F.signum("value")), F.min(F.abs("weight"))).first()
    xs = [cut + (k + 0.5) * 0.001 for k in range(100_000)]
    w = [min(x / tau, 1) * math.exp(-x / b) / b for x in xs]
    p = sum(w) * 0.001
    assert p == pytest.approx(laplace_keep(b, cut, tau), rel=1e-4)
    assert abs(got[0] - m * p) < 5 * math.sqrt(m * p) and abs(got[1] - sum(x * y for x, y in zip(xs, w, strict=True)) / sum(w)) < 0.15 and abs(got[2]) < 0.04 and got[3] >= tau


@pytest.mark.parametrize("way", ["skip", "block"])
def test_crowded_blocks_are_cut(spark, way, monkeypatch):
    from sparse_release.operators import zero_cells as Z

    monkeypatch.setattr(Z, "ROWS", 20)
    m, at = 1 << 20, 400_000
    crowd = spark.range(1000).selectExpr(f"{at} + id * 2 AS cell_id", "5L AS v")
    leaves, occupied = Z.cut_blocks(crowd, m, 64)
    sizes = {r.lo: r["count"] for r in occupied.groupBy("lo").count().collect()}
    rows = sorted((r.lo, r["size"], r.block) for r in leaves.collect())
    assert max(sizes.values()) <= Z.CROWD * 20 and sum(sizes.values()) == 1000 and set(sizes) <= {lo for lo, _, _ in rows}
    assert rows[0][0] == 0 and all(a[0] + a[1] == b[0] for a, b in zip(rows, rows[1:])) and sum(rows[-1][:2]) == m and len({b for _, _, b in rows}) == len(rows)
    kept = [r.cell_id for r in Z.zero_cells(crowd, m, 0.01, 3, way, 64, "xxhash64").collect()]
    taken = set(range(at, at + 2000, 2))
    assert len(kept) == len(set(kept)) and not taken & set(kept) and min(kept) >= 0 and max(kept) < m
    assert abs(len(kept) - (m - 1000) * 0.01) < 6 * ((m - 1000) * 0.01) ** 0.5
    inside = [k for k in kept if at <= k < at + 2000]
    assert abs(len(inside) - 10) < 20


def test_long_laws_are_bisected(spark, monkeypatch):
    law, plan = KeepLaw(S.alpha_of(0.05), 3, 90.0), S.Plan(m=1 << 20, eps=0.05, mode="xxhash64")
    places = spark.range(60_000).selectExpr("id AS cell_id")

    def shares():
        return {r.x: r["count"] / 60_000 for r in places.selectExpr(f"{S.magnitude(law, plan)} AS x").groupBy("x").count().collect()}

    listed = shares()
    monkeypatch.setattr(S, "LISTED_CUTS", 10)
    halved = shares()
    for x in (3, 4, 10, 30, 89, 90, 91, 120):
        want = law.at_least(x) - law.at_least(x + 1)
        assert abs(halved.get(x, 0) - want) < 6 * (want / 60_000) ** 0.5 and abs(listed.get(x, 0) - want) < 6 * (want / 60_000) ** 0.5
    assert min(halved) == 3


def test_lowered_cut_has_the_lower_cuts_law(spark, cells):
    sizes, bands = [], []
    for seed in range(12):
        plan = replace(PLAN, seed=seed)
        high = S.high_pass(cells, plan, 20).select("cell_id", "value").persist()
        low = S.lower_cut(cells, high, plan, 20, 12).persist()
        rows = low.collect()
        assert len({r.cell_id for r in rows}) == len(rows) and min(abs(r.value) for r in rows) >= 12 and high.exceptAll(low).count() == 0
        direct = S.high_pass(cells, replace(plan, release="other"), 12).collect()
        sizes.append(len(rows) - len(direct))
        bands.append(sum(12 <= abs(r.value) < 16 for r in rows) - sum(12 <= abs(r.value) < 16 for r in direct))
    n = len(rows)
    assert abs(sum(sizes)) < 6 * (2 * 12 * n) ** 0.5 and abs(sum(bands)) < 6 * (2 * 12 * n) ** 0.5


def test_wide_domains_are_drawn_whole(spark):
    few = spark.createDataFrame([(5, 1)], "cell_id long, v long")
    m = (1 << 62) + 12_345
    z = [r.cell_id for r in zero_cells(few, m, 2000 / m, 1, "reject", mode="xxhash64").collect()]
    assert 1700 < len(z) < 2300 and len({x % 1024 for x in z}) > 800 and max(z) < m and sum(x > m // 2 for x in z) > 800
