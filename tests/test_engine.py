"""Domains, releases, ledger, streams, data source; and every query with an SQL twin."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sparse_release import queries as core
from sparse_release.operators.accountant import Accountant
from sparse_release.operators.contingency import contingency, density
from sparse_release.operators.domain import Domain, bucket, categorical, day, hour, int_range
from sparse_release.operators.summaries import Plan
from sparse_release.plans.release import release, suggest
from sparse_release.sources.synthetic import SyntheticSource
from sparse_release.streaming.windows import bound_batch, bound_stream, publish_windows, window_counts

from .compare import connect, difference

ROWS = [("x", 3, 10.0), ("y", 4, 25.0), (None, 3, 99.0), ("z", 9, float("nan")), ("x", 3, 10.0)]


def test_domain(spark):
    df = spark.createDataFrame(ROWS, "a string, b int, c double")
    dom = Domain((categorical("a", ["x", "y"], other=True), int_range("b", 3, 8), bucket("c", 10, 5)))
    assert dom.size == 75 and sorted(r.cell_id for r in dom.encode(df).collect()) == [1, 1, 32]
    clamped = Domain(dom.dims, "clamp").encode(df).collect()
    assert len(clamped) == 5 and max(r.cell_id for r in clamped) == 70
    cells = contingency(df, dom)
    back = {(r.a, r.b, r.c): r.v for r in dom.decode(cells).collect()}
    assert back == {("x", 3, 10.0): 2, ("y", 4, 20.0): 1}
    turned = Domain(dom.dims, order=("c", "b", "a"))
    assert {(r.a, r.b, r.c): r.v for r in turned.decode(contingency(df, turned)).collect()} == back
    assert contingency(df, dom, F.expr("CAST(c AS BIGINT)")).agg(F.sum("v")).first()[0] == 45
    assert density(cells, dom.size).first().n == 2
    with pytest.raises(ValueError):
        Domain((int_range("a", 0, 1 << 40), int_range("b", 0, 1 << 40))).encode(df)
    t = spark.sql("SELECT TIMESTAMP_NTZ'2024-01-02 03:30:00' AS ts")
    assert Domain((day("ts", "2024-01-01", 10),)).encode(t).first().cell_id == 1 and Domain((hour("ts", "2024-01-01 00:00:00", 100),)).encode(t).first().cell_id == 27


def test_release_and_ledger(spark, sf, tmp_path):
    rows = core.V.table(spark, sf, "customer")
    dom = core.V.v5(spark, sf)[1]
    ledger = Accountant(1.0)
    made = release(rows).over(dom).epsilon(0.5).method("filter_priority", cut=3, s=60).using(seed="s", release="a").run(ledger)
    assert made.summary.columns == ["cell_id", "value", "weight"] and made.summary.count() <= 60 and ledger.left() == pytest.approx(0.5)
    made.create_view("customers")
    total = spark.sql("SELECT SUM(weight) FROM released_customers").first()[0]
    assert total == pytest.approx(sum(r.estimate for r in made.group_by("c_mktsegment").collect())) and made.top(3).count() == 3
    assert made.where("c_nationkey < 25").first().estimate == pytest.approx(total)
    made.write(str(tmp_path / "r"))
    back = spark.read.parquet(str(tmp_path / "r" / "summary"))
    assert set(back.columns) == {"cell_id", "value", "weight", "c_nationkey", "c_mktsegment", "c_acctbal"} and "priority" not in spark.read.text(str(tmp_path / "r" / "meta")).first()[0].replace("filter_priority", "")
    for method, p in {"high_pass": {"cut": 5}, "threshold": {"tau": 9.0}, "filter_threshold": {"cut": 2, "tau": 9.0}, "priority": {"s": 50}, "uniform": {"fraction": 0.1}, "full": {}}.items():
        assert release(rows).over(dom).epsilon(0.5).method(method, **p).using(seed="s", release=method).run().summary.count() > 0
    with pytest.raises(ValueError):
        release(rows).over(dom).epsilon(0.9).method("full").using(seed="s", release="b").run(ledger)
    again = release(rows).over(dom).epsilon(0.5).method("filter_priority", cut=3, s=60).using(seed="s", release="a")
    assert again.run(ledger).summary.exceptAll(made.summary).count() == 0 and ledger.left() == pytest.approx(0.5)
    other = [again.epsilon(0.1), again.method("priority", s=60), again.over(core.V.v5b(spark, sf)[1]), release(rows.limit(100)).over(dom).epsilon(0.5).method("filter_priority", cut=3, s=60).using(seed="s", release="a")]
    for plan in other:
        with pytest.raises(ValueError, match="another release"):
            plan.run(ledger)
    plain = release(rows).over(dom).epsilon(0.5).method("full")
    for bad in (plain, plain.using(seed="s"), plain.using(release="x"), plain.using(seed="s", release="x", mode="md5"), plain.using(seed="s", release="x", mode="xxhash64")):
        with pytest.raises(ValueError):
            bad.run()
    bounded = release(core.V.table(spark, sf, "orders")).over(Domain((categorical("o_orderstatus", ["F", "O", "P"]),))).epsilon(0.5).method("full").each("o_custkey", 3, "o_orderkey").using(seed="s", release="y").run()
    assert bounded.meta["sensitivity"] == 3 and 0 < sum(r.value for r in bounded.summary.collect()) < 3 * 150 + 200
    assert suggest(10**6, 10**5, 10**7, 0.1, 10**5)["cut"] == 23
    ledger.spend("p1", 0.2, part="day/1")
    ledger.spend("p2", 0.4, part="day/2")
    assert ledger.spent() == pytest.approx(0.9) and ledger.spend("p2", 0.4, part="day/2") == pytest.approx(0.1)
    ledger.append_to(spark, str(tmp_path / "l"))
    assert Accountant.read(spark, str(tmp_path / "l"), 1.0).spent() == pytest.approx(0.9)


def test_a_name_is_not_used_twice():
    ledger = Accountant(1.0)
    assert ledger.spend("r", 0.1) == pytest.approx(0.9) == ledger.spend("r", 0.1)
    for change in ({"eps": 50.0}, {"eps": 0.2}, {"eps": 0.1, "part": "day/1"}, {"eps": 0.1, "digest": "other"}, {"eps": 0.1, "delta": 1e-9}):
        with pytest.raises(ValueError):
            ledger.spend("r", **change)
    assert ledger.left() == pytest.approx(0.9)


def test_stream(spark, sf, tmp_path):
    events = core.V.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartition(1).sortWithinPartitions("ts").write.parquet(str(tmp_path / "in"))
    dom = Domain((categorical("event_type", ["click", "error", "purchase", "signup", "view"]),))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    plan, spent = Plan(m=dom.size, eps=0.5), []
    for run in ("one", "two"):
        publish_windows(window_counts(stream, dom), plan, 2, 4.0, str(tmp_path / run), str(tmp_path / f"ck-{run}"), spent.append).awaitTermination()
    one, two = (spark.read.parquet(str(tmp_path / r)) for r in ("one", "two"))
    assert one.count() > 0 and one.exceptAll(two).count() == 0 == two.exceptAll(one).count() and len(set(spent)) * 2 == len(spent)
    batch = window_counts(events, dom)
    assert batch.agg(F.sum("v")).first()[0] == events.count()
    assert window_counts(events, dom, slide="12 hours").agg(F.sum("v")).first()[0] == 2 * events.count()
    assert window_counts(events, dom, length="30 minutes", session_key="user_id").agg(F.sum("v")).first()[0] == events.count()
    assert bound_batch(events, "user_id", 2, "event_id").groupBy("user_id", F.to_date("ts")).count().agg(F.max("count")).first()[0] == 2
    q = bound_stream(stream, "user_id", 2).writeStream.format("memory").queryName("bounded").option("checkpointLocation", str(tmp_path / "ck-b")).trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.table("bounded")
    assert out.columns == events.columns and out.groupBy("user_id", F.to_date("ts")).count().agg(F.max("count")).first()[0] == 2


def test_data_source(spark):
    spark.dataSource.register(SyntheticSource)
    rows = spark.read.format("sparse_release_synthetic").option("m", 10_000).option("rho", 0.1).load()
    assert 800 < rows.count() < 1200 and rows.select("cell_id").distinct().count() == rows.count() and rows.where("v < 1").count() == 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", sorted(core.ORACLE_SQL))
def test_twin(spark, sf, name):
    assert difference(core.QUERIES[name](spark, sf), connect(sf), core.ORACLE_SQL[name]) == ""


def test_trends(spark):
    """What wins where, as relations: hierarchies on long ranges, two-sided filters over one-sided ones, a lower cut's larger size."""
    from sparse_release.plans import experiments as X

    cells, m, n, total = X.gsyn(spark, 100_000)
    f = {(r.method, r.param): r for r in X.filter_sizes(cells, m, (20, 40), 5000, 60).collect()}
    assert all(f["filter_2_sided", c].abs_error < f["filter_1_sided", c].abs_error for c in (20.0, 40.0)) and f["filter_2_sided", 40.0].median_rel_error < 0.02
    s = {r.method: r for r in X.methods_by_size(cells, m, n, total, n, [1000], ranges=True, per_size=12).collect()}
    assert s["filter"].abs_error < s["geometric"].abs_error < s["priority"].abs_error < s["uniform"].abs_error
    assert s["filter_priority"].abs_error < s["priority"].abs_error and s["filter_priority"].rows == n
    d = {(r.method, r.size): r.abs_error for r in X.dyadic_ranges(cells, m, n, [100, 50_000], per_size=40).collect()}
    assert d["dyadic_geometric", 50_000] < d["flat_geometric", 50_000] and d["dyadic_geometric", 100] > d["flat_geometric", 100]
    clustered, m2, _, _ = X.gsyn(spark, 1 << 14, 0.05, places="clustered")
    c = {r.method: r.abs_error for r in X.consistency(clustered, m2, 500, [1000], 300, 40).collect()}
    assert c["filter_pruned"] < c["filter"]


def test_pick_theta_on_a_full_domain(spark, tmp_path):
    """Every cell of the seven attributes is occupied, as in large tables."""
    from sparse_release.sources import views as V

    at = lambda values, code: f"array({', '.join(repr(v) for v in values)})[CAST({code} AS INT)]"
    made = {
        "customer": spark.range(125).selectExpr("id AS c_custkey", "CAST(id % 25 AS INT) AS c_nationkey", f"{at(V.SEGMENTS, 'id div 25')} AS c_mktsegment"),
        "part": spark.range(25).selectExpr("id AS p_partkey", "concat('Brand#', id + 1) AS p_brand"),
        "orders": spark.range(1875).selectExpr("id AS o_orderkey", "id % 125 AS o_custkey", f"{at(V.PRIORITIES, 'id div 125 % 5')} AS o_orderpriority", f"{at(V.ORDER_STATUSES, 'id div 625')} AS o_orderstatus"),
        "lineitem": spark.range(281_250).selectExpr("id % 1875 AS l_orderkey", "id div 1875 % 25 AS l_partkey", f"{at(V.FLAGS, 'id div 46875 % 3')} AS l_returnflag", f"{at(V.STATUSES, 'id div 140625')} AS l_linestatus"),
    }
    for name, df in made.items():
        df.write.parquet(f"{tmp_path}/{name}.parquet")
    assert V.v2(spark, str(tmp_path))[0].count() == core.M2
    assert sorted(map(tuple, core.QUERIES["pick_theta"](spark, str(tmp_path)).collect())) == [(1, 1), (2, 1)]


def test_events_of_all_users(spark, sf, tmp_path):
    """Larger tables have users beyond the 1,500 that releases state, and hours outside the month."""
    events = spark.read.parquet(f"{sf}/events.parquet")
    more = events.selectExpr("event_id + 1000000 AS event_id", "ts - INTERVAL '3' HOUR AS ts", "user_id + 1500 AS user_id", "event_type", "value", "props")
    events.unionByName(more).write.parquet(f"{tmp_path}/events.parquet")
    con = connect(sf)
    con.execute(f"CREATE OR REPLACE VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    for name in ("density_v4", "contingency_v4"):
        assert difference(core.QUERIES[name](spark, str(tmp_path)), con, core.ORACLE_SQL[name]) == ""


READS = ["noise_histogram", "noise_moments", "keep_chances", "expected_sizes", "dyadic_cover", "ledger_report", "synthetic_workload", "synthetic_clustered"]


@pytest.mark.parametrize("name", READS)
def test_reads_its_table(spark, sf, tmp_path, name):
    """With a third of the rows gone, the result is another, and still that of the SQL."""
    con, table, key = connect(sf), *{"lineitem": ("lineitem", "l_orderkey"), "events": ("events", "event_id")}.get({"noise_histogram": "lineitem", "ledger_report": "events"}.get(name), ("orders", "o_orderkey"))
    spark.read.parquet(f"{sf}/{table}.parquet").where(f"{key} % 3 > 0").write.parquet(f"{tmp_path}/{table}.parquet")
    whole = sorted(map(tuple, core.QUERIES[name](spark, sf).collect()))
    con.execute(f"CREATE OR REPLACE VIEW {table} AS SELECT * FROM read_parquet('{tmp_path}/{table}.parquet/*.parquet')")
    fewer = core.QUERIES[name](spark, str(tmp_path))
    assert difference(fewer, con, core.ORACLE_SQL[name]) == "" and sorted(map(tuple, fewer.collect())) != whole


def test_plain_mechanism_is_not_written_out(spark, monkeypatch):
    """Answers of the plain mechanism and of the full tree are those of all their noisy rows, and need none of these kept: domains over MATERIALISED_CELLS are answered too."""
    import numpy as np

    from sparse_release.operators import baselines as B
    from sparse_release.operators import hierarchy as H
    from sparse_release.operators import summaries as S
    from sparse_release.plans import experiments as X
    from sparse_release.sources.synthetic import range_queries

    m = 9000
    cells, plan = spark.createDataFrame([(k * k % m, k + 1) for k in range(60)], "cell_id long, v long").dropDuplicates(["cell_id"]).persist(), X._plan(m)
    joined = spark.range(m).selectExpr("id AS cell_id").join(cells, "cell_id", "left").selectExpr("cell_id", f"coalesce(v, 0) + {plan.noise()} AS value")
    want = sorted(map(tuple, joined.collect()))
    assert sorted(map(tuple, S.all_noisy(cells, plan).collect())) == want
    asked = spark.createDataFrame([(0,), (25,), (4096,), (m - 1,)], "cell_id long")
    assert sorted(map(tuple, S.noisy_at(cells, plan, asked).collect())) == [w for w in want if w[0] in (0, 25, 4096, m - 1)]
    q, h = range_queries(spark, m, [1, 50, 5000], 20).persist(), H.height(m)
    weighted = S.full_geometric(cells, plan).selectExpr("*", "CAST(value AS DOUBLE) AS weight")
    flat, tree = X._scored("geometric", 0, weighted, cells, q), X._scored("tree", 7, B.full_dyadic(cells, h, plan), cells, q, estimate=lambda t: H.answer_dyadic(t, q, h))
    monkeypatch.setattr(S, "MATERIALISED_CELLS", 1000)
    rows = lambda df: sorted(tuple(r)[:-1] for r in df.collect())
    assert rows(X._scored_plain("geometric", cells, plan, q)) == rows(flat)
    assert rows(X._scored_tree("tree", 7, cells, h, plan, q)) == rows(tree)
    assert X.synthetic_data_baseline(cells, 90, 100, 900, [100], 5).count() == 2
    # the urn's means and spread are those of a multinomial with Dirichlet weights
    rng, at, v = np.random.default_rng(1), np.array([3]), np.array([6])
    drawn = np.zeros((4000, 4))
    for k in range(4000):
        place, n = B.urn(rng, 10, 2.0, 4, at, v)
        drawn[k, place] = n
    a, total = np.array([2.0, 2, 2, 8]), 14.0
    assert (drawn.sum(axis=1) == 10).all() and np.allclose(drawn.mean(axis=0), 10 * a / total, atol=0.12)
    assert np.allclose(drawn.var(axis=0), 10 * a / total * (1 - a / total) * (total + 10) / (total + 1), rtol=0.12)


def test_sums_of_large_domains(spark, monkeypatch):
    """What a dense summary of a large domain adds up to in a block is drawn at once: by moments as the cells one by one, and answers of all methods are as close as theirs."""
    import numpy as np

    from sparse_release.functions.laws import KeepLaw
    from sparse_release.operators import summaries as S
    from sparse_release.plans import experiments as X
    from sparse_release.sources.synthetic import range_queries

    a, x = 0.9, np.arange(1, 20_000)
    chance = 2 * (1 - a) / (1 + a) * a ** x.astype(float)
    for cut, tau in ((None, 0.0), (13, 0.0), (0, 25.3), (6, 7.2), (6, 40.0), (0, 500.5)):
        law = None if cut is None else KeepLaw(a, cut, tau or 1.0)
        keep = np.ones(len(x)) if law is None else np.where(x >= law.lo, np.minimum(1, x / tau) if tau else 1.0, 0)
        w, n = S.weight_sums(np.random.default_rng(1), np.full(40_000, 1000), a, law, tau)
        variance = 1000 * (chance * keep * np.maximum(x, tau) ** 2).sum()
        assert abs(w.mean()) < 5 * np.sqrt(variance / 40_000) and abs(w.var() / variance - 1) < 0.05
        assert (n == 1000).all() if law is None else abs(n.mean() / (1000 * (chance * keep).sum()) - 1) < 0.01
    m = 100_000_000_000  # drawn cell by cell, this would not end
    cells = spark.range(3000).selectExpr("id * 33000001 + 5 AS cell_id", "id % 50 + 1 AS v").persist()
    plan = X._plan(m, eps=1.0)
    sums = S.empty_sums(cells, plan, 1 << 22).selectExpr("count(*) AS b", "sum(n) AS n", "avg(w) AS w", "variance(w) / avg(n) AS v").first()
    assert sums.b == (m + (1 << 22) - 1) >> 22 and sums.n == m - 3000 and abs(sums.v / (2 * plan.alpha / (1 - plan.alpha) ** 2) - 1) < 0.05
    assert sorted(map(tuple, S.empty_sums(cells.repartition(3), plan, 1 << 22).collect())) == sorted(map(tuple, S.empty_sums(cells, plan, 1 << 22).collect()))
    monkeypatch.setattr(X, "BLOCK", 64)
    monkeypatch.setattr(X, "DRAWN_CELLS", 1000)
    small = range_queries(spark, 20_000, [50, 5000], 60).persist()
    few, plan = cells.where("cell_id < 1").unionByName(spark.range(900).selectExpr("id * 22 AS cell_id", "id % 50 + 1 AS v")), X._plan(20_000, eps=1.0)
    got = {r.size: r for r in X._scored_plain("geometric", few, plan, small).collect()}
    assert {r.rows for r in got.values()} == {20_000} and all(r.seconds is None for r in got.values())
    for size in (50, 5000):
        assert 0.5 < got[size].abs_error / np.sqrt(size * 2 * plan.alpha / (1 - plan.alpha) ** 2 * 2 / np.pi) < 1.7


def test_values_without_higher_order_functions(spark):
    """Magnitudes looked up in batches are those of the SQL, and the plan has no interpreted function."""
    from sparse_release.functions.laws import KeepLaw
    from sparse_release.operators import summaries as S

    plan, places = S.Plan(m=1 << 40, eps=0.1), spark.range(3000).selectExpr("id * 7 AS cell_id", "id AS k")
    for cut, tau in ((13, 1.0), (0, 25.3), (6, 40.5), (0, 90_000.5), (300, 9000.0)):
        law = KeepLaw(plan.alpha, cut, tau)
        sign = f"CASE WHEN {plan.u('sign')} < 0.5D THEN -1 ELSE 1 END"
        got = S.valued(places, law, plan)
        assert got.columns == ["cell_id", "k", "value"] and "lambda" not in got._jdf.queryExecution().optimizedPlan().toString()
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, places.selectExpr("cell_id", "k", f"CAST({sign} * ({S.magnitude(law, plan)}) AS BIGINT) AS value").collect()))


def test_dense_summaries_of_large_domains(spark, monkeypatch):
    """Dense filters, flat and as hierarchies, and the sketch of all noisy cells are answered without laying them out, as closely as when they are."""
    from sparse_release.functions.laws import KeepLaw
    from sparse_release.operators import hierarchy as H
    from sparse_release.operators import sketch as K
    from sparse_release.operators import summaries as S
    from sparse_release.plans import experiments as X

    m = 9000
    cells = spark.range(900).selectExpr("id * 10 + id % 7 AS cell_id", "id % 90 + 30 AS v").persist()
    n, total = 900, float(cells.selectExpr("sum(v)").first()[0])
    by = lambda df: {(r["method"], r["size"]): r for r in df.collect()}
    flat = lambda: by(X.methods_by_size(cells, m, n, total, n, [1000], filter_cut=13, combined_cut=6, ranges=True, per_size=20))
    near = lambda a, b: abs(a - b) < 0.1 * b + 60
    small = flat()
    trees = by(X.consistency(cells, m, 100, [1000], 300, 40))
    monkeypatch.setattr(X, "DRAWN_CELLS", 500)
    large = flat()
    for name in ("geometric", "filter", "filter_threshold"):
        a, b = large[name, 1000], small[name, 1000]
        assert a.seconds is None and b.seconds is not None and near(a.rows, b.rows) and a.abs_error < 2.5 * b.abs_error + 100 and b.abs_error < 2.5 * a.abs_error + 100, name
    # of a tree, covers and pruned nodes are those of the filter over all its noisy nodes
    h, plan = H.height(m), X._plan(m)
    kept = H.hier_release(cells, h, X.replace(plan, route="materialised"), lambda c, p: S.high_pass(c, p, 300)).persist()
    got, q = by(X.consistency(cells, m, 100, [1000], 300, 40)), X.range_queries(spark, m, [1000], 40)
    want = X._scored("filter", 300, kept, cells, q, estimate=lambda t: H.answer_dyadic(t, q, h)).first()
    pruned = X._scored("filter_pruned", 300, H.prune(kept, h), cells, q, estimate=lambda t: H.answer_dyadic(t, q, h)).first()
    assert got["filter", 1000].abs_error == want.abs_error and near(got["filter", 1000].rows, want.rows) and got["filter", 1000].seconds is None
    assert (got["filter_pruned", 1000].abs_error, got["filter_pruned", 1000].rows) == (pruned.abs_error, pruned.rows) and set(got) == set(trees)
    # the sketch: the same buckets for asked and occupied cells, the noise of all others by their number
    asked = spark.range(40).selectExpr("id * 3 AS cell_id")
    sums = K.sketch_of_noisy_sums(cells, X._plan(2_000_000), 800, asked)
    whole = K.sketch_of_noisy(cells, X._plan(2_000_000), 800, 1)
    spread = lambda df: df.selectExpr("count(*) AS n", "stddev(v) AS sd").first()
    a, b = spread(sums), spread(whole)
    assert a.n == b.n == 800 and 0.85 < a.sd / b.sd < 1.18
    assert K.sketch_of_noisy_sums(cells, X._plan(2 << 40), 50_000, asked).count() == 50_000
    # rows of a throughput are timed in domains of any size
    monkeypatch.setattr(S, "MATERIALISED_CELLS", 1000)
    assert X.throughput(spark, {"v": (cells, m, n)}, only=("geometric", "dyadic_geometric")).count() == 2
    assert KeepLaw(plan.alpha, 13).keep() * m > 500
