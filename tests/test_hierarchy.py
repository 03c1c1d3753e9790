"""Hierarchies, covers, Haar answers, consistency, sketches: hand examples and exactness without noise."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from sparse_release.functions.registered import dyadic_nodes, register
from sparse_release.operators import baselines as B
from sparse_release.operators import hierarchy as H
from sparse_release.operators import sketch as K
from sparse_release.operators import summaries as S
from sparse_release.sources.synthetic import range_queries, synthetic

HAND = [(3, 10), (4, 1), (15, 7)]


@pytest.fixture(scope="module")
def hand(spark):
    return spark.createDataFrame(HAND, "cell_id long, v long")


def test_hand_nodes(spark, hand):
    want = {(0, 3): 10, (0, 4): 1, (0, 15): 7, (1, 1): 10, (1, 2): 1, (1, 7): 7, (2, 0): 10, (2, 1): 1, (2, 3): 7, (3, 0): 11, (3, 1): 7, (4, 0): 18}
    for rows in (H.dyadic(hand, 4), H.dyadic(hand, 4, step=2), H.dyadic_at_once(hand, 4)):
        assert {(r.level, r.pos): r.v for r in rows.collect()} == want
    q = spark.createDataFrame([(1, 3, 16)], "qid long, lo long, hi long")
    assert sorted((r.level, r.pos) for r in H.dyadic_cover(q, 4).collect()) == [(0, 3), (2, 1), (3, 1)]
    assert H.answer_dyadic(H.dyadic(hand, 4), q, 4, "v").first().estimate == 18
    haar = {(r.level, r.pos): r.v for r in H.haar(hand, 4).collect()}
    assert haar == {(5, 0): 18, (4, 0): 4, (3, 0): 9, (3, 1): -7, (2, 0): -10, (2, 1): 1, (2, 3): -7, (1, 1): -10, (1, 2): 1, (1, 7): -7}


def test_numbers_go_back_and_forth(spark):
    h = 6
    nodes = spark.createDataFrame([(k, p) for k in range(h + 1) for p in range(1 << (h - k))], "level int, pos long").selectExpr("level", "pos", f"{H.node_id(h)} AS cell_id")
    assert sorted(r.cell_id for r in nodes.collect()) == list(range((2 << h) - 1))
    a, b = H.node_of(h)
    assert nodes.where(f"{a} != level OR {b} != pos").count() == 0
    coef = spark.createDataFrame([(k, p) for k in range(1, h + 1) for p in range(1 << (h - k))] + [(h + 1, 0)], "level int, pos long").selectExpr("level", "pos", f"CAST({H.haar_id(h)} AS BIGINT) AS cell_id")
    assert sorted(r.cell_id for r in coef.collect()) == list(range(1 << h))
    a, b = H.haar_of(h)
    assert coef.where(f"{a} != level OR {b} != pos").count() == 0


def test_hand_pruning(spark):
    nodes = spark.createDataFrame([(4, 0), (3, 0), (2, 1), (1, 2), (0, 4), (1, 7), (0, 15)], "level int, pos long").withColumn("value", F.lit(1))
    assert sorted((r.level, r.pos) for r in H.prune(nodes, 4).collect()) == [(0, 4), (1, 2), (2, 1), (3, 0), (4, 0)]


def test_covers_and_exact_answers(spark):
    m = 1 << 10
    cells, q = synthetic(spark, m, 0.1), range_queries(spark, m, [1, 7, 64, 500, m], 8)
    data = {r.cell_id: r.v for r in cells.collect()}
    truth = {r.qid: sum(v for c, v in data.items() if r.lo <= c < r.hi) for r in q.collect()}
    assert {r.qid: r.estimate for r in H.answer_dyadic(H.dyadic(cells, 10), q, 10, "v").collect()} == truth
    assert {r.qid: round(r.estimate, 6) for r in H.answer_haar(H.haar(cells, 10), q, 10, "v").collect()} == truth
    cover = {}
    for r in H.dyadic_cover(q, 10).collect():
        cover.setdefault(r.qid, []).append((r.level, r.pos))
    for r in q.collect():
        assert sorted(cover[r.qid]) == sorted(dyadic_nodes(r.lo, r.hi, 10)) and len(cover[r.qid]) <= 20
    register(spark)
    assert spark.sql("SELECT count(*) FROM dyadic_cover(3, 16, 4)").first()[0] == 3
    assert spark.sql("SELECT min(geo_noise(0.9D, 's', CAST(id AS STRING))) < 0 AND max(prf_uniform('s', 't', CAST(id AS STRING))) < 1 FROM range(100)").first()[0]


def test_consistent_filter_is_filter_then_prune(spark):
    cells = synthetic(spark, 1 << 9, 0.1, places="clustered")
    plan = S.Plan(m=1 << 9, eps=1.0)
    both = H.prune(H.hier_release(cells, 9, replace(plan, route="materialised"), lambda c, p: S.high_pass(c, p, 40)), 9).select("level", "pos", "value")
    down = H.consistent_filter(cells, 9, plan, 40).select("level", "pos", "value")
    assert both.count() > 0 and both.exceptAll(down).count() == 0 == down.exceptAll(both).count()
    kept, tau = H.filter_prune_priority(cells, 9, plan, 20, 30)
    assert kept.count() == 30 and tau > 0


def test_full_hierarchies(spark, hand):
    plan = S.Plan(m=16, eps=50.0)
    q = spark.createDataFrame([(1, 3, 16), (2, 0, 4), (3, 15, 16)], "qid long, lo long, hi long")
    assert B.full_dyadic(hand, 4, plan).count() == 31 and B.full_haar(hand, 4, plan).count() == 16
    assert {r.qid: round(r.estimate) for r in H.answer_haar(B.full_haar(hand, 4, plan), q, 4).collect()} == {1: 18, 2: 10, 3: 7}
    assert {r.qid: round(r.estimate) for r in H.answer_haar(B.haar_weighted(hand, 4, 5000.0), q, 4).collect()} == {1: 18, 2: 10, 3: 7}


def test_sketch(spark):
    cells = synthetic(spark, 2000, 0.05)
    sk = K.count_sketch(cells, 4096, 5)
    got = {r.cell_id: r.estimate for r in K.sketch_point(sk, cells, 4096, 5, how="median").collect()}
    data = {r.cell_id: r.v for r in cells.collect()}
    assert sum(got[c] == v for c, v in data.items()) > 0.95 * len(data)
    assert K.private_sketch(cells, 64, 3, 0.5).count() == 192
    assert abs(sum(data.values()) - K.sketch_sum(sk, cells.selectExpr("1 AS qid", "cell_id"), 4096, 5, how="median").first().estimate) < 0.05 * sum(data.values())


def test_boxes(spark):
    rows = spark.range(300).selectExpr("CAST(pmod(xxhash64(id), 16) AS BIGINT) AS a", "CAST(pmod(xxhash64(id, 1), 8) AS BIGINT) AS b", "1 AS v")
    boxes = spark.createDataFrame([(1, 2, 9, 1, 7), (2, 0, 16, 0, 8)], "qid long, a_lo long, a_hi long, b_lo long, b_hi long")
    got = {r.qid: r.estimate for r in H.answer_nd(H.dyadic_nd(rows, {"a": 4, "b": 3}), boxes, {"a": 4, "b": 3}).collect()}
    assert got == {1: sum(2 <= r.a < 9 and 1 <= r.b < 7 for r in rows.collect()), 2: 300}


def test_private_grid_hierarchy(spark):
    heights = {"x": 4, "y": 3}
    rows = spark.range(300).selectExpr("id % 16 AS x", "(id * 7) % 8 AS y", "1L AS v")
    plan = S.Plan(m=0, eps=5000.0, mode="xxhash64")
    seen = []

    def keep(c, p):
        seen.append(p)
        return S.high_pass(c, p, 1)

    got = H.release_nd(rows, heights, plan, keep)
    assert seen[0].sensitivity == 5 * 4 and seen[0].m == 31 * 15
    want = {(r.x_level, r.x_pos, r.y_level, r.y_pos): r.v for r in H.dyadic_nd(rows, heights).collect()}
    assert {(r.x_level, r.x_pos, r.y_level, r.y_pos): r.value for r in got.collect()} == want
    boxes = spark.createDataFrame([(1, 3, 11, 0, 5), (2, 0, 16, 0, 8), (3, 7, 8, 2, 3)], "qid long, x_lo long, x_hi long, y_lo long, y_hi long")
    answers = {r.qid: r.estimate for r in H.answer_nd(got, boxes, heights, "weight").collect()}
    points = [(k % 16, (k * 7) % 8) for k in range(300)]
    assert answers == {q: float(sum(a <= x < b and c <= y < d for x, y in points)) for q, a, b, c, d in [(1, 3, 11, 0, 5), (2, 0, 16, 0, 8), (3, 7, 8, 2, 3)]}
