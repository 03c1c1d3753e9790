"""The thin queries on the smallest tables: columns, types, digests; and the pipeline stage by stage."""

import hashlib
import math
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from sparse_release.llm import queries

from .test_shingle_join import kept_by_force
from .test_operators import SCHEMA, base_measures, base_spans, check_pieces, corpus, judge, plain_components, plain_fingerprint, plain_targets, plain_word_kernel, words

corpus_pipeline = pytest.importorskip("corpus_pipeline")
KINDS = ("assign", "access", "hex")


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}


def test_substring_query(spark, sf, texts):
    first = {}
    for i in sorted(texts):
        w = words(texts[i])
        for k in range(len(w) - 12):
            first.setdefault(tuple(w[k : k + 13]), i)
    for r in queries.op1_substring_dedup(spark, sf).collect():
        w = words(texts[r.doc_id])
        gone = [False] * len(w)
        for k in range(len(w) - 12):
            if first[tuple(w[k : k + 13])] < r.doc_id:
                gone[k : k + 13] = [True] * 13
        assert (r.n_words, r.n_removed) == (len(w), sum(gone))
        assert r.kept_sha256 == hashlib.sha256(" ".join(x for x, g in zip(w, gone) if not g).encode()).hexdigest()


def test_topk_query(spark, sf):
    import numpy as np

    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.floor(256 * np.array([r.embedding for r in rows], np.float32).astype(float))
    got = defaultdict(list)
    for r in queries.op2_topk_search(spark, sf).collect():
        got[r.query_id].append((r.rank, r.vec_id, r.score))
    for q in np.flatnonzero(ids % 50 == 0):
        s = x @ x[q]
        order = [k for k in np.lexsort((ids, -s)) if ids[k] != ids[q]][:5]
        assert sorted(got[ids[q]]) == [(k + 1, ids[o], int(s[o])) for k, o in enumerate(order)]


def test_quality_query(spark, sf, texts):
    for r in queries.op3_quality_rules(spark, sf).collect():
        n, chars, symbols, lines, repeats = base_measures(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, symbols, lines, repeats)
        assert r.base_failed == (n < 50 or 100 * repeats > 50 * n) and not (r.base_failed and r.kept)


def test_toxicity_query(spark, sf):
    out = queries.op4_toxicity(spark, sf)
    assert out.where("score < 0 OR score > 1 OR score IS NULL OR predicted != CAST(score >= 0.5 AS INT)").count() == 0
    assert out.where(F.col("held_out") != (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0)).count() == 0


def test_secret_query(spark, sf, texts):
    for r in queries.op7_secret_scan(spark, sf).collect():
        spans = base_spans(texts[r.doc_id])
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(s[1] == k for s in spans) for k in range(3))
        said = ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest() and set(filter(None, said.split(","))) <= set(r.spans.split(","))


def test_near_dup_query(spark, sf, texts):
    fps = {i: plain_fingerprint(t) for i, t in texts.items()}
    comp = plain_components([(i, f) for i, f in fps.items()])
    assert {(r.doc_id, r.fingerprint, r.component_id) for r in queries.op8_near_dup(spark, sf).collect()} == {(i, f"{f:016x}", comp[f]) for i, f in fps.items()}


def test_remaining_queries(spark, sf, texts):
    for name in ("op5_url_rules", "op6_license_scan", "op9_packing", "op10_source_mixing"):
        assert queries.QUERIES[name](spark, sf).count() > 0
    assert sum(r.length for r in queries.op9_packing(spark, sf).collect()) == sum(r.doc_tokens for r in queries.op9_packing(spark, sf).select("doc_id", "doc_tokens").distinct().collect())
    mix = queries.op10_source_mixing(spark, sf).collect()
    assert {r.doc_id: r.size for r in mix} == {i: len(words(t)) for i, t in texts.items()} and all(r.taken <= 2 * r.size for r in mix)


def test_stages_on_odd_rows(spark):
    """Nulls in every column, blank and long texts, repeated rows, clashing names; and empty tables."""
    rows = corpus(n=40)
    docs, none = spark.createDataFrame(rows, SCHEMA).repartition(3), spark.createDataFrame([], SCHEMA)
    stages = dict(corpus_pipeline.STAGES)
    for name, stage in stages.items():
        empty = stage(spark, none, "")
        assert empty.count() == 0 and (name == "packing" or empty.columns == docs.columns)
    good = stages["quality_rules"](spark, docs, "")
    assert good.columns == docs.columns and {r.text for r in good.collect()} <= {t for _, t, *_ in rows if base_measures(t)[0] >= 50}
    one = stages["near_duplicates"](spark, docs, "")
    assert one.columns == docs.columns and sorted(r.doc_id for r in one.collect() if r.doc_id is not None) == kept_by_force([r[:2] for r in dict.fromkeys(rows) if r[0] is not None])
    clean = stages["secret_scan"](spark, docs, "")
    assert clean.columns == docs.columns and Counter((r.doc_id, r.text, r.n_chars) for r in clean.collect()) == Counter((r[0], r[1], None if r[1] is None else len(r[1])) for r in rows)
    mixed = stages["source_mixing"](spark, docs, "")
    taken, have = Counter(r.doc_id for r in mixed.collect()), Counter(r[0] for r in rows)
    assert mixed.columns == docs.columns and all(n <= 2 * have[i] for i, n in taken.items()) and not any(words(r.text) == [] for r in mixed.collect())
    packed = stages["packing"](spark, docs, "").collect()
    whole = {r.doc_id: r.doc_tokens for r in packed}
    got = Counter()
    for r in packed:
        got[r.doc_id] += r.length
    assert all(got[i] == have[i] * whole[i] for i in have) and got[0] == 1
    bare = stages["secret_scan"](spark, docs.drop("n_chars"), "")
    assert bare.columns == [c for c in docs.columns if c != "n_chars"]


def test_url_query(spark, sf):
    for r in queries.op5_url_rules(spark, sf).join(spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "url"), "page_id").collect():
        assert (r.host, r.path, r.rule, r.verdict) == judge(r.url, queries.URL_RULES)


def test_mixing_query_meets_targets(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").collect()
    sizes = Counter()
    for r in docs:
        sizes[r.source] += len(words(r.text))
    want, taken, source = plain_targets(sizes), Counter(), {r.doc_id: r.source for r in docs}
    for r in queries.op10_source_mixing(spark, sf).collect():
        assert r.target == pytest.approx(want[source[r.doc_id]]) and r.source_size == sizes[source[r.doc_id]] and r.taken in (0, r.size, 2 * r.size)
        taken[source[r.doc_id]] += r.taken
    longest = max(len(words(r.text)) for r in docs)
    assert all(abs(taken[s] - want[s]) <= longest for s in want)


def test_toxicity_query_by_plain_scores(spark, sf):
    """The query's scores are those of its model over whole texts, read one by one."""
    from sparse_release.llm import toxicity

    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.fit(docs, labels.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0))
    got = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    marks = [w for ws in model.landmarks for w in ws]
    share = [x for ws, x in zip(model.landmarks, model.weights) for _ in ws]
    for r in docs.orderBy("n_chars").limit(25).collect():
        best = max((sum(x * plain_word_kernel(w.decode(), m.decode()) for m, x in zip(marks, share)) for w in toxicity.tokens(r.text) if w.isascii() and w.isalpha()), default=0.0)
        if all(w.isascii() and w.isalpha() for w in toxicity.tokens(r.text)):
            assert got[r.doc_id] == pytest.approx(1 / (1 + math.exp(-(model.slope * (best + model.offset) + model.base))), abs=1e-3)


def test_pipeline(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality_rules", "near_duplicates", "secret_scan", "source_mixing", "packing"]
    good = stages["quality_rules"](spark, docs, sf)
    kept = {r.doc_id: r.text for r in good.collect()}
    for r in docs.collect():
        n, _, _, _, repeats = base_measures(r.text)
        assert not (r.doc_id in kept and (n < 50 or 2 * repeats > n))
    one = stages["near_duplicates"](spark, good, sf)
    assert sorted(r.doc_id for r in one.collect()) == kept_by_force(kept.items())  # five words, similarity 0.8 or more
    clean = stages["secret_scan"](spark, one, sf)
    before, after = {r.doc_id: r.text for r in one.collect()}, {r.doc_id: r for r in clean.collect()}
    assert clean.columns == docs.columns and before.keys() == after.keys()
    assert all((after[i].text == t) == (not base_spans(t)) and not base_spans(after[i].text) and after[i].n_chars == len(after[i].text) for i, t in before.items())
    mixed = stages["source_mixing"](spark, clean, sf)
    copies = Counter((r.doc_id, r.text) for r in mixed.collect())
    assert mixed.columns == docs.columns and set(copies.values()) <= {1, 2} and all(after[i].text == t for i, t in copies)
    packed = stages["packing"](spark, mixed, sf)
    total = defaultdict(int)
    for r in packed.collect():
        total[r.doc_id] += r.length
    assert total.keys() == {i for i, _ in copies} and all(total[r.doc_id] == copies[r.doc_id, after[r.doc_id].text] * r.doc_tokens for r in packed.select("doc_id", "doc_tokens").distinct().collect())
    assert corpus_pipeline.run(spark, sf).columns == packed.columns and check_pieces
