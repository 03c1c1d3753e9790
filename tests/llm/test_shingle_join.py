"""The similarity join against brute force."""

from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparse_release.llm import near_dup, shingle_join

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def shingles(text, width=5):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])


def kept_by_force(rows):
    """The smallest id of each component of links of similarity 0.8 or more."""
    sets = {i: shingles(t) for i, t in rows}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in combinations(sorted(sets), 2):
        if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return sorted({find(i) for i in sets})


def test_stage_links_five_word_similarity(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = kept_by_force([(r.doc_id, r.text) for r in docs.collect()])
    assert sorted(r.doc_id for r in dict(corpus_pipeline.STAGES)["near_duplicates"](spark, docs, sf).collect()) == want


@pytest.mark.parametrize("crowd, block", [(64, 512), (3, 8)])
def test_similar_edges(spark, crowd, block):
    import random

    r, rows = random.Random(5), [(0, None), (1, ""), (2, "a b"), (3, "A  b"), (4, "a b c")]
    for base in range(6):
        w = [f"w{r.randrange(300)}" for _ in range(80)]
        for _ in range(12):
            v = list(w)
            for _ in range(r.randrange(4)):
                v[r.randrange(80)] = f"x{r.random()}"
            rows.append((len(rows), " ".join(v + ["one very common line at the end of all"] * (base % 2))))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    texts = docs.select(F.col("doc_id").alias("id"), "text", F.xxhash64("text").alias("th"))
    named = shingle_join.names(texts, 5).persist()
    edges = shingle_join.similar_edges(texts.select("text", "th"), named, 5, 0.8, crowd, block)
    root = {e.node: e.root for e in near_dup.components(edges).collect()}
    least = {}
    for x in named.collect():
        c = root.get(x.fp, x.fp)
        least[c] = min(least.get(c, x.id), x.id)
    assert sorted(least.values()) == kept_by_force(rows)


def test_index_comes_first(spark):
    """Pairs within the index's reach come from it, are checked whole, and are linked like the others; a set's fingerprint is that of its shingles."""
    import random

    r, rows = random.Random(7), []
    for base in range(5):
        w = [f"w{r.randrange(10_000)}" for _ in range(400)]
        for k in range(4):
            rows.append((len(rows), " ".join(w[:200] + [f"x{base}-{k}"] + w[200:])))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    texts = docs.select(F.col("doc_id").alias("id"), "text", F.xxhash64("text").alias("th"))
    named = shingle_join.names(texts, 5).persist()
    sets = {shingle_join.named(s): s for s in shingle_join.shingle_sets([t for _, t in rows], 5)}
    for x in named.collect():
        s = sets[x.fp % (1 << 64)]
        plain = sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in s.tolist()) > len(s))
        assert x.sim % (1 << 64) == plain == shingle_join.bits(s)
    pairs = near_dup.index_pairs(named.select("fp", "sim").distinct()).collect()
    assert pairs and all(p.a < p.b for p in pairs)
    calls, real = [], near_dup.index_pairs
    near_dup.index_pairs = lambda *a: calls.append(1) or real(*a)
    try:
        kept = dict(corpus_pipeline.STAGES)["near_duplicates"](spark, docs.selectExpr("doc_id", "text"), "")
        assert sorted(x.doc_id for x in kept.collect()) == kept_by_force(rows) and calls
    finally:
        near_dup.index_pairs = real


def test_few_edges_as_many(spark, monkeypatch):
    """Components of few edges, found in one process, are those of the rounds over tables."""
    import random

    r = random.Random(3)
    edges = spark.createDataFrame([(r.randrange(-90, 90), r.randrange(-90, 90)) for _ in range(80)], "a long, b long")
    few = sorted(map(tuple, near_dup.components(edges).collect()))
    monkeypatch.setattr(near_dup, "HELD", 0)
    assert few and few == sorted(map(tuple, near_dup.components(edges).collect()))


def test_long_lists_by_sketches(spark):
    """Long lists that overlap are compared one by one, by sketches that lose no pair: two never differ in more bits than their sets in shingles."""
    import random

    r, rows = random.Random(11), []
    lines = [" ".join(f"l{k}x{j}" for j in range(8)) for k in range(40)]
    for k in range(39):
        for _ in range(4):
            rows.append((len(rows), f"{lines[k]} u{r.random()} {lines[k + 1]}"))
    rows += [(len(rows) + k, rows[8 * k][1] + " tail") for k in range(10)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    texts = docs.select(F.col("doc_id").alias("id"), "text", F.xxhash64("text").alias("th"))
    named = shingle_join.names(texts, 5).persist()
    edges = shingle_join.similar_edges(texts.select("text", "th"), named, 5, 0.8, 3, 8).collect()
    sets = {i: shingles(t) for i, t in rows}
    names = {x.id: x.fp for x in named.collect()}
    alike = {tuple(sorted((names[a], names[b]))) for a, b in combinations(sets, 2) if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and names[a] != names[b]}
    found = {tuple(sorted((e.a, e.b))) for e in edges}
    stars = [[x.tolist() for x in near_dup.forest(*np.array(sorted(pairs)).T)] for pairs in (found, alike)]
    assert alike and found <= alike and stars[0] == stars[1]
    for a, b in combinations(shingle_join.shingle_sets([t for _, t in rows[::7]], 5), 2):
        x, y = shingle_join.sketch(a), shingle_join.sketch(b)
        if len(x) == len(y):
            assert sum(int(k).bit_count() for k in x ^ y) <= len(set(a.tolist()) ^ set(b.tolist()))


@pytest.mark.parametrize("links", [0, 10_000])
def test_long_lists_hand_on_few_pairs(spark, monkeypatch, tmp_path, links):
    """Sets of one large group meet in many lists, and most are not quite alike: the lists hand on no pair twice and only pairs at the bound; and no link is lost."""
    import random

    r, base = random.Random(13), " ".join(f"b{k}" for k in range(100))
    rows = [(k, " ".join([base, *(f"o{r.random()}" for _ in range(17))])) for k in range(40)]
    rows += [(len(rows) + k, " ".join([base, *(f"o{r.random()}" for _ in range(8))])) for k in range(12)]
    made, real = str(tmp_path / "made"), shingle_join._lists  # tasks run on this machine; accumulators do not reach them

    def counted(*args):
        run = real(*args)

        def go(batches):
            for b in run(batches):
                with open(made, "a") as f:
                    f.write(f"{b.num_rows}\n")
                yield b

        return go

    monkeypatch.setattr(shingle_join, "_lists", counted)
    monkeypatch.setattr(shingle_join, "LINKED", links, raising=False)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    texts = docs.select(F.col("doc_id").alias("id"), "text", F.xxhash64("text").alias("th"))
    named = shingle_join.names(texts, 5).persist()
    edges = shingle_join.similar_edges(texts.select("text", "th"), named, 5, 0.8, 3, 16)
    root, least = {e.node: e.root for e in near_dup.components(edges).collect()}, {}
    for x in named.collect():
        c = root.get(x.fp, x.fp)
        least[c] = min(least.get(c, x.id), x.id)
    assert sorted(least.values()) == kept_by_force(rows) and len(least) < len(rows)
    with open(made) as f:
        assert 0 < sum(map(int, f)) <= 40 * 12 + 2 * len(rows)  # those of similarity 0.793, once each
