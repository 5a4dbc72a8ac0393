import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from knnscope.llm import embdup, neardup


def brute(texts, words, similar):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append(frozenset(tuple(w[i : i + words]) for i in range(len(w) - words + 1)) if len(w) >= words else frozenset([tuple(w)] if w else []))
    name = list(range(len(texts)))
    while True:
        new = list(name)
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if i != j and a and 100 * len(a & b) >= similar * len(a | b):
                    new[i] = min(new[i], name[j])
        if new == name:
            return [len(s) for s in sets], name
        name = new


def families(seed=5, count=12):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    shared = [rng.choice(vocabulary) for _ in range(60)]  # a passage that many hold
    texts = [None, "", "one", "One", "two words", "two  words"]
    for f in range(count):
        base = [rng.choice(vocabulary) for _ in range(rng.choice((20, 80, 300, 900)))] + (shared if f % 2 else [])
        for _ in range(rng.choice((1, 3, 8))):
            own = list(base)
            for _ in range(int(len(own) * rng.choice((0, 0.005, 0.02, 0.03, 0.06)))):
                own[rng.randrange(len(own))] = rng.choice(vocabulary)
            texts.append(" ".join(own))
    return texts


@pytest.mark.parametrize(("words", "similar"), [(3, 85), (5, 80)])
def test_components_equal_brute_force(make_docs, words, similar):
    texts = families()
    sizes, names = brute(texts, words, similar)
    got = {r.doc_id: r for r in neardup.link(make_docs(texts), words, similar).collect()}
    assert len(got) == len(texts)
    for i in range(len(texts)):
        assert (got[i].n_shingles, got[i].component_id, got[i].kept) == (sizes[i], names[i], names[i] == i)
    kept = {r.doc_id for r in neardup.one_of_each(make_docs(texts), words, similar).collect()}
    assert kept == {i for i, n in enumerate(names) if n == i}


def test_filters_never_reject_what_is_similar_and_sketches_bound_the_difference():
    rng = np.random.default_rng(1)
    for n in (5, 40, 400, 3000):
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate([a[: int(len(a) * 0.95)], rng.integers(0, 2**63, n // 30, dtype=np.uint64)]))
        (ea, oa), (eb, ob) = neardup.odd_sketch(a), neardup.odd_sketch(b)
        differ = len(np.setxor1d(a, b))
        if ea == eb == 1:
            assert np.bitwise_count((oa ^ ob).view(np.uint64)).sum() <= differ
        sa, sb = (np.concatenate([neardup.signature(x), o])[None] for x, o in ((a, oa), (b, ob)))
        similar = 100 * len(np.intersect1d(a, b)) >= 85 * len(np.union1d(a, b))
        ok = neardup.close((np.array([len(a)]), np.array([ea]), sa), (np.array([len(b)]), np.array([eb]), sb), 85)
        assert bool(ok[0]) or not similar


def test_null_ids_and_repeated_rows_link_nothing_of_their_own(make_docs):
    docs = make_docs(["a b c d e f", "a b c d e f", "x y z"])
    odd = docs.unionByName(docs.withColumn("doc_id", F.lit(None).cast("long")))
    rows = sorted(((r.doc_id is None, r.doc_id or 0, r.component_id, r.kept) for r in neardup.link(odd.unionByName(docs)).collect()), key=str)
    assert [r for r in rows if r[0]] == [(True, 0, None, True)] * 3
    assert sorted(r[1:] for r in rows if not r[0]) == [(0, 0, True)] * 2 + [(1, 0, False)] * 2 + [(2, 2, True)] * 2


def test_empty_table(make_docs):
    assert neardup.link(make_docs([])).count() == 0


@pytest.mark.parametrize("rows_a_task", [7, 1000])
def test_embedding_links_equal_brute_force(spark, monkeypatch, rows_a_task):
    rng = np.random.default_rng(2)
    centres = rng.normal(size=(6, 16))
    x = np.concatenate([c + rng.normal(size=(25, 16)) * s for c in centres for s in (0.02, 0.12)])
    rows = [(i, v.astype(np.float32).tolist(), int(i % 3)) for i, v in enumerate(x)]
    rows += [(500, rows[3][1], 0), (501, [0.0] * 16, 0), (502, None, 1), (503, [float("nan")] * 16, 1), (504, rows[1][1], None), (505, [None] * 16, 1), (506, [1.0, 2.0], 1)]
    monkeypatch.setattr(embdup, "ROWS", rows_a_task)
    monkeypatch.setattr(embdup, "BLOCK", 16)
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").selectExpr("*", "1 AS rep", "2 AS cell")
    got = {r.vec_id: r for r in embdup.link(df, 0.98).collect()}
    usable = [r for r in rows if r[2] is not None and r[1] and None not in r[1] and np.isfinite(r[1]).all() and any(r[1])]
    names = {r[0]: r[0] for r in rows}
    links = {r[0]: set() for r in rows}
    for a in usable:
        for b in usable:
            if a[0] != b[0] and a[2] == b[2] and len(a[1]) == len(b[1]):
                u, v = np.array(a[1], float), np.array(b[1], float)
                if u @ v / (np.linalg.norm(u) * np.linalg.norm(v)) >= 0.98:
                    links[a[0]].add(b[0])
    for _ in rows:
        names = {i: min([names[i], *(names[j] for j in links[i])]) for i in names}
    assert sum(map(len, links.values())) > 50
    for i in names:
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (len(links[i]), names[i], names[i] == i), i
    assert embdup.link(df.limit(0)).count() == 0


def test_pivots_of_a_label_separate_its_groups(spark):
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(30, 24))
    x = np.concatenate([c + rng.normal(size=(40, 24)) * 0.02 for c in centres])
    df = spark.createDataFrame([(i, v.tolist(), 1 + (i % 2)) for i, v in enumerate(x)], "rep long, embedding array<double>, label long")
    df = df.selectExpr("label", "size(embedding) AS dim", "rep", "1L AS times", "embedding")
    placed = embdup.in_cells(df, 0.2).toPandas()
    assert placed["home"].sum() == len(x) and placed.groupby("label")["cell"].nunique().tolist() == [7, 7]
    assert len(placed) < 2 * len(x)  # without bounds every vector would be in about half of the cells
    assert sorted(placed[placed["home"]]["rep"]) == list(range(len(x)))
