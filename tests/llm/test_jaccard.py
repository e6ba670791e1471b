import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from structcurve.llm import jaccard as J


def shingles(text, n=5):
    w = re.findall(r"\w+", text.lower())
    n = min(n, len(w))
    return frozenset(tuple(w[i : i + n]) for i in range(len(w) - n + 1)) if n else frozenset()


def brute(rows, t=0.8):
    sets = {i: shingles(x) for i, x in rows}
    ids = sorted(sets)
    root, links = {i: i for i in ids}, dict.fromkeys(ids, 0)

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[k + 1 :]:
            a, b = sets[i], sets[j]
            both = len(a & b)
            if (not a and not b) or (a or b) and both >= t * (len(a) + len(b) - both) - 1e-9:
                links[i] += 1
                links[j] += 1
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return {i: (find(i), links[i]) for i in ids}


def corpus(seed=0, groups=12):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choices("abcdefghij", k=5))
    passage = [word() for _ in range(40)]
    rows, i = [], 0
    for g in range(groups):
        base = [word() for _ in range(rng.randint(3, 250))]
        for _ in range(rng.choice((1, 1, 2, 5, 25))):
            copy = list(base)
            for _ in range(rng.randint(0, max(1, len(copy) // 40))):
                copy[rng.randrange(len(copy))] = word()
            rows.append((i, " ".join(copy + (passage if g % 3 == 0 else []))))
            i += 1
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("bucket,block", [(1000, 400), (6, 5)])
def test_against_brute_force(spark, monkeypatch, bucket, block):
    """Small limits force splitting along paths, block pairs in buckets and block pairs in verification."""
    monkeypatch.setattr(J, "BUCKET", bucket)
    monkeypatch.setattr(J, "BLOCK", block)
    rows = corpus(bucket)
    got = J.similar_documents(spark.createDataFrame(rows, "doc_id bigint, text string"), recall=0.9999).collect()
    assert {r.doc_id: (r.class_id, r.n_links) for r in got} == brute(rows)


def test_keep_one(spark):
    rows = corpus(7)
    want = {c for c, _ in brute(rows).values()}
    assert {r.doc_id for r in J.keep_one(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()} == want


def test_signature_estimates_similarity():
    rng = np.random.default_rng(1)
    pool = J.mix(np.arange(1, 4001, dtype=np.uint64))
    gaps = []
    for _ in range(20):
        a, b = pool[rng.random(4000) < 0.3], None
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.9], pool[rng.random(4000) < 0.02]]))
        exact = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        gaps.append((J.signature(a) == J.signature(b)).mean() - exact)
    assert abs(np.mean(gaps)) < 0.03 and np.std(gaps) < 0.08


def test_intersections():
    rng = np.random.default_rng(3)
    sets = [np.unique(rng.integers(0, 300, rng.integers(1, 200))).astype(np.uint64) for _ in range(30)]
    got = J.intersections(sets)
    assert all(got[i, j] == len(np.intersect1d(sets[i], sets[j])) for i in range(30) for j in range(30) if i != j)


def test_runs_grow_with_recall():
    assert J.runs_for(0.9) < J.runs_for(0.99) < J.runs_for(0.999)


def test_components(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(40)]
    root = {v: v for e in edges for v in e}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in J.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert all(got.get(v, v) == find(v) for v in root)


def test_an_id_on_two_texts_is_two_documents(spark):
    rng = random.Random(2)
    text = lambda: " ".join("".join(rng.choices("abcdefghij", k=5)) for _ in range(60))
    a, b = text(), text()
    rows = [(1, a), (1, b), (2, a), (3, b), (4, a + " more"), (None, a), (None, a), (5, text()), (5, rows5 := text()), (5, rows5)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({c: F.lit(1) for c in ("_extra", "id", "row", "head", "a.b", "n")})
    kept = J.keep_one(docs)
    assert kept.columns == docs.columns
    got = sorted((r.doc_id or 0, r.text) for r in kept.collect())
    assert got == sorted([(1, a), (1, b), (0, a), (0, a), rows[7], (5, rows5)])
    links = sorted((r.doc_id or 0, r.class_id or 0, r.n_links) for r in J.similar_documents(docs).collect())
    assert links == [(0, 0, 0), (0, 0, 0), (1, 1, 1), (1, 1, 2), (2, 1, 2), (3, 1, 1), (4, 1, 2), (5, 5, 0), (5, 5, 1), (5, 5, 1)]


def test_recall_at_the_default():
    """Pairs of similarity 0.80 to 0.83 meet in some run and look alike on sketches."""
    rng = np.random.default_rng(9)
    runs, met, n = J.runs_for(0.995), 0, 600
    least = int(np.ceil((0.8 - 0.12) * J.POSITIONS))
    for i in range(n):
        pool = J.mix(np.arange(i * 5000 + 1, i * 5000 + 261, dtype=np.uint64))
        same = int(rng.integers(160, 166))
        a, b = pool[: same + 20], np.concatenate([pool[:same], pool[200:220]])
        x, y = J.signature(np.unique(a)), J.signature(np.unique(b))
        keys = [set(J.first_keys(s, runs, 0.8).tolist()) for s in (x, y)]
        alike = ((x & np.uint64(255)) == (y & np.uint64(255))).sum() >= least
        met += bool(keys[0] & keys[1]) and bool(alike)
    assert met / n >= 0.985, met / n
