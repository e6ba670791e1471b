import random

import numpy as np

from structcurve.llm import quality as Q


def test_trees_learn_and_traverse():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(3000, 6))
    y = ((x[:, 0] > 0.3) ^ (x[:, 1] * x[:, 2] > 0)).astype(float)
    m = Q.train_trees(x[:2000], y[:2000], trees=60)
    assert ((m.predict(x[2000:]) > 0.5) == y[2000:]).mean() > 0.9

    def walk(row):
        total = m.base
        for r in m.roots:
            n = r
            while m.left[n] != n:
                n = m.left[n] if row[m.feature[n]] <= m.threshold[n] else m.right[n]
            total += m.value[n]
        return total

    assert np.allclose(m.raw(x[:50]), [walk(r) for r in x[:50]])


def test_one_class_and_no_rows():
    x = np.ones((5, 3))
    assert np.allclose(Q.train_trees(x, np.ones(5)).predict(x), 1, atol=1e-3)
    assert Q.train_trees(np.zeros((0, 3)), np.zeros(0)).predict(x).tolist() == [0.5] * 5


def test_features_are_finite():
    texts = ["", " ", "\n\n", "a", "!!!", "|||" * 5, "A B\nA B\nA B", "é" * 1000, "x" * 100_000]
    m = Q.feature_matrix(texts)
    assert m.shape == (len(texts), len(Q.FEATURES)) and np.isfinite(m).all()


def test_held_out_accuracy(spark):
    rng = random.Random(2)
    word = lambda: "".join(rng.choices("abcdefgh", k=rng.randint(2, 9)))
    rows, labels = [], []
    for i in range(600):
        words = [word() for _ in range(rng.randint(30, 120))]
        bad = i % 4 == 0
        rows.append((i, " ".join(w.upper() + "!!" for w in words) if bad else " ".join(words) + "."))
        labels.append((i, int(not bad), 0))
    got = Q.quality(spark.createDataFrame(rows, "doc_id bigint, text string"), spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int")).collect()
    held = [r for r in got if r.held_out]
    assert held and sum(r.predicted == int(r.doc_id % 4 != 0) for r in held) / len(held) > 0.97
