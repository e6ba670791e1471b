"""Inverted indexes against brute force: decontamination and toxicity."""

import math
import random
from collections import Counter

import numpy as np

from structcurve.llm import decontaminate as D
from structcurve.llm import toxicity as T


def brute_scores(items, words, k1=1.2, b=0.75):
    docs = [(i, D.words_of(t)) for i, t in sorted(items) if D.words_of(t)]
    df = Counter(w for _, ws in docs for w in set(ws))
    mean = sum(len(ws) for _, ws in docs) / len(docs)

    def score(ws, query):
        c = Counter(ws)
        return sum(math.log(1 + (len(docs) - df[t] + 0.5) / (df[t] + 0.5)) * c[t] * (k1 + 1) / (c[t] + k1 * (1 - b + b * len(ws) / mean)) for t in set(query) if t in c)

    return {i: score(ws, words) / score(ws, ws) for i, ws in docs}


def test_all_items_above_the_threshold_are_found():
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(60)]
    items = [(i, " ".join(rng.choices(vocab, k=rng.randint(5, 25)))) for i in range(50)]
    index = D.ItemIndex(items, block=4)
    for _ in range(60):
        words = rng.choices(vocab + ["zzz"], k=40)
        ids = np.array([index.terms.get(w, len(index.terms)) for w in words])
        found = {index.ids[i]: s for _, i, s in index.candidates(ids, len(words), 0.4)}
        exact = {i: s for i, s in brute_scores(items, words).items() if s >= 0.4 + 1e-9}
        assert set(exact) <= set(found) and all(abs(found[i] - s) < 1e-9 for i, s in exact.items())


def test_windows_are_searched_like_passages_of_their_own(monkeypatch):
    rng = random.Random(8)
    vocab = [f"w{i}" for i in range(50)]
    items = [(i, " ".join(rng.choices(vocab, k=rng.randint(5, 25)))) for i in range(40)]
    index = D.ItemIndex(items, block=4)
    for n in (1, 9, 10, 11, 20, 21, 95, 300):
        words = rng.choices(vocab, k=n)
        ids = np.array([index.terms.get(w, len(index.terms)) for w in words])
        got = {(w, index.ids[i]): s for w, i, s in index.candidates(ids, 10, 0.45)}
        want = {}
        for w in range(max(1, -(-n // 10) - 1)):
            want |= {(w, i): s for i, s in brute_scores(items, words[w * 10 : (w + 2) * 10]).items() if s >= 0.45 - 1e-12}
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_a_full_index_is_small_and_fast():
    """8 MB of items and one text of 20,000 words: memory and time stay bounded."""
    import pickle
    import time

    rng = np.random.default_rng(5)
    vocab = np.array([f"{'abcdefghij'[i % 10]}{i}" for i in range(60_000)])
    zipf = lambda n: vocab[np.minimum(59_999, (rng.pareto(0.9, n) * 300).astype(int))]
    items, size = [], 0
    while size < D.INDEX_BYTES:
        t = " ".join(zipf(60))
        items.append((len(items), t))
        size += len(t)
    index = D.ItemIndex(items)
    assert len(pickle.dumps(index)) < 150 << 20
    words = zipf(20_000).tolist()
    words[10_000:10_000] = items[77][1].split()
    text = " ".join(words)
    index.matches(text[:500], 0.5, 0.5)
    start = time.thread_time()
    found = index.matches(text, 0.5, 0.5)
    took = time.thread_time() - start
    assert 77 in {f[0] for f in found} and took < 2, took


def test_planted_passages(spark):
    rng = random.Random(1)
    noise = lambda n: " ".join("".join(rng.choices("abcdefgh", k=6)) for _ in range(n))
    items = [(i, noise(rng.randint(15, 60)) + ". " + noise(6) + ".") for i in range(30)]
    rows = [(i, noise(rng.randint(0, 300)) + " " + (items[i][1].upper() if i % 3 == 0 else "") + " " + noise(200)) for i in range(30)]
    rows += [(100, " ".join(items[0][1].split()[:8]) + " " + noise(50))]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = {(r.doc_id, r.item_id) for r in D.contamination(docs, bench).collect()}
    assert got == {(i, i) for i in range(0, 30, 3)}
    kept = {r.doc_id for r in D.decontaminate(docs, bench).collect()}
    assert kept == {r[0] for r in rows} - {i for i in range(0, 30, 3)}


def test_one_index_and_many_agree(spark, monkeypatch):
    rng = random.Random(7)
    vocab = [f"w{i}" for i in range(40)]
    texts = [" ".join(rng.choices(vocab, k=rng.randint(6, 40))) + ". " + " ".join(rng.choices(vocab, k=5)) + "." for _ in range(40)] + ["", "!?"]
    docs = [(i, " ".join(rng.choices(vocab, k=30)) + " " + " ".join(t.split()[rng.randint(0, 3) :]) + " " + " ".join(rng.choices(vocab, k=90))) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(docs, "doc_id bigint, text string")
    bench = spark.createDataFrame(list(enumerate(texts)), "item_id bigint, text string")
    one = sorted(map(tuple, D.contamination(docs, bench, overlap=0.3).collect()))
    kept = sorted(r.doc_id for r in D.decontaminate(docs, bench, overlap=0.3).collect())
    monkeypatch.setattr(D, "INDEX_BYTES", 1500)
    assert sum(1 for _ in D.item_indexes(bench)) > 2
    assert one and sorted(map(tuple, D.contamination(docs, bench, overlap=0.3).collect())) == one
    assert sorted(r.doc_id for r in D.decontaminate(docs, bench, overlap=0.3).collect()) == kept


def test_question_and_answer_of_one_sentence():
    q, a = D.question_and_answer("one two three four five six")
    assert (q, a) == (["one", "two", "three", "four"], ["five", "six"])
    assert D.question_and_answer("What is it? It is this.") == (["what", "is", "it"], ["it", "is", "this"])


def test_nearest_examples_are_exact():
    rng = np.random.default_rng(2)
    vectors = []
    for _ in range(300):
        terms = np.sort(rng.choice(40, size=rng.integers(1, 6), replace=False))
        w = rng.random(len(terms))
        vectors.append((terms, w / np.linalg.norm(w)))
    for block in (4, 16, 64):
        index = T.BlockMaxIndex(vectors, 40, block=block)
        for q in vectors[::7]:
            near, sims = index.search(q, 10)
            brute = T.plain_neighbours(vectors, q, 10)
            assert near.tolist() == [i for i, _ in brute] and np.allclose(sims, [s for _, s in brute])
        assert index.search(vectors[5], 3, without=5)[0].tolist() == [i for i, _ in T.plain_neighbours(vectors, vectors[5], 4) if i != 5][:3]


def test_score_against_brute_force(spark):
    """The whole score by plain loops: frequencies, weights, all cosines, the vote and its calibration."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    model = T.fit_toxicity(docs, spark.read.parquet("/root/testdata/sf0.01/labels.parquet"))
    rows = docs.collect()
    made = [model.vocabulary.counts(r.text or "") for r in rows]
    df = Counter(t for c, _, plain in made for t in {*c, *plain})
    learnt = model.vocabulary.learnt()

    def vector(counts, plain):
        parts = []
        for c, scale in ((counts, 1.0), (Counter(plain), T.WORDS)):
            idf = lambda t: math.log((1 + len(rows)) / (1 + df[t])) + 1e-3 if t < learnt else max(0.0, math.log(T.COMMON * (1 + len(rows)) / (1 + df[t])))
            w = {t: (1 + math.log(n)) * idf(t) for t, n in c.items()}
            size = math.sqrt(sum(x * x for x in w.values()))
            parts.append({t: x / size * scale for t, x in w.items()} if size else {})
        both = parts[0] | parts[1]
        size = math.sqrt(sum(x * x for x in both.values()))
        return {t: x / size for t, x in both.items()} if size else {}

    vectors = {r.doc_id: vector(c, plain) for r, (c, _, plain) in zip(rows, made)}
    examples = [(i, y) for i, y in zip(model.ids.tolist(), model.labels.tolist())]
    with_neighbours = 0
    for r in rows:
        q = vectors[r.doc_id]
        cosines = [(sum(x * vectors[i].get(t, 0.0) for t, x in q.items()), j, y) for j, (i, y) in enumerate(examples)]
        near = sorted(((round(s, 12), j, y) for s, j, y in cosines if s > 0), key=lambda c: (-c[0], c[1]))[: model.k]
        w = [s**4 for s, _, _ in near]
        vote = (sum(a * y for a, (_, _, y) in zip(w, near)) + 0.25) / (sum(w) + 0.5)
        want = model.empty_score
        if near and len(model.knots):
            want = float(model.values[min(len(model.values) - 1, int((model.knots < vote - 1e-12).sum()))])
        got = model.score(r.text or "")
        assert abs(got[0] - want) < 1e-9 or min(abs(model.knots - vote)) < 1e-9
        with_neighbours += len(got[2]) > 0
    assert with_neighbours > 100  # few words are rare enough to weigh anything in a table this small


def test_score_beats_counting_on_held_out_labels(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet").groupBy("doc_id").agg({"toxic": "max"}).toDF("doc_id", "y")
    model = T.fit_toxicity(docs, spark.read.parquet("/root/testdata/sf0.1/labels.parquet"))
    labelled = docs.join(labels.where("y is not null and crc32(cast(doc_id as string)) % 5 = 0"), "doc_id").collect()
    scored = [(model.score(r.text or ""), r.y) for r in labelled]
    right = sum((s[0] >= 0.5) == bool(y) for s, y in scored) / len(scored)
    counted = sum((s[1] >= 2) == bool(y) for s, y in scored) / len(scored)
    rank = lambda f: np.mean([(f(a) > f(b)) + 0.5 * (f(a) == f(b)) for a, y in scored if y for b, z in scored if not z])
    print(f"score: right {right:.4f}, AUC {rank(lambda s: s[0]):.4f}; two hits: right {counted:.4f}, AUC {rank(lambda s: s[1]):.4f}; with neighbours {sum(len(s[2]) > 0 for s, _ in scored)} of {len(scored)}")
    assert right > 0.98 and rank(lambda s: s[0]) > 0.95 and sum(len(s[2]) > 0 for s, _ in scored) > 0.98 * len(scored)


def test_calibration_rises():
    x = np.array([0.1, 0.2, 0.3, 0.4, 0.5])
    knots, values = T.isotonic(x, np.array([0.0, 1.0, 0.0, 1.0, 1.0]), np.ones(5))
    assert (np.diff(values) >= 0).all() and values[-1] == 1


def test_learns_stems_and_counts(spark):
    rng = random.Random(3)
    noise = lambda n: [f"{rng.choice('klmnp')}{rng.randint(0, 400)}x" for _ in range(n)]
    rows, labels = [], []
    for i in range(600):
        words = noise(rng.randint(20, 80))
        toxic = int(i % 5 == 0)
        for _ in range(rng.randint(2, 5) if toxic else int(i % 41 == 3)):
            words.insert(rng.randrange(len(words)), rng.choice(["grubbel", "fizzlo"]) + rng.choice(["", "n", "st"]))
        rows.append((i, " ".join(words)))
        labels.append((i, 1, toxic))
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = T.toxicity(docs, spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int")).collect()
    held = [r for r in got if r.held_out]
    assert held and sum(r.predicted == int(r.doc_id % 5 == 0) for r in held) / len(held) > 0.97
    assert any(r.neighbours for r in held if r.predicted)
