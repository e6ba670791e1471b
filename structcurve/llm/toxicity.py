"""Toxicity by nearest labelled examples under exact TF-IDF cosine.

A text's vector holds all words that occur in at least two labelled examples, and beside them the terms of a
vocabulary learnt from the labels: whole words and word stems (prefixes) that go with the label, picked
greedily so that every toxic example is covered several times, with unary count terms for how many of the
text's words hit it, so that one stray word and many differ in angle.  Document frequencies for the
weights are counted over all documents.  The two parts are scaled to norms of 1 and WORDS: a text with
vocabulary terms is nearest to examples that share them, any other to examples of like words.  All
sampled examples, clean and toxic, form an inverted index cut into blocks with the largest weight of
each term in each block; a query bounds all blocks, opens the best first and then those alone whose
bound reaches its k-th neighbour, so the neighbours are exact.  Similarity-weighted votes are calibrated on
a fifth of the examples that a vocabulary learnt from the other four fifths has not seen.
"""

from __future__ import annotations

import heapq
import math
import re
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_filter, arrow_map, crc_fold, text_of

SCHEMA = "doc_id bigint, held_out boolean, score double, predicted int, n_hits int, neighbours array<bigint>, similarity array<double>, terms array<string>"
WORD = re.compile(r"\w+")
STEMS = (4, 5, 6, 7)
#: Norm of the part of all words beside that of the vocabulary; words in more than this share of documents weigh nothing.
WORDS, COMMON = 0.3, 0.02
COUNT_TERMS = 8
#: Bound of the sample of labelled rows that is fitted on, for each label.
SAMPLE_PER_LABEL = 3000


def word_terms(word: str) -> list[str]:
    """The word itself and its proper stems; stems end in a mark that no word has."""
    return [word, *(word[:k] + "*" for k in STEMS if len(word) > k)]


def text_terms(text: str) -> set[str]:
    """All terms of a text; a stem that begins at least two of its words is also a term of its own."""
    words = WORD.findall(text.lower())
    stems = Counter(w[:k] + "**" for w in words for k in STEMS if len(w) > k)
    return {t for w in set(words) for t in word_terms(w)} | {t for t, n in stems.items() if n > 1}


class _Codes(dict):
    """Word -> its learnt term, its stem that needs two words, and its plain word, each plus one, packed in a number."""

    def __init__(self, ids: dict[str, int], words: dict[str, int]):
        self.ids, self.words = ids, words

    def __missing__(self, w: str) -> int:
        ids = self.ids
        one = next((ids[x] + 1 for x in word_terms(w) if x in ids), 0)
        two = next((ids[x + "*"] + 1 for x in word_terms(w)[1:] if x + "*" in ids), 0)
        code = self[w] = one | two << 16 | self.words.get(w, -1) + 1 << 32
        return code


class Vocabulary:
    """Terms of the vectors: learnt terms first, then count terms, then plain words."""

    def __init__(self, ids: dict[str, int], words: dict[str, int] | None = None):
        self.ids, self.words = ids, words or {}
        self.memo = _Codes(self.ids, self.words)

    def __getstate__(self) -> tuple:
        return self.ids, self.words

    def __setstate__(self, state: tuple) -> None:
        self.__init__(*state)

    def counts(self, text: str) -> tuple[Counter, int, np.ndarray]:
        """Term id -> occurrences, unary count terms included; how many words hit the vocabulary; sorted ids of plain words.

        A word counts for its most specific term; where it has none, for a stem that needs two words.
        """
        if len(self.memo) > 500_000:
            self.memo.clear()
        found = WORD.findall(text.lower())
        codes = np.fromiter(map(self.memo.__getitem__, found), np.int64, len(found))
        plain = codes >> 32
        plain = np.sort(plain[plain > 0]) + (self.learnt() - 1)
        learnt = codes & 0xFFFFFFFF
        hits: Counter = Counter()
        if learnt.any():
            paired: Counter = Counter()
            for c in learnt[learnt > 0].tolist():
                if c & 0xFFFF:
                    hits[(c & 0xFFFF) - 1] += 1
                else:
                    paired[(c >> 16) - 1] += 1
            hits.update({t: n for t, n in paired.items() if n > 1})
        n = sum(hits.values())
        for j in range(min(n, COUNT_TERMS)):
            hits[len(self.ids) + j] = 1
        return hits, n, plain

    def learnt(self) -> int:
        return len(self.ids) + COUNT_TERMS

    def size(self) -> int:
        return self.learnt() + len(self.words)


def shared_words(texts: list[str]) -> dict[str, int]:
    """Words of at least two texts, numbered in order."""
    once: set[str] = set()
    twice: set[str] = set()
    for text in texts:
        found = set(WORD.findall(text.lower()))
        twice |= found & once
        once |= found
    return {w: i for i, w in enumerate(sorted(twice))}


def _copy_key(text: str) -> int:
    """Equal for most near copies: the least hash of two long words in a row."""
    words = [w for w in text.split() if len(w) > 5]
    return min((zlib.crc32(f"{a} {b}".encode("utf-8", "surrogatepass")) for a, b in zip(words, words[1:])), default=zlib.crc32(text.encode("utf-8", "surrogatepass")))


def choose_vocabulary(texts: list[str], labels: list[int], cover: int = 6, precision: float = 0.85, support: int = 3, most: int = 2000) -> Vocabulary:
    """Greedy multi-cover of the toxic examples by terms that are rare in the others; near copies count once."""
    clean = [t for t, y in zip(texts, labels) if not y]
    seen: set[int] = set()
    toxic: list[str] = []
    for text, y in zip(texts, labels):
        if y and (key := _copy_key(text)) not in seen:
            seen.add(key)
            toxic.append(text)
    if not toxic:
        return Vocabulary({})
    weight = max(1.0, sum(labels) / max(1, len(clean)))
    # counts by hash first: only terms that may have the support are ever held as strings
    rough = np.zeros(1 << 22, np.uint16)
    place = lambda terms: np.fromiter((zlib.crc32(t.encode("utf-8", "surrogatepass")) & 0x3FFFFF for t in terms), np.int64)
    for text in toxic:
        rough[np.unique(place(text_terms(text)))] += 1
    toxic_df: Counter = Counter()
    for text in toxic:
        terms = list(text_terms(text))
        toxic_df.update(t for t, n in zip(terms, rough[place(terms)]) if n >= support)
    toxic_df = Counter({t: n for t, n in toxic_df.items() if n >= support})
    clean_df: Counter = Counter()
    for text in clean:
        clean_df.update(t for t in text_terms(text) if t in toxic_df)
    # many thousands of terms are tried, so a term must also be far likelier in toxic texts, one clean text granted
    lift = max(1, len(clean)) / len(toxic)
    good = {t for t, n in toxic_df.items() if n / (n + weight * clean_df[t] + 0.5) >= precision and n * lift >= 15 * (clean_df[t] + 1)}
    where: dict[str, list[int]] = {}
    for i, text in enumerate(toxic):
        for t in text_terms(text) & good:
            where.setdefault(t, []).append(i)
    docs = {t: np.array(v) for t, v in where.items()}
    need = np.full(len(toxic), cover)
    ids: dict[str, int] = {}
    # lazy greedy: a term's gain only falls, so the top of the queue is checked again before it is taken
    queue = [(-len(v), -len(t), t) for t, v in docs.items()]
    heapq.heapify(queue)
    while queue and len(ids) < most:
        old, size, t = heapq.heappop(queue)
        gain = int((need[docs[t]] > 0).sum())
        if gain < support:
            continue
        if gain < -old:
            heapq.heappush(queue, (-gain, size, t))
            continue
        stem = t.rstrip("*")
        if any(t.count("*") >= x.count("*") and (stem.startswith(x.rstrip("*")) or x.startswith(stem)) for x in ids):
            continue  # a stem or word of the same family stands for it
        ids[t] = len(ids)
        need[docs[t]] -= 1
    return Vocabulary(ids)


Vector = tuple[np.ndarray, np.ndarray]


def _spread(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The numbers start[i] .. start[i] + n[i] - 1 of all i, one after another."""
    return np.arange(int(n.sum())) + np.repeat(start - np.cumsum(n) + n, n)


class BlockMaxIndex:
    """Examples' unit vectors (term ids, weights) as postings in blocks; exact k nearest by cosine."""

    def __init__(self, vectors: list[Vector], n_terms: int, block: int = 256):
        self.n, self.block = len(vectors), block
        self.blocks = -(-self.n // block)
        sizes = [len(v[0]) for v in vectors]
        term = np.concatenate([np.zeros(0, np.int64), *(v[0] for v in vectors)])
        row = np.repeat(np.arange(self.n), sizes)
        order = np.lexsort((row, term))
        term, self.row = term[order], row[order].astype(np.int32)
        self.weight = np.concatenate([np.zeros(0), *(v[1] for v in vectors)])[order]
        self.key = term * (self.blocks * block) + self.row
        every = np.arange(n_terms + 1)
        self.start = np.searchsorted(term, every)
        new = np.ones(len(term), bool)
        new[1:] = (term[1:] != term[:-1]) | (self.row[1:] // block != self.row[:-1] // block)
        first = np.nonzero(new)[0]
        self.block_of = (self.row[first] // block).astype(np.int32)
        self.block_max = np.maximum.reduceat(self.weight, first) if len(first) else np.zeros(0)
        self.block_start = np.searchsorted(term[first], every)

    def _scores(self, terms: np.ndarray, weights: np.ndarray, live: np.ndarray) -> Vector:
        """(examples, cosines above 0) of the examples in ``live`` blocks."""
        if 4 * len(live) < self.blocks:  # cursors go straight to the blocks
            first = (terms * (self.blocks * self.block))[:, None] + (live * self.block)[None, :]
            lo = self.key.searchsorted(first.ravel())
            n = self.key.searchsorted((first + self.block).ravel()) - lo
            at, w = _spread(lo, n), np.repeat(np.repeat(weights, len(live)), n)
            scores = np.bincount(self.row[at], self.weight[at] * w, self.n)
        else:
            n = self.start[terms + 1] - self.start[terms]
            at = _spread(self.start[terms], n)
            scores = np.bincount(self.row[at], self.weight[at] * np.repeat(weights, n), self.n)
            dead = np.ones(self.blocks, bool)
            dead[live] = False
            scores[np.repeat(dead, self.block)[: self.n]] = 0
        hit = np.nonzero(scores > 0)[0]
        return hit, scores[hit]

    def search(self, query: Vector, k: int, without: int = -1, ahead: int = 1) -> Vector:
        """The k largest cosines above 0 (ties: smallest example) and their examples."""
        terms, weights = query
        if not len(terms) or not self.n:
            return np.zeros(0, np.int64), np.zeros(0)
        n = self.block_start[terms + 1] - self.block_start[terms]
        at = _spread(self.block_start[terms], n)
        bound = np.bincount(self.block_of[at], self.block_max[at] * np.repeat(weights, n), self.blocks)

        def best(i: np.ndarray, s: np.ndarray) -> Vector:
            if without >= 0:
                i, s = i[i != without], s[i != without]
            if len(s) > 4 * k:
                keep = s >= np.partition(s, len(s) - k)[len(s) - k] - 1e-9
                i, s = i[keep], s[keep]
            order = np.lexsort((i, -np.round(s, 12)))[:k]
            return i[order], s[order]

        order = np.argsort(-bound, kind="stable")
        order = order[bound[order] > 0]
        i, s = best(*self._scores(terms, weights, np.sort(order[:ahead])))
        rest = order[ahead:]
        if len(s) >= k:
            rest = rest[bound[rest] >= s[-1] - 1e-9]
        if len(rest):
            j, t = self._scores(terms, weights, np.sort(rest))
            i, s = best(np.concatenate([i, j]), np.concatenate([s, t]))
        return i, s


def isotonic(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators: knots and values of the rising fit of y on x."""
    order = np.argsort(x, kind="stable")
    blocks: list[list[float]] = []  # value, weight, last x
    for i in order:
        blocks.append([y[i], w[i], x[i]])
        while len(blocks) > 1 and (blocks[-2][0] >= blocks[-1][0] or blocks[-2][2] == blocks[-1][2]):
            b, a = blocks.pop(), blocks.pop()
            s = a[1] + b[1]
            blocks.append([(a[0] * a[1] + b[0] * b[1]) / s, s, b[2]])
    return np.array([b[2] for b in blocks]), np.array([b[0] for b in blocks])


@dataclass
class ToxicityModel:
    vocabulary: Vocabulary
    idf: np.ndarray
    index: BlockMaxIndex
    ids: np.ndarray
    labels: np.ndarray
    k: int
    knots: np.ndarray
    values: np.ndarray
    empty_score: float

    def vector(self, counts: Counter, plain: np.ndarray) -> Vector:
        """Unit vector of all terms: the learnt ones at norm 1, the plain words beside them at norm WORDS."""
        return unit_vector(counts, plain, self.idf)

    def vote(self, near: np.ndarray, sims: np.ndarray, prior: float = 0.5) -> float:
        weight = sims**4
        return (float((weight * self.labels[near]).sum()) + 0.5 * prior) / (float(weight.sum()) + 0.5)

    def calibrated(self, vote: float) -> float:
        if not len(self.knots):
            return self.empty_score
        return float(self.values[min(len(self.values) - 1, int(np.searchsorted(self.knots, vote)))])

    def score(self, text: str) -> tuple[float, int, np.ndarray, np.ndarray, Counter]:
        counts, n, plain = self.vocabulary.counts(text)
        near, sims = self.index.search(self.vector(counts, plain), self.k)
        score = self.calibrated(self.vote(near, sims)) if len(near) else self.empty_score
        return score, n, near, sims, counts


def unit_vector(counts: Counter, plain: np.ndarray, idf: np.ndarray) -> Vector:
    edge = np.nonzero(np.diff(plain, prepend=-1))[0]
    words = plain[edge]
    w = idf[words] * (1 + np.log(np.diff(edge, append=len(plain))))
    words, w = words[w > 0], w[w > 0]
    size = math.sqrt(w @ w)
    if not counts:
        return words, w / (size or 1)
    own = np.array(sorted(counts), np.int64)
    v = (1 + np.log(np.array([counts[t] for t in own.tolist()], np.float64))) * idf[own]
    own, v = own[v > 0], v[v > 0]
    v /= math.sqrt(v @ v) or 1
    whole = math.sqrt((len(v) > 0) + (size > 0) * WORDS**2) or 1
    return np.concatenate([own, words]), np.concatenate([v / whole, w * (WORDS / (size or 1) / whole)])


def _sampled(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, per_label: int, folds: int, held: int) -> tuple[list, dict[int, int]]:
    """At most about ``per_label`` labelled training rows of each class, with the classes' sizes."""
    train = labels.where(crc_fold(id_col, folds) != held).where(F.col("toxic").isin(0, 1)).groupBy(F.col(id_col).cast("bigint").alias("doc_id")).agg(F.max("toxic").cast("int").alias("y"))
    sizes = {r.y: r.n for r in train.groupBy("y").agg(F.count("*").alias("n")).collect()}
    dice = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    keep = F.lit(False)
    for y, n in sizes.items():
        keep = keep | ((F.col("y") == y) & (dice < per_label / n))
    chosen = train.where(keep)
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(chosen), "doc_id").collect()
    return rows, sizes


def fit_toxicity(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 15, per_label: int = SAMPLE_PER_LABEL, folds: int = 5, held: int = 0, parts: int = 5) -> ToxicityModel:
    """Fit on labelled rows whose fold is not ``held``; document frequencies come from all rows.

    The sample is bounded by ``per_label`` rows of each class, whatever the input's size.  Without labels
    the model scores every text alike.
    """
    rows, sizes = _sampled(docs, labels, id_col, text_col, per_label, folds, held)
    unique = {r.text: r for r in sorted(rows, key=lambda r: (-r.doc_id, r.y))}
    rows = sorted(unique.values(), key=lambda r: r.doc_id)
    texts, ys = [r.text for r in rows], [r.y for r in rows]
    # near copies share a part, so that a text is never calibrated on what its copy taught
    apart = np.array([_copy_key(t) % parts == 0 for t in texts], bool)
    vocabulary = Vocabulary(choose_vocabulary([t for t, a in zip(texts, apart) if not a], [y for y, a in zip(ys, apart) if not a]).ids, shared_words(texts))
    n_docs, df = _document_frequency(docs, text_col, vocabulary)
    learnt = vocabulary.learnt()
    idf = np.where(df > 0, np.log((1 + n_docs) / (1 + df)) + 1e-3, 0.0)
    idf[learnt:] = np.maximum(0.0, np.log(COMMON * (1 + n_docs) / (1 + df[learnt:])))
    vectors = [unit_vector(c, plain, idf) for c, _, plain in map(vocabulary.counts, texts)]
    y = np.array(ys, np.float64)

    def fitted(of: np.ndarray) -> ToxicityModel:
        some = np.array([i for i in np.nonzero(of)[0] if len(vectors[i][0])], np.int64)
        ids = np.array([rows[i].doc_id for i in some], np.int64)
        return ToxicityModel(vocabulary, idf, BlockMaxIndex([vectors[i] for i in some], vocabulary.size()), ids, y[some], k, np.zeros(0), np.zeros(0), 0.0)

    taught = fitted(~apart)
    tested = np.array([i for i in np.nonzero(apart)[0] if len(vectors[i][0])], np.int64)
    votes = np.array([taught.vote(*taught.index.search(vectors[i], k)) for i in tested], np.float64)
    # each class counts as it does among all labelled rows, not as in the balanced sample
    drawn = Counter(ys)
    weight = np.array([sizes.get(y, 0) / max(1, drawn[y]) for y in ys])
    model = fitted(np.ones(len(rows), bool))
    model.knots, model.values = isotonic(votes, y[tested], weight[tested])
    # before any evidence a text is what documents are by the labels' shares
    model.empty_score = min(0.49, float((weight * y).sum() + 0.01) / float(weight.sum() + 1)) if len(y) else 0.01
    return model


def _document_frequency(docs: DataFrame, text_col: str, vocabulary: Vocabulary) -> tuple[int, np.ndarray]:
    """Over all documents: each task adds up its own counts and leaves a short row per term."""
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Vocabulary = sent.value
        total, df = 0, np.zeros(own.size(), np.int64)
        for batch in batches:
            for text in batch.column(0).to_pylist():
                hits, _, plain = own.counts(text)
                total += 1
                for t in hits:
                    df[t] += 1
                df[plain] += 1  # a word that occurs again is set to the same value
        at = np.nonzero(df)[0]
        yield pa.RecordBatch.from_arrays([pa.array(np.append(-1, at).astype(np.int32)), pa.array(np.append(total, df[at]))], ["term", "n"])

    rows = arrow_map(docs.select(text_of(text_col).alias("text")), run, "term int, n bigint").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    term, n = rows.column("term").to_numpy(), rows.column("n").to_numpy()
    out = np.zeros(vocabulary.size(), np.float64)
    out[term[term >= 0]] = n[term >= 0]
    return int(n[term < 0].sum()), out


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, held: int = 0) -> DataFrame:
    """One row per document: ``doc_id, held_out, score, predicted`` and the evidence.

    Evidence: words that hit the vocabulary, the nearest examples' ids and cosines, the terms.
    A text none of whose words is known, such as an empty or null one, has no neighbours and gets the share of
    toxic labels, below 0.5; null ids stay null;
    equal texts get equal scores, ties between examples go to the smallest id; empty tables give empty
    tables; other columns are ignored.  A map without shuffle; the model is bounded by its sample.
    """
    names = [t for t, _ in sorted(model.vocabulary.ids.items(), key=lambda x: x[1])]
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: ToxicityModel = sent.value
        for batch in batches:
            cols: list[list] = [[], [], [], [], [], []]
            for text in batch.column(2).to_pylist():
                score, n, near, sims, counts = m.score(text)
                cols[0].append(score)
                cols[1].append(int(score >= 0.5))
                cols[2].append(n)
                cols[3].append(m.ids[near].tolist())
                cols[4].append(np.round(sims, 6).tolist())
                cols[5].append([names[t] for t in sorted(counts) if t < len(names)])
            kinds = (pa.float64(), pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.float64()), pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, t) for c, t in zip(cols, kinds))], ["doc_id", "held_out", "score", "predicted", "n_hits", "neighbours", "similarity", "terms"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(crc_fold(id_col, folds) == held, F.lit(False)).alias("held_out"), text_of(text_col).alias("text"))
    return arrow_map(rows, run, SCHEMA)


def toxicity(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """Fit and score: see :func:`fit_toxicity` and :func:`score_toxicity`."""
    return score_toxicity(docs, fit_toxicity(docs, labels, **options))


def without_toxic(docs: DataFrame, labels: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """The documents that are not predicted toxic (score below 0.5), all columns kept as they were.

    Null and empty texts and rows with a null id stay; repeated rows share their fate; without labels every document
    stays; an empty table stays empty; columns of any name do no harm.  A map, nothing is shuffled.
    """
    sent = docs.sparkSession.sparkContext.broadcast(fit_toxicity(docs, labels, text_col=text_col, **options))
    return arrow_filter(docs, text_col, lambda texts: [sent.value.score(t)[0] < 0.5 for t in texts])


def plain_neighbours(vectors: Iterable[Vector], query: Vector, k: int) -> list[tuple[int, float]]:
    """Brute force, for tests."""
    wanted = dict(zip(query[0].tolist(), query[1].tolist()))
    scored = [(i, sum(w * wanted.get(t, 0.0) for t, w in zip(v[0].tolist(), v[1].tolist()))) for i, v in enumerate(vectors)]
    return sorted(((i, s) for i, s in scored if s > 0), key=lambda x: (-round(x[1], 12), x[0]))[:k]
