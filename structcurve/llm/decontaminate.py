"""Benchmark decontamination: BM25 over a block-max inverted index of test items, walked by WAND cursors."""

from __future__ import annotations

import math
import re
from array import array
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_filter, arrow_map, text_of, written

SCHEMA = "doc_id bigint, item_id bigint, score double, question_overlap double, answer_overlap double, word_from int, word_to int"
WORD = re.compile(r"\w+")
SENTENCE = re.compile(r"(?<=[.!?])\s+")
#: Bytes of item text in one index; more items are queried index by index, so what is sent stays bounded.
INDEX_BYTES = 8 << 20
DENSE_CELLS = 1 << 21


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def question_and_answer(text: str) -> tuple[list[str], list[str]]:
    """An item's last sentence is its answer, the rest its question; of one sentence, the last third."""
    parts = [p for p in (words_of(s) for s in SENTENCE.split(text)) if p]
    if len(parts) > 1:
        return [w for p in parts[:-1] for w in p], parts[-1]
    words = parts[0] if parts else []
    cut = len(words) - len(words) // 3
    return words[:cut], words[cut:]


def grams(words: list[str], n: int) -> set[tuple[str, ...]]:
    n = min(n, len(words))
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)} if n else set()


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted, each value once (quicker for short arrays than numpy's own)."""
    x = np.sort(x)
    new = np.ones(len(x), bool)
    np.not_equal(x[1:], x[:-1], out=new[1:])
    return x[new]


@dataclass(frozen=True)
class ItemStatistics:
    """What BM25 needs to know of all items, whichever of them an index holds."""

    items: int  #: items with words
    words: int  #: their words
    longest: int  #: words of the longest
    df: dict[str, int]  #: items with a term, for the terms of one index at least

    @classmethod
    def of(cls, words: list[list[str]]) -> ItemStatistics:
        return cls(len(words), sum(map(len, words)), max(map(len, words), default=1), Counter(t for w in words for t in set(w)))


class ItemIndex:
    """An inverted index of the items' BM25 impacts, each divided by the item's score against itself.

    A term has its postings in item order and, for each block of items that it occurs in, the largest
    impact there.  :meth:`bounds` adds those block maxima over a passage's distinct terms, which bounds
    every score in a block, and :meth:`wand` moves the terms' cursors from one block whose bound reaches
    the threshold to the next, skipping all others.  No item above the threshold is lost.  Block maxima are
    sparse; terms in more than an eighth of the blocks (in an index of under DENSE_CELLS terms times blocks,
    all) have theirs as a row of numbers too, which adds up faster and costs at most eight times the
    sparse form.  So the index's size follows the items' text.
    ``whole`` has the statistics if the items are only some of all.
    """

    def __init__(self, items: list[tuple[int, str]], k1: float = 1.2, b: float = 0.75, block: int = 2, gram: int = 3, whole: ItemStatistics | None = None):
        kept = [(i, t, w) for i, t in sorted(items) if (w := words_of(t))]
        self.ids = [i for i, _, _ in kept]
        self.texts = [t for _, t, _ in kept]
        self.gram = gram
        whole = whole or ItemStatistics.of([w for _, _, w in kept])
        df = whole.df
        self.terms = {t: j for j, t in enumerate(sorted({t for _, _, w in kept for t in w}))}
        mean = whole.words / max(1, whole.items)
        self.length = whole.longest
        self.block, self.blocks = block, -(-len(kept) // block)
        term, item, impact = array("i"), array("i"), array("d")
        for i, (_, _, words) in enumerate(kept):
            norm = k1 * (1 - b + b * len(words) / mean)
            w = {t: math.log(1 + (whole.items - df[t] + 0.5) / (df[t] + 0.5)) * n * (k1 + 1) / (n + norm) for t, n in Counter(words).items()}
            own = sum(w.values())
            for t, v in w.items():
                term.append(self.terms[t])
                item.append(i)
                impact.append(v / own)
        term, item, impact = np.array(term, np.int32), np.array(item, np.int32), np.array(impact, np.float64)
        order = np.lexsort((item, term))
        term, self.item, self.impact = term[order], item[order], impact[order]
        self.key = term * np.int64(self.blocks * block) + self.item
        every = np.arange(len(self.terms) + 2)
        self.start = np.searchsorted(term, every)  # the last term stands for other words: no postings
        new = np.ones(len(term), bool)
        new[1:] = (term[1:] != term[:-1]) | (self.item[1:] // block != self.item[:-1] // block)
        first = np.nonzero(new)[0]
        self.block_of = (self.item[first] // block).astype(np.int32)
        self.block_max = np.maximum.reduceat(self.impact, first) if len(first) else np.zeros(0)
        self.block_start = np.searchsorted(term[first], every)
        lists = np.diff(self.block_start)
        wide = np.nonzero(lists * 8 > (self.blocks if len(self.terms) * self.blocks > DENSE_CELLS else 0))[0]
        self.row = np.full(len(self.terms) + 1, -1, np.int32)
        self.row[wide] = np.arange(len(wide))
        self.rows = np.zeros((len(wide), self.blocks), np.float32)
        for r, t in enumerate(wide.tolist()):
            at = slice(self.block_start[t], self.block_start[t + 1])
            self.rows[r, self.block_of[at]] = self.block_max[at]
        self.parts: dict[int, tuple] = {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"parts": {}}

    def part(self, i: int) -> tuple[set, set, int, int]:
        """An item's question and answer as word runs, made when first asked for."""
        found = self.parts.get(i)
        if found is None:
            if len(self.parts) > 5000:
                self.parts.clear()
            q, a = question_and_answer(self.texts[i])
            found = self.parts[i] = (grams(q, self.gram), grams(a, self.gram), len(q), len(a))
        return found

    def bounds(self, window: np.ndarray, terms: np.ndarray, windows: int) -> np.ndarray:
        """(windows x blocks): the sum of the block maxima of each window's terms, distinct in a window."""
        row = self.row[terms]
        wide = row >= 0
        out = np.zeros((windows, self.blocks))
        if not wide.all():
            of, t = window[~wide], terms[~wide]
            first = self.block_start[t]
            n = self.block_start[t + 1] - first
            at = np.arange(int(n.sum())) + np.repeat(first - np.cumsum(n) + n, n)
            cell = np.repeat(of * self.blocks, n) + self.block_of[at]
            out += np.bincount(cell, self.block_max[at], windows * self.blocks).reshape(windows, self.blocks)
        if wide.any():
            used = distinct(row[wide])
            holds = np.zeros((windows, len(used)), np.float32)
            holds[window[wide], used.searchsorted(row[wide])] = 1
            out += holds @ self.rows[used]
        return out

    def wand(self, terms: np.ndarray, live: np.ndarray, threshold: float) -> Iterator[tuple[int, float]]:
        """(item, score) of the items in ``live`` blocks that score at least the threshold for the distinct ``terms``.

        WAND moves one cursor a term from pivot to pivot, the next item whose bound reaches the threshold, and
        skips what lies between.  The block maxima of all terms together name the pivots beforehand, the live
        blocks' first items, so all cursors are moved to all of them in one search of the sorted (term, item)
        keys; the postings from there to the blocks' ends are all that is read.
        """
        first = (terms * (self.blocks * self.block))[:, None] + (live * self.block)[None, :]
        lo = self.key.searchsorted(first.ravel())
        n = self.key.searchsorted((first + self.block).ravel()) - lo
        if not (total := int(n.sum())):
            return
        at = np.arange(total) + np.repeat(lo - np.cumsum(n) + n, n)
        place = np.repeat(np.tile(np.arange(len(live)) * self.block, len(terms)), n) + self.item[at] % self.block
        scores = np.bincount(place, self.impact[at], len(live) * self.block)
        for j in np.nonzero(scores >= threshold)[0].tolist():
            yield int(live[j // self.block]) * self.block + j % self.block, float(scores[j])

    def candidates(self, term_ids: np.ndarray, step: int, threshold: float) -> Iterator[tuple[int, int, float]]:
        """(window, item, score) of all items that score at least the threshold in a window: window w has the words
        from w * step to (w + 2) * step.

        Bounds are made for as many windows at a time as keep their table small; they carry single
        precision, so they are held against the threshold less a margin.
        """
        none = len(self.terms) + 1
        windows = max(1, -(-len(term_ids) // step) - 1)
        known = np.nonzero(term_ids < none - 1)[0]
        stretch = known // step  # it lies in the window of its own number and in the one before
        pair = np.concatenate([stretch, stretch - 1])
        words = np.concatenate([term_ids[known]] * 2)
        inside = (pair >= 0) & (pair < windows)
        seen = distinct(pair[inside] * none + words[inside])
        window, terms = np.divmod(seen, none)
        each = max(1, (1 << 20) // max(1, self.blocks))
        for low in range(0, windows, each):
            high = min(windows, low + each)
            a, b = np.searchsorted(window, [low, high])
            bound = self.bounds(window[a:b] - low, terms[a:b], high - low)
            live = bound >= threshold - 1e-5
            for w in np.nonzero(live.any(axis=1))[0].tolist():
                lo, hi = np.searchsorted(window, [low + w, low + w + 1])
                for i, score in self.wand(terms[lo:hi], np.nonzero(live[w])[0], threshold):
                    yield low + w, i, score

    def matches(self, text: str, threshold: float, overlap: float) -> list[tuple[int, float, float, float, int, int]]:
        """Verified items of one whole text, the best window of each."""
        words = words_of(text)
        if not words or not self.ids:
            return []
        none = len(self.terms)
        get = self.terms.get
        ids = np.array([get(w, none) for w in words], np.int64)
        step = self.length
        best: dict[int, tuple] = {}
        found: dict[int, set] = {}
        now = -1
        for w, i, score in self.candidates(ids, step, threshold):
            lo, hi = w * step, min(len(words), (w + 2) * step)
            question, answer, nq, na = self.part(i)
            if w != now:
                now, found = w, {}

            def share(part: set, n: int) -> float:
                if not part:
                    return 1.0
                n = min(self.gram, n)
                if n not in found:
                    found[n] = grams(words[lo:hi], n) if n <= hi - lo else set()
                return len(part & found[n]) / len(part)

            q, a = share(question, nq), share(answer, na)
            row = (i, round(score, 9), q, a, lo, hi)
            if q >= overlap and a >= overlap and (i not in best or (-row[1], lo) < (-best[i][1], best[i][4])):
                best[i] = row
        return [best[i] for i in sorted(best)]


def item_indexes(items: DataFrame, item_col: str = "item_id", item_text: str = "text") -> Iterator[tuple[Broadcast, bool]]:
    """The items as indexes of at most about INDEX_BYTES of text each, one at a time, and whether it is the only one.

    Several indexes share the statistics of all items: counts and lengths come from one aggregate, and
    each index gets the document frequencies of its own terms.  An index is built when it is asked for and
    taken back from the executors after that, so neither driver nor executors ever hold all.
    """
    spark = items.sparkSession
    bench = items.select(F.col(item_col).cast("bigint").alias("item_id"), text_of(item_text).alias("text")).distinct()
    total = bench.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    shards = max(1, -(-total // INDEX_BYTES))
    if shards == 1:
        yield spark.sparkContext.broadcast(ItemIndex([(r.item_id, r.text) for r in bench.collect()])), True
        return

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = [words_of(t) for t in batch.column(1).to_pylist()]
            kinds = (pa.int64(), pa.int64(), pa.list_(pa.string()))
            rows = [(s, len(w), sorted(set(w))) for s, w in zip(batch.column(0).to_pylist(), words) if w]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["shard", "n", "terms"])

    bench = written(bench.withColumn("shard", F.pmod(F.xxhash64("item_id", "text"), F.lit(shards))), "items")
    counted = written(arrow_map(bench.select("shard", "text"), count, "shard bigint, n bigint, terms array<string>"), "item-words")
    sums = counted.agg(F.count("*").alias("items"), F.coalesce(F.sum("n"), F.lit(0)).alias("words"), F.coalesce(F.max("n"), F.lit(1)).alias("longest")).first()
    terms = counted.select("shard", F.explode("terms").alias("term")).groupBy("term", "shard").agg(F.count("*").alias("n"))
    df = terms.groupBy("term").agg(F.sum("n").alias("df"), F.collect_list("shard").alias("shards"))
    df = written(df.select(F.explode("shards").alias("shard"), "term", "df"), "item-terms")
    for s in range(shards):
        whole = ItemStatistics(sums.items, sums.words, sums.longest, {r.term: r.df for r in df.where(F.col("shard") == s).collect()})
        index = spark.sparkContext.broadcast(ItemIndex([(r.item_id, r.text) for r in bench.where(F.col("shard") == s).collect()], whole=whole))
        yield index, False
        index.unpersist()


def contamination(docs: DataFrame, items: DataFrame, threshold: float = 0.5, overlap: float = 0.5, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document and test item found in it: ``doc_id, item_id, score, question_overlap,
    answer_overlap, word_from, word_to``.

    Every passage of every whole document is queried: windows of twice the longest item's words, at
    steps of one such length, so that each run of an item's words lies whole in some window.  All items
    whose BM25 score reaches ``threshold`` of their score against themselves are retrieved; a hit needs
    ``overlap`` of the question's and of the answer's three-word runs in the window.  Null and empty
    texts and items have no passages and give no rows; a null doc_id is kept; repeated rows repeat their
    hits; repeated items are one if id and text agree; the best window of a document stands for the rest
    (ties: the first).  Item counts, frequencies and lengths are of all items, however many indexes they fill.
    Other columns are ignored; empty tables give an empty table.  A map without shuffle: documents are read
    once per index of at most 8 MB of item text, and only such an index is sent to the executors; of
    several, each one's rows are written before the next is built.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text"))

    def one(index: Broadcast) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = index.value
            for batch in batches:
                out = [(d, own.ids[m[0]], *m[1:]) for d, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for m in own.matches(text, threshold, overlap)]
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int32(), pa.int32())
                names = [f.split()[0] for f in SCHEMA.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], names)

        return arrow_map(rows, run, SCHEMA)

    return reduce(DataFrame.union, (one(i) if only else written(one(i), "hits") for i, only in item_indexes(items, item_col, item_text)))


def decontaminate(docs: DataFrame, items: DataFrame, threshold: float = 0.5, overlap: float = 0.5, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The documents without a hit (see :func:`contamination`), all columns kept as they were.

    Null and empty texts have no hit and stay, as do rows with a null id; repeated rows share their fate;
    without items every document stays; an empty table stays empty; columns of any name do no harm, as only the
    text is read.  A map for each index, nothing is shuffled; of several, what one leaves is written
    before the next is built.
    """
    for index, only in item_indexes(items, item_col, item_text):
        left = arrow_filter(docs, text_col, lambda texts, index=index: [not index.value.matches(t, threshold, overlap) for t in texts])
        docs = left if only else written(left, "clean")
    return docs
