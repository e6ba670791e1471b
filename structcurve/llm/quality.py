"""Quality by histogram gradient-boosted trees over document statistics."""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_filter, arrow_map, crc_fold, text_of

SCHEMA = "doc_id bigint, held_out boolean, score double, predicted int"
#: Bound of the sample of labelled rows that the trees are fitted on.
SAMPLE_ROWS = 20_000

FEATURES = (
    "log_bytes", "log_words", "word_length", "word_length_sd", "longest_word", "lower_share", "upper_share", "digit_share",
    "blank_share", "sentence_mark_share", "symbol_share", "exclaim_per_word", "bar_per_word", "wide_share", "distinct_words",
    "top_word_share", "distinct_lines", "repeated_line_share", "line_length", "top_line_share", "short_words", "marked_words",
    "upper_words", "packed_size", "ended_lines", "distinct_pairs",
)


def _bytes_of(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars.encode())] = True
    return out


_LOWER, _UPPER, _DIGIT = _bytes_of("abcdefghijklmnopqrstuvwxyz"), _bytes_of("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _bytes_of("0123456789")
_BLANK, _MARK, _SYMBOL = _bytes_of(" \t\r\n\v\f"), _bytes_of(".,;:?'\"()-"), _bytes_of("#$%&*+/<=>@[]\\^_`{|}~!")
_CLASSES = np.stack([_LOWER, _UPPER, _DIGIT, _BLANK, _MARK, _SYMBOL]).astype(np.float64)


def statistics(text: str) -> list[float]:
    """The features of one whole text, in the order of FEATURES."""
    raw = text.encode("utf-8", "surrogatepass")
    n = max(1, len(raw))
    hist = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    lower, upper, digit, blank, mark, symbol = (_CLASSES @ hist).tolist()
    words = text.split()
    n_words = max(1, len(words))
    lengths = np.fromiter(map(len, words), np.float64, len(words)) if words else np.zeros(1)
    seen = Counter(words)
    lines = [x for x in text.split("\n") if x]
    n_lines = max(1, len(lines))
    line_seen = Counter(lines)
    repeated = sum(len(x) * (c - 1) for x, c in line_seen.items() if c > 1)
    chars = max(1, len(text))
    return [
        np.log1p(len(raw)), np.log1p(len(words)), float(lengths.mean()), float(lengths.std()), float(min(lengths.max(), 200.0)), lower / n, upper / n, digit / n,
        blank / n, mark / n, symbol / n, hist[33] / n_words, hist[124] / n_words, float(hist[192:].sum()) / n, len(seen) / n_words,
        max(seen.values(), default=0) / n_words, len(line_seen) / n_lines, repeated / chars, chars / n_lines, max(line_seen.values(), default=0) / n_lines, float((lengths <= 3).mean()), sum(not w[-1].isalnum() for w in words) / n_words,
        sum(w.isupper() for w in words) / n_words, len(zlib.compress(raw, 1)) / n, sum(x[-1] in ".!?" for x in lines) / n_lines, len(set(zip(words, words[1:]))) / n_words,
    ]


def feature_matrix(texts: list[str]) -> np.ndarray:
    return np.array([statistics(t) for t in texts], np.float64).reshape(len(texts), len(FEATURES))


@dataclass
class BoostedTrees:
    """All trees' nodes in flat arrays; a leaf points to itself, so every row takes ``depth`` equal steps."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    depth: int
    base: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        if not len(x) or not len(self.roots):
            return np.full(len(x), self.base)
        node = np.broadcast_to(self.roots, (len(x), len(self.roots)))
        row = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            node = np.where(x[row, self.feature[node]] <= self.threshold[node], self.left[node], self.right[node])
        return self.base + self.value[node].sum(axis=1)

    def predict(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -30, 30)))


def train_trees(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, penalty: float = 1.0, least: int = 10) -> BoostedTrees:
    """Logistic boosting; each level's histograms of gradients are one bincount per feature."""
    n, f = x.shape
    rate_of_ones = min(max(float(y.mean()) if n else 0.5, 1e-4), 1 - 1e-4)
    base = float(np.log(rate_of_ones / (1 - rate_of_ones)))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(f)] if n else []
    binned = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], axis=1) if n else np.zeros((0, f), np.int64)
    feature, threshold, left, right, value, roots = [], [], [], [], [], []

    def node() -> int:
        feature.append(0)
        threshold.append(0.0)
        left.append(len(left))
        right.append(len(right))
        value.append(0.0)
        return len(feature) - 1

    margin = np.full(n, base)
    for _ in range(trees if n and 0 < y.sum() < n else 0):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        roots.append(node())
        at = np.full(n, roots[-1])
        open_nodes = [roots[-1]]
        for _ in range(depth):
            place = {k: i for i, k in enumerate(open_nodes)}
            slot = np.full(len(feature), -1)
            slot[open_nodes] = range(len(open_nodes))
            own = slot[at]
            live = own >= 0
            k = len(open_nodes)
            best = np.full(k, 1e-6)
            pick: list[tuple[int, int] | None] = [None] * k
            for j in range(f):
                key = own[live] * bins + binned[live, j]
                gs = np.bincount(key, g[live], k * bins).reshape(k, bins).cumsum(1)
                hs = np.bincount(key, h[live], k * bins).reshape(k, bins).cumsum(1)
                cs = np.bincount(key, minlength=k * bins).reshape(k, bins).cumsum(1)
                gt, ht, ct = gs[:, -1:], hs[:, -1:], cs[:, -1:]
                gain = gs**2 / (hs + penalty) + (gt - gs) ** 2 / (ht - hs + penalty) - gt**2 / (ht + penalty)
                gain[(cs < least) | (ct - cs < least)] = 0
                gain[:, len(cuts[j]) :] = 0
                top = gain.argmax(1)
                for i in range(k):
                    if gain[i, top[i]] > best[i]:
                        best[i], pick[i] = gain[i, top[i]], (j, int(top[i]))
            following = []
            for k_node, i in place.items():
                if pick[i] is None:
                    continue
                j, b = pick[i]
                feature[k_node], threshold[k_node] = j, float(cuts[j][b])
                lo, hi = node(), node()
                left[k_node], right[k_node] = lo, hi
                rows = np.nonzero(at == k_node)[0]
                at[rows] = np.where(binned[rows, j] <= b, lo, hi)
                following += [lo, hi]
            open_nodes = following
            if not open_nodes:
                break
        for leaf in np.unique(at):
            rows = at == leaf
            value[leaf] = float(-rate * g[rows].sum() / (h[rows].sum() + penalty))
        margin = margin + np.array(value)[at]
    return BoostedTrees(np.array(feature, np.int64), np.array(threshold), np.array(left, np.int64), np.array(right, np.int64), np.array(value), np.array(roots, np.int64), depth, base)


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE_ROWS, folds: int = 4, held: int = 2, **options) -> BoostedTrees:
    """Fit on at most about ``sample`` labelled rows whose fold is not ``held``; statistics are computed on the executors."""
    train = labels.where(crc_fold(id_col, folds) != held).where(F.col("quality").isin(0, 1)).groupBy(F.col(id_col).cast("bigint").alias("doc_id")).agg(F.min("quality").cast("int").alias("y"))
    n = train.count()
    dice = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    chosen = train.where(dice < sample / max(1, n))
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(chosen), "doc_id").select("doc_id", "y", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = feature_matrix(batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "y", "x"])

    got = sorted(map(tuple, arrow_map(rows, run, "doc_id bigint, y int, x binary").collect()))
    x = np.frombuffer(b"".join(r[2] for r in got), np.float64).reshape(len(got), len(FEATURES))
    return train_trees(x, np.array([r[1] for r in got], np.float64), **options)


def score_quality(docs: DataFrame, model: BoostedTrees, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.7, folds: int = 4, held: int = 2) -> DataFrame:
    """One row per document: ``doc_id, held_out, score, predicted`` (score >= threshold).

    Null texts count as empty and get the score of an empty text's statistics; null ids stay null;
    repeated rows give repeated results and equal texts equal scores; an empty table gives an empty
    table; without labels every score is 0.5.  Other columns are ignored.  A map without shuffle.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = sent.value.predict(feature_matrix(batch.column(2).to_pylist()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(crc_fold(id_col, folds) == held, F.lit(False)).alias("held_out"), text_of(text_col).alias("text"))
    return arrow_map(rows, run, SCHEMA)


def quality(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """Fit and score: see :func:`fit_quality` and :func:`score_quality`."""
    return score_quality(docs, fit_quality(docs, labels, **options))


def without_poor(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, text_col: str = "text", **options) -> DataFrame:
    """The documents that reach the threshold, all columns kept."""
    sent = docs.sparkSession.sparkContext.broadcast(fit_quality(docs, labels, text_col=text_col, **options))
    return arrow_filter(docs, text_col, lambda texts: (sent.value.predict(feature_matrix(texts)) >= threshold).tolist())
