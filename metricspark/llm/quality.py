"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics come from whole texts, on the executors; of the bounded sample of labelled rows only they reach the driver, where
training bins every statistic and grows small trees on gradient histograms with the logistic loss. The trees are
flattened into arrays (feature, threshold, children, value) that numpy walks for all rows and trees together.

Null and empty texts have all-zero statistics and get the score that the trees give these. Texts of any length are taken whole. Rows
of equal text have equal scores, repeated rows keep their rows, and a null doc_id is in no fold. Equal statistics never part in a
tree (a cut is "at most"). An empty table gives an empty result; without labels of both classes every score is the share of positives
(0.5 without any). Only doc_id and text are read, so other columns may have any names.
"""
from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import small_batches, text_batches

PER_CLASS = {0: 3000, 1: 5000}  # most labelled documents of each class that training sees
TREES, DEPTH, RATE, BINS, LEAST_ROWS, L2 = 60, 4, 0.15, 64, 20, 1.0
FEATURES = ["bytes", "words", "mean_word", "upper", "lower", "digit", "space", "lines", "ascii_symbol", "stop_punct", "other", "high", "distinct_words", "distinct_lines", "longest_word", "top_word", "mean_line", "distinct_trigrams"]

# byte classes: 0 other control, 1 upper, 2 lower, 3 digit, 4 space, 5 newline, 6 symbol, 7 sentence mark, 8 non-ASCII
CLASS = np.zeros(256, np.uint8)
CLASS[33:127] = 6
CLASS[65:91], CLASS[97:123], CLASS[48:58], CLASS[[9, 32]], CLASS[[10, 13]], CLASS[128:] = 1, 2, 3, 4, 5, 8
CLASS[[ord(c) for c in ".,;:!?'\"-()"]] = 7


def statistics(texts: list[str]) -> np.ndarray:
    """One row of FEATURES a text."""
    out = np.zeros((len(texts), len(FEATURES)))
    for i, text in enumerate(texts):
        raw = text.encode("utf-8", "surrogatepass")
        n = len(raw)
        if not n:
            continue
        c = np.bincount(CLASS[np.frombuffer(raw, np.uint8)], minlength=9)
        words = raw.split()
        lines = [x for x in raw.split(b"\n") if x]
        nw, distinct = len(words), set(words)
        row = out[i]
        row[0], row[1] = np.log1p(n), np.log1p(nw)
        row[2] = (n - c[4] - c[5]) / max(1, nw)
        row[3:7] = c[1] / n, c[2] / n, c[3] / n, c[4] / n
        row[7], row[8], row[9], row[10], row[11] = c[5] / n, c[6] / n, c[7] / n, c[0] / n, c[8] / n
        row[12] = len(distinct) / max(1, nw)
        row[13] = len(set(lines)) / max(1, len(lines))
        row[14] = np.log1p(max(map(len, distinct), default=0))
        row[16] = np.log1p(n / max(1, len(lines)))
        trip = list(zip(words, words[1:], words[2:]))
        row[17] = len(set(trip)) / max(1, len(trip))
        row[15] = nw / max(1, len(distinct)) / np.sqrt(max(1, nw))
    return out


class Forest:
    """Flattened trees: node j of tree t goes to left[t, j] if its statistic is <= cut[t, j], else to left[t, j] + 1."""

    def __init__(self, base: float, feature, cut, left, value, depth: int):
        self.base, self.feature, self.cut, self.left, self.value, self.depth = base, feature, cut, left, value, depth

    def margin(self, x: np.ndarray) -> np.ndarray:
        if not len(x) or not len(self.feature):
            return np.full(len(x), self.base)
        trees = np.arange(len(self.feature))[None, :]
        node = np.zeros((len(x), len(self.feature)), np.int64)
        rows = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            step = self.left[trees, node]
            right = x[rows, self.feature[trees, node]] > self.cut[trees, node]
            node = np.where(step > 0, step + right, node)
        return self.base + self.value[trees, node].sum(axis=1)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x)))


def fit_forest(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, rate: float = RATE, bins: int = BINS) -> Forest:
    if not len(y) or y.min() == y.max():
        p = float(y.mean()) if len(y) else 0.5
        p = min(max(p, 1e-3), 1 - 1e-3)
        empty = np.zeros((0, 1))
        return Forest(float(np.log(p / (1 - p))), empty.astype(int), empty, empty.astype(int), empty, 0)
    n, width = x.shape
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    binned = np.stack([np.searchsorted(cuts[f], x[:, f], "left") for f in range(width)], axis=1)
    p = y.mean()
    base = float(np.log(p / (1 - p)))
    margin, size = np.full(n, base), 2 ** (depth + 1) - 1
    feature, cut, left, value = np.zeros((trees, size), int), np.zeros((trees, size)), np.zeros((trees, size), int), np.zeros((trees, size))
    offset = np.arange(width) * bins
    for t in range(trees):
        prob = 1 / (1 + np.exp(-margin))
        grad, hess = y - prob, prob * (1 - prob)
        node, used, front = np.zeros(n, int), 1, [0]
        for _ in range(depth):
            nxt = []
            for j in front:
                rows = np.flatnonzero(node == j)
                if len(rows) < 2 * LEAST_ROWS:
                    continue
                flat = (binned[rows] + offset).ravel()
                each = lambda v: np.bincount(flat, np.repeat(v[rows], width) if v is not None else None, width * bins).reshape(width, bins).cumsum(axis=1)
                g, h, c = each(grad), each(hess), each(None)
                gt, ht, ct = g[:, -1:], h[:, -1:], len(rows)
                gain = g**2 / (h + L2) + (gt - g) ** 2 / (ht - h + L2) - gt**2 / (ht + L2)
                gain[(c < LEAST_ROWS) | (ct - c < LEAST_ROWS)] = -1
                f, b = np.unravel_index(gain.argmax(), gain.shape)
                if gain[f, b] <= 1e-6 or b >= len(cuts[f]):
                    continue
                feature[t, j], cut[t, j], left[t, j] = f, cuts[f][b], used
                node[rows] = np.where(binned[rows, f] <= b, used, used + 1)
                nxt += [used, used + 1]
                used += 2
            front = nxt
        gs, hs = np.bincount(node, grad, size), np.bincount(node, hess, size)
        value[t] = rate * gs / (hs + L2)
        margin += value[t][node]
    return Forest(base, feature, cut, left, value, depth)


def _measured(batches):
    for batch in batches:
        col = batch.column(1)
        rows = statistics([col[k].as_py() or "" for k in range(batch.num_rows)])
        yield pa.RecordBatch.from_arrays([batch.column(2), pa.array(list(rows), pa.list_(pa.float64()))], names=["y", "x"])


def fit_quality(labelled: DataFrame, **options) -> Forest:
    """A forest from (doc_id, text, y): the statistics are made on the executors, and one short row a document is collected."""
    small_batches(labelled.sparkSession)
    rows = labelled.select("doc_id", "text", "y").repartition(64, "doc_id").mapInArrow(_measured, "y int, x array<double>").collect()
    rows.sort(key=lambda r: (r.y, r.x))
    return fit_forest(np.array([r.x for r in rows], float).reshape(len(rows), len(FEATURES)), np.array([r.y for r in rows], float), **options)


def _predict(forest: Forest, folds: int, out_fold: int, cut: float):
    def run(batches):
        for batch in batches:
            ids, col, n = batch.column(0).to_pylist(), batch.column(1), batch.num_rows
            for at in range(0, n, 500):
                part = ids[at : at + 500]
                score = forest.score(statistics([col[k].as_py() for k in range(at, at + len(part))]))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(part)), pa.array([i is not None and zlib.crc32(str(i).encode()) % folds == out_fold for i in part], pa.bool_()), pa.array(score), pa.array((score >= cut).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return run


def score_quality(docs: DataFrame, forest: Forest, folds: int = 5, out_fold: int = 0, cut: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of `docs` (doc_id, text)."""
    return text_batches(docs, _predict(forest, folds, out_fold, cut), "doc_id long, held_out boolean, score double, predicted int")
