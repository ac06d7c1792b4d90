"""Toxicity by multiple-instance learning.

A document is a bag of sentences. A sentence's score is the logistic of a sum of weights of its distinct words
(as a whole and by their first letters); the document's score is the noisy-or of its sentences, 1 - prod(1 - p). Only
document labels are known: the gradient of the document loss through the noisy-or teaches the sentence model, so the model
also says which sentences offend.

Training sees a bounded sample of labelled rows with whole texts. Features are counted by class on the executors; those that
toxic documents have more often (by LEAST_Z standard errors) are the vocabulary. Then each document becomes numbers of the known
features of its words, sentence by sentence, and only these numbers reach the driver.

Null and empty texts have no sentence and score 0. Texts of any length are scored whole. Rows of equal text have equal scores,
repeated rows keep their rows, a null doc_id is in no fold, and of equally bad sentences the first is the worst. An
empty table gives an empty result. Without training rows of both classes every score is the bias's. Only doc_id and text are read
(and, in `drop_toxic`, carried along), so other columns may have any names.
"""
from __future__ import annotations

import re
import zlib
from array import array
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import discard, lean, small_batches, text_batches, written

PER_CLASS = {0: 3500, 1: 2500}  # most labelled documents of each class that training sees
TRAIN_ITEMS = 10_000_000  # most sentences and known words that training holds; documents beyond it, by hash, are left out of the sample
VOCABULARY, LEAST_DOCS, LEAST_Z, ROUNDS, RATE, L2, RARE = 20_000, 3, 2.0, 200, 0.1, 1e-5, 3000
BIAS = -5.0
NO = 65_535  # no known feature

words_of = re.compile(r"[^\W\d_]+").findall
sentence_of = re.compile(r"[^.!?\n]+").finditer
PREFIXES = (3, 4, 5, 6)
KEEP_WORDS = 150_000  # words whose weight a worker remembers


def features(word: str) -> list[str]:
    """A word counts as itself and by its beginnings, so that inflected and compound forms of a stem share what is learnt."""
    return [word + "$", *(word[:n] for n in PREFIXES if len(word) >= n)]


def sentences(text: str) -> list[tuple[int, int, set[str]]]:
    """(start, end, distinct words) of each sentence that has words."""
    out = []
    for m in sentence_of(text):
        w = set(words_of(m.group().lower()))
        if w:
            out.append((m.start(), m.end(), w))
    return out


class SentenceModel:
    def __init__(self, weights: dict[str, float], bias: float):
        self.weights, self.bias, self.known = weights, bias, {}

    def __reduce__(self):
        return SentenceModel, (self.weights, self.bias)

    def word(self, word: str) -> float:
        if len(self.known) > KEEP_WORDS:
            self.known.clear()
        got = self.known[word] = sum(self.weights.get(f, 0.0) for f in features(word))
        return got

    def sentence(self, words: set[str]) -> float:
        known = self.known
        total = self.bias
        for w in words:
            x = known.get(w)
            total += self.word(w) if x is None else x
        return total

    def document(self, text: str) -> tuple[float, int, int, int]:
        """(noisy-or score, sentences at 0.5 or more, start and end of the worst or -1)."""
        sums = [(self.sentence(w), a, b) for a, b, w in sentences(text)]
        if not sums:
            return 0.0, 0, -1, -1
        s = np.array([x[0] for x in sums])
        p = float(-np.expm1(-np.logaddexp(0, s).sum()))
        worst = sums[int(s.argmax())]
        return min(1.0, max(0.0, p)), int((s >= 0).sum()), worst[1], worst[2]


def association(pos, neg, n_pos, n_neg):
    """By how many standard errors the share of toxic documents with a feature exceeds that of the others."""
    p = (pos + neg) / (n_pos + n_neg)
    return (pos / n_pos - neg / n_neg) / (p * (1 - p) * (1 / n_pos + 1 / n_neg) + 1e-12) ** 0.5


def document_features(text: str) -> set[str]:
    return {f for w in set(words_of(text.lower())) for f in features(w)}


class Bags:
    """Documents in numbers: per known word its features (NO where unknown) and its sentence, per sentence its document."""

    def __init__(self, vocab: dict[str, int]):
        self.vocab, self.known = vocab, {}

    def word(self, w: str) -> tuple | None:
        if w not in self.known:
            if len(self.known) > KEEP_WORDS:
                self.known.clear()
            got = [self.vocab.get(f, NO) for f in features(w)] + [NO] * (1 + len(PREFIXES))
            self.known[w] = tuple(got[: 1 + len(PREFIXES)]) if any(x != NO for x in got) else None
        return self.known[w]

    def document(self, text: str) -> tuple[np.ndarray, np.ndarray, int]:
        """(features of the known words, a row each; number of the sentence of each; sentences)."""
        rows, at, n = array("H"), array("i"), 0
        for _, _, words in sentences(text):
            for w in sorted(words):
                got = self.word(w)
                if got:
                    rows.extend(got)
                    at.append(n)
            n += 1
        return np.frombuffer(rows, np.uint16).reshape(-1, 1 + len(PREFIXES)), np.frombuffer(at, np.int32), n


def train(vocab: list[str], count: np.ndarray, bags: list[tuple[np.ndarray, np.ndarray, int]], labels: list[int], rounds: int = ROUNDS, rate: float = RATE) -> SentenceModel:
    """Adam on the document loss. `count` is the number of documents with each feature of `vocab`."""
    y = np.array(labels, float)
    n_sent = sum(b[2] for b in bags)
    if not len(y) or y.min() == y.max() or not n_sent or not len(vocab):
        return SentenceModel({}, BIAS)
    first = np.cumsum([0] + [b[2] for b in bags])
    doc_of = np.repeat(np.arange(len(bags)), [b[2] for b in bags])
    rows = np.concatenate([b[0] for b in bags])
    in_sentence = np.concatenate([b[1] + f for b, f in zip(bags, first)])
    kinds, word_at = np.unique(rows, axis=0, return_inverse=True)
    word_at = word_at.reshape(-1)
    of_word, slot = np.nonzero(kinds != NO)
    of_feature = kinds[of_word, slot].astype(np.int64)
    n_docs, n_words = len(bags), len(kinds)
    w, bias = np.zeros(len(vocab)), BIAS
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    has = np.array([b[2] > 0 for b in bags])
    weight = np.where(y > 0, max(1.0, (y == 0).sum() / (2 * y.sum())), 1.0)  # rare positives count as a third of the sample
    penalty = L2 * (1 + RARE / count)  # rare features could learn the sample by heart
    for step in range(1, rounds + 1):
        per_word = np.bincount(of_word, w[of_feature], n_words)
        s = bias + np.bincount(in_sentence, per_word[word_at], n_sent)
        total = np.bincount(doc_of, np.logaddexp(0, s), n_docs)
        # loss: total if label 0, -log(1 - exp(-total)) if label 1
        slope = weight * np.where(y > 0, -1 / np.maximum(np.expm1(np.minimum(total, 50)), 1e-6), 1.0) * has
        ds = slope[doc_of] / (1 + np.exp(-s))
        g = np.bincount(of_feature, np.bincount(word_at, ds[in_sentence], n_words)[of_word], len(w)) / n_docs + penalty * w
        gb = ds.sum() / n_docs
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.999 * vb + 0.001 * gb * gb
        c1, c2 = 1 - 0.9**step, 1 - 0.999**step
        w -= rate * (m / c1) / (np.sqrt(v / c2) + 1e-8)
        bias -= rate * (mb / c1) / (np.sqrt(vb / c2) + 1e-8)
    return SentenceModel({f: float(w[k]) for k, f in enumerate(vocab) if abs(w[k]) > 1e-3}, float(bias))


def fit_texts(sample: list[tuple[str, int]], **options) -> SentenceModel:
    """The same from texts at hand (tests and small sets)."""
    seen = {0: Counter(), 1: Counter()}
    for text, y in sample:
        seen[y].update(document_features(text))
    n = Counter(y for _, y in sample)
    if not n[0] or not n[1]:
        return SentenceModel({}, BIAS)
    every = [(association(seen[1][f], seen[0][f], n[1], n[0]), f) for f in seen[1] if seen[0][f] + seen[1][f] >= LEAST_DOCS]
    vocab = [f for z, f in sorted(every, key=lambda x: (-x[0], x[1])) if z > LEAST_Z][:VOCABULARY]
    bags = Bags({f: k for k, f in enumerate(vocab)})
    return train(vocab, np.array([seen[0][f] + seen[1][f] for f in vocab], float), [bags.document(t) for t, _ in sample], [y for _, y in sample], **options)


def _count_features(batches):
    for batch in batches:
        seen: dict[str, list[int]] = {}
        for text, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            for f in document_features(text):
                seen.setdefault(f, [0, 0])[y] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), *[pa.array([c[y] for c in seen.values()], pa.int64()) for y in (0, 1)]], names=["f", "neg", "pos"])


def _numbered(vocab: dict[str, int]):
    def run(batches):
        bags = Bags(vocab)
        for batch in batches:
            got = [bags.document(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([g[0].tobytes() for g in got], pa.binary()), pa.array([g[1].tobytes() for g in got], pa.binary()), pa.array([g[2] for g in got], pa.int64())], names=["doc_id", "y", "rows", "at", "n"])

    return run


def fit_toxicity(labelled: DataFrame, **options) -> SentenceModel:
    """A model from (doc_id, text, y), a bounded sample. Words are counted and numbered on the executors."""
    small_batches(labelled.sparkSession)
    n = {r.y: r.n for r in labelled.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if not n.get(0) or not n.get(1):
        return SentenceModel({}, BIAS)
    dealt = labelled.repartition(64, "doc_id")
    seen = dealt.select("text", "y").mapInArrow(_count_features, "f string, neg long, pos long").groupBy("f").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    seen = seen.where(F.col("neg") + F.col("pos") >= LEAST_DOCS).withColumn("z", association(F.col("pos"), F.col("neg"), n[1], n[0])).where(F.col("z") > LEAST_Z)
    chosen = seen.orderBy(F.desc("z"), "f").limit(VOCABULARY).collect()
    vocab = [r.f for r in chosen]
    made = written(dealt.select("doc_id", "text", "y").mapInArrow(_numbered({f: k for k, f in enumerate(vocab)}), "doc_id long, y int, rows binary, at binary, n long"), "toxic-bags")
    held, within = 0, []
    for r in made.select("doc_id", (F.length("at") / 4 + F.col("n")).alias("items")).orderBy(F.xxhash64("doc_id"), "doc_id").collect():  # at most sum(PER_CLASS) rows
        if held + r.items <= TRAIN_ITEMS:
            held += r.items
            within.append(r.doc_id)
    ordered = made.orderBy(F.xxhash64("doc_id"), "doc_id")
    rows = (ordered.where(F.col("doc_id").isin(within)) if len(within) < sum(n.values()) else ordered).collect()
    bags = [(np.frombuffer(bytes(r.rows), np.uint16).reshape(-1, 1 + len(PREFIXES)), np.frombuffer(bytes(r["at"]), np.int32), r.n) for r in rows]
    model = train(vocab, np.array([r.neg + r.pos for r in chosen], float), bags, [r.y for r in rows], **options)
    discard(made)
    return model


def _predict(model: SentenceModel, folds: int, out_fold: int):
    def run(batches):
        for batch in batches:
            ids, col = batch.column(0).to_pylist(), batch.column(1)
            got = [model.document(col[k].as_py()) for k in range(len(ids))]
            held = [i is not None and zlib.crc32(str(i).encode()) % folds == out_fold for i in ids]
            score = np.array([g[0] for g in got], float)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(held, pa.bool_()), pa.array(score), pa.array((score >= 0.5).astype(np.int32)), *[pa.array([g[k] for g in got], pa.int64()) for k in (1, 2, 3)]], names=["doc_id", "held_out", "score", "predicted", "n_offending", "worst_start", "worst_end"])

    return run


def score_toxicity(docs: DataFrame, model: SentenceModel, folds: int = 5, out_fold: int = 0) -> DataFrame:
    """doc_id, held_out, score, predicted, n_offending, worst_start, worst_end for every row of `docs` (doc_id, text)."""
    return text_batches(docs, _predict(model, folds, out_fold), "doc_id long, held_out boolean, score double, predicted int, n_offending long, worst_start long, worst_end long")


def drop_toxic(docs: DataFrame, model: SentenceModel, cut: float = 0.5) -> DataFrame:
    """`docs`, all columns, without the documents whose score reaches `cut`. Rows are judged in place."""
    text_at = docs.columns.index("text")
    small_batches(docs.sparkSession)

    def run(batches):
        for batch in batches:
            col = batch.column(text_at)
            yield batch.filter(pa.array([model.document(col[k].as_py() or "")[0] < cut for k in range(batch.num_rows)], pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
