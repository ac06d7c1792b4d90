"""Benchmark decontamination with the q-gram lemma.

A passage of m characters that occurs in a document with at most k edits shares at least m - q + 1 - k q q-grams
with the document, all on diagonals (document position minus passage position) within k of that of the
occurrence. So we count shared q-grams in overlapping diagonal bands of width 2 (k + 1), shifted by k + 1, keep the bands that
reach the bound, and align the passage there within a band. Only true occurrences within the budget stay, and
none is missed.

A first test needs no passages: since the q-grams of an occurrence lie in few blocks of BLOCK characters, one of
these must hold its share of the bound, counting every position whose q-gram occurs in any passage. Few
documents get past it.

Characters are compared in lower case (where that is one character), white space as a space. The budget is
`rate` * m edits, less for passages so short that the bound would vanish. Empty passages match nothing. Null texts
are empty. Passages shorter than q are sought as exact substrings. Each (document, passage) gives one row, for its
best occurrence: fewest edits, then smallest start.

Texts of any length are searched whole. Rows of equal doc_id, repeated rows and rows with a null doc_id are judged each by itself and keep their
rows. Without documents or without passages nothing is found (and nothing dropped). `contaminated_spans` reads only doc_id and text,
`drop_contaminated` carries all columns along, whatever their names. Passages reach the tasks in chunks of bounded size, each a pass over the
documents; the benchmark is the small side by its nature, and its size is what bounds the number of passes.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import lean, small_batches

Q = 8
RATE = 0.08
BLOCK = 64
CHUNK_CHARS = 4_000_000  # of passages held by a task at once; more passages take more passes
SEGMENT_CHARS = 1 << 20
BITS = 22

FOLD = np.arange(128, dtype=np.uint8)
FOLD[65:91] += 32
FOLD[9:14] = 32


def lowered(text: str) -> str:
    low = text.lower()
    return low if len(low) == len(text) else "".join(x if len(x := c.lower()) == 1 else c for c in text)


def codes(text: str) -> np.ndarray:
    """One byte a character. Other than ASCII characters share bytes over 127, which only adds candidates before alignment."""
    if text.isascii():
        return FOLD[np.frombuffer(text.encode(), np.uint8)]
    cp = np.frombuffer(lowered(text).encode("utf-32-le", "surrogatepass"), np.uint32)
    return np.where(cp < 128, FOLD[cp & 127], 128 | (cp ^ cp >> 7) & 127).astype(np.uint8)


def folded(text: str) -> np.ndarray:
    cp = np.frombuffer(lowered(text).encode("utf-32-le", "surrogatepass"), np.uint32)
    return np.where(cp < 128, FOLD[cp & 127], cp)


def grams(flat: np.ndarray) -> np.ndarray:
    """The 8-gram at each position as one number."""
    if len(flat) < Q:
        return np.empty(0, np.uint64)
    two = flat[:-1].astype(np.uint64) | flat[1:].astype(np.uint64) << np.uint64(8)
    four = two[:-2] | two[2:] << np.uint64(16)
    return four[:-4] | four[4:] << np.uint64(32)


def slot(g: np.ndarray) -> np.ndarray:
    return (g * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)


def best_alignment(passage: np.ndarray, region: np.ndarray, low: int, width: int, budget: int) -> tuple[int, int, int] | None:
    """Fewest edits that turn `passage` into a stretch of `region` on diagonals low .. low + width - 1; (edits, start, end)."""
    far = budget + 1
    d = low + np.arange(width)
    inside = (d >= 0) & (d <= len(region))
    cost = np.where(inside, 0, far).astype(np.int64)
    start = d.copy()
    step = np.arange(width)
    for i in range(len(passage)):
        at = d + i  # position in region of the character matched on each diagonal
        ok = (at >= 0) & (at < len(region))
        diff = np.where(ok, region[np.clip(at, 0, len(region) - 1)] != passage[i], True) if len(region) else np.ones(width, bool)
        sub = np.where(ok, cost + diff, far)
        drop = np.append(cost[1:], far) + 1  # passage character left out
        drop[~((at + 1 >= 0) & (at + 1 <= len(region)))] = far
        new = np.minimum(sub, drop)
        new_start = np.where(sub <= drop, start, np.append(start[1:], 0))
        grown = np.minimum.accumulate(new - step)  # region characters put in: from a lower diagonal
        ins = grown + step
        if (ins < new).any():
            arg = np.maximum.accumulate(np.where(new - step == grown, step, 0))
            new_start = np.where(ins < new, new_start[arg], new_start)
            new = np.minimum(new, ins)
        over = at + 1 > len(region)
        new[over] = far
        cost, start = np.minimum(new, far), new_start
        if cost.min() >= far:
            return None
    k = min(range(width), key=lambda j: (cost[j], start[j], d[j]))
    return (int(cost[k]), int(start[k]), int(d[k] + len(passage))) if cost[k] <= budget else None


class Passages:
    def __init__(self, items: list[tuple[int, str]], rate: float = RATE):
        self.items = [(i, t, folded(t)) for i, t in items if t]
        self.short = [k for k, x in enumerate(self.items) if len(x[2]) < Q]
        m = np.array([len(x[2]) for x in self.items], np.int64)
        self.budget = np.maximum(0, np.minimum(np.floor(rate * m + 1e-9).astype(np.int64), (m - Q) // Q))
        self.bound = m - Q + 1 - self.budget * Q
        share = [-(-int(b) // (-(-int(n + k) // BLOCK) + 1)) for b, n, k in zip(self.bound, m, self.budget) if n >= Q]
        self.share = min(share, default=0)
        gs, who, at = [], [], []
        for k, (_, t, _) in enumerate(self.items):
            g = grams(codes(t))
            gs.append(g)
            who.append(np.full(len(g), k))
            at.append(np.arange(len(g)))
        g = np.concatenate(gs) if gs else np.empty(0, np.uint64)
        order = np.argsort(g, kind="stable")
        self.g = g[order]
        self.who = np.concatenate(who)[order].astype(np.int64) if gs else np.empty(0, np.int64)
        self.at = np.concatenate(at)[order].astype(np.int64) if gs else np.empty(0, np.int64)
        self.seen = np.zeros(1 << BITS, bool)
        self.seen[slot(self.g)] = True

    def near(self, texts: list[str]) -> list[list[tuple[int, int, int, int]]]:
        """Per text: (item_id, start, end, edits) of each passage found."""
        out: list[list] = [[] for _ in texts]
        if not self.items:
            return out
        for k in self.short:
            item, t, f = self.items[k]
            for n, text in enumerate(texts):
                at = _find(folded(text), f)
                if at >= 0:
                    out[n].append((item, at, at + len(f), 0))
        parts = [codes(t) for t in texts]
        flat = np.concatenate(parts) if parts else np.empty(0, np.uint8)
        g = grams(flat)
        if not len(g) or not len(self.g):
            return out
        hit = self.seen[slot(g)]
        cuts = np.concatenate([[0], np.cumsum([len(p) for p in parts])])
        cum = np.concatenate([[0], np.cumsum(hit, dtype=np.int64)])
        # Blocks are laid over the run of all texts. Each holds one more block's width, so that grams over a border count fully.
        edge = np.arange(0, len(hit), BLOCK)
        full = cum[np.minimum(edge + BLOCK, len(hit))] - cum[edge] >= self.share
        dense = edge[full]
        first, last = np.searchsorted(cuts, dense, "right") - 1, np.searchsorted(cuts, np.minimum(dense + BLOCK - 1, len(flat) - 1), "right") - 1
        docs = sorted({n for a, b in zip(first.tolist(), last.tolist()) for n in range(a, b + 1)})
        for n in docs:
            a, b = int(cuts[n]), int(cuts[n + 1])
            if b - a < Q:
                continue
            pos = np.flatnonzero(hit[a : b - Q + 1])
            out[n] += self._bands(texts[n], g[a : b - Q + 1], pos)
        return out

    def _bands(self, text: str, g: np.ndarray, pos: np.ndarray) -> list[tuple[int, int, int, int]]:
        lo, hi = np.searchsorted(self.g, g[pos], "left"), np.searchsorted(self.g, g[pos], "right")
        n = hi - lo
        total = int(n.sum())
        if not total:
            return []
        where = np.repeat(pos, n)
        entry = np.arange(total) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)
        who, diag = self.who[entry], where - self.at[entry]
        half = self.budget[who] + 1
        band = diag // half  # a band is [band * half, (band + 2) * half): each diagonal lies in two of them
        shift = len(g) + int(max(len(x[2]) for x in self.items)) + 2
        longest = shift - len(g)
        key = np.concatenate([who * (4 * shift) + band + shift, who * (4 * shift) + band - 1 + shift])
        # a gram that repeats in the text counts once for each of its places in the passage at most
        key = np.unique(key * longest + np.tile(self.at[entry], 2)) // longest
        keys, counts = np.unique(key, return_counts=True)
        whose = keys // (4 * shift)
        keep = counts >= self.bound[whose]
        found: dict[int, tuple] = {}
        region = None
        for k, b in zip(whose[keep].tolist(), (keys[keep] % (4 * shift) - shift).tolist()):
            item, _, f = self.items[k]
            region = folded(text) if region is None else region
            budget = int(self.budget[k])
            if k in found and found[k][0] == 0:
                continue
            exact = _exact(region, f, diag[who == k])
            if exact is not None:
                found[k] = (0, exact, exact + len(f))
                continue
            low, width = b * (budget + 1) - budget, 2 * (budget + 1) + 2 * budget
            first = max(0, low)
            piece = region[first : low + width + len(f) + budget]
            got = best_alignment(f, piece, low - first, width, budget)
            if got:
                new = (got[0], got[1] + first, got[2] + first)
                found[k] = min(found.get(k, new), new)
        return [(self.items[k][0], s, e, d) for k, (d, s, e) in sorted(found.items())]


def _exact(text: np.ndarray, what: np.ndarray, diagonals: np.ndarray) -> int | None:
    """Smallest start of a verbatim occurrence: all of its q-grams lie on one diagonal."""
    ds, n = np.unique(diagonals, return_counts=True)
    for d in ds[n > len(what) - Q].tolist():
        if d >= 0 and np.array_equal(text[d : d + len(what)], what):
            return d
    return None


def _find(text: np.ndarray, what: np.ndarray) -> int:
    if len(what) > len(text):
        return -1
    same = np.ones(len(text) - len(what) + 1, bool)
    for i, c in enumerate(what):
        same &= text[i : len(text) - len(what) + 1 + i] == c
    at = np.flatnonzero(same)
    return int(at[0]) if len(at) else -1


def passage_chunks(benchmark: DataFrame, chunk_chars: int = CHUNK_CHARS):
    """The passages in chunks of bounded size, streamed to the driver: each chunk is one pass over the documents."""
    chunk, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("i"), F.col("text").cast("string").alias("t")).where("t is not null and t <> ''").distinct().orderBy("i", "t").toLocalIterator():
        if chunk and size + len(r.t) > chunk_chars:
            yield chunk
            chunk, size = [], 0
        chunk.append((r.i, r.t))
        size += len(r.t)
    if chunk:
        yield chunk


def _segments(col, n: int):
    at = 0
    while at < n:
        texts, chars = [], 0
        while at + len(texts) < n and chars < SEGMENT_CHARS:
            texts.append(col[at + len(texts)].as_py() or "")
            chars += len(texts[-1])
        yield at, texts
        at += len(texts)


def contaminated_spans(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """doc_id, item_id, start, end, edits for every passage found in every document."""
    schema = "doc_id long, item_id long, start long, end long, edits long"
    spark, out = docs.sparkSession, None
    small_batches(spark)
    for chunk in passage_chunks(benchmark, chunk_chars):
        items = spark.sparkContext.broadcast(chunk)

        def run(batches, items=items):
            passages = Passages(items.value, rate)
            for batch in batches:
                for at, texts in _segments(batch.column(1), batch.num_rows):
                    rows = [(batch.column(0)[at + n].as_py(), *r) for n, rs in enumerate(passages.near(texts)) for r in rs]
                    cols = list(zip(*rows)) or [[]] * 5
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "item_id", "start", "end", "edits"])

        part = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    return out if out is not None else spark.createDataFrame([], schema)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """`docs`, all columns, without the documents that hold a passage. Rows are judged in place; nothing is joined."""
    spark, text_at = docs.sparkSession, docs.columns.index("text")
    small_batches(spark)
    for chunk in passage_chunks(benchmark, chunk_chars):
        items = spark.sparkContext.broadcast(chunk)

        def run(batches, items=items):
            passages = Passages(items.value, rate)
            for batch in batches:
                keep = [not f for _, texts in _segments(batch.column(text_at), batch.num_rows) for f in passages.near(texts)]
                yield batch.filter(pa.array(keep, pa.bool_()))

        docs = docs.mapInArrow(lean(run), docs.schema)
    return docs
