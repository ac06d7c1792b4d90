"""Exact top-k by inner product with a three-phase uniform threshold.

The components of the vectors are cut into `lists` runs; a vector's partial products over a run form one score list,
and its score is the sum over lists. Lists are kept apart: phases see entries of single lists, and sums are made only for chosen entries.
  1. Gather: every list of a block of vectors gives its leaders for each query; the missing entries of these few are
     looked up in the other lists. The k-th best score met for a query is a safe cutoff: the true k-th best is no lower.
  2. Collect: with the cutoff spread evenly, cutoff / lists, any vector that reaches it has an entry at or above this
     uniform threshold in some list. Only vectors with such an entry are collected.
  3. Resolve: their missing entries are below the threshold, which bounds their score; for those whose bound reaches the cutoff the missing
     entries are looked up, and the best k of a block that reach the cutoff go on. A last ranking over blocks gives the result.
The lists lie together in a block, so entries are collected and looked up without a shuffle; what leaves a block is at most k rows
a query. The lists of a block are made in both passes, since storing them would take a number a pair.

Each block of vectors is shuffled once a pass, and the queries, the smaller side, go to each block; cutoffs travel with the queries. So
nothing that grows with the data is broadcast, and a task holds one block of vectors and one of queries at a time.

Components are floor(256 x) as integers. Products are exact: in float64 while sums stay under 2^53, in int64 beyond;
scores must fit a long. Vectors that are null or hold a null or non-finite component, and rows with a null vec_id, take no part. Shorter
vectors count as padded with zeros, empty ones as zeros. A repeated vec_id stands for one candidate with its best score, and as a query for one
query with its first vector in order of components; a query is never a candidate for itself by id. Ties go to the smaller vec_id. An empty table
gives an empty result. Only vec_id and embedding are read, so other columns may have any names.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F

K, LISTS = 5, 4
BLOCK_ROWS, QUERY_ROWS = 8192, 512
NONE = -(1 << 62)


def eligible(vectors: DataFrame) -> DataFrame:
    """(vec_id, comps array<long>) of the vectors that take part."""
    x = F.transform("embedding", lambda v: v.cast("double"))
    whole = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x")).where(F.col("vec_id").isNotNull() & F.col("x").isNotNull() & whole).select("vec_id", F.transform("x", lambda v: F.floor(v * 256.0)).alias("comps"))


def _matrix(lists: pa.Array) -> np.ndarray:
    n = np.diff(np.asarray(lists.offsets)) if len(lists) else np.empty(0, int)
    flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((len(n), int(n.max(initial=0))), np.int64)
    out[np.arange(out.shape[1])[None, :] < n[:, None]] = flat
    return out


def _pack(tag: str, most: int, extra: bool):
    """Rows of a partition to blocks: group, ids, width, components (int32 if they fit) and, for queries, cutoffs."""

    def run(batches):
        group = TaskContext.get().partitionId()
        for batch in batches:
            for at in range(0, batch.num_rows, most):
                part = batch.slice(at, most)
                m = _matrix(part.column(1))
                kind = np.int32 if not m.size or np.abs(m).max() < 1 << 31 else np.int64
                row = {f"{tag}g": pa.array([group], pa.int32()), f"{tag}ids": pa.array([part.column(0).to_numpy().tobytes()], pa.binary()), f"{tag}w": pa.array([m.shape[1]], pa.int32()), f"{tag}m": pa.array([m.astype(kind).tobytes()], pa.binary())}
                if extra:
                    row[f"{tag}cut"] = pa.array([part.column(2).to_numpy().tobytes()], pa.binary())
                yield pa.RecordBatch.from_pydict(row)

    return run


def _blocks(df: DataFrame, tag: str, groups: int, most: int, extra: bool = False) -> DataFrame:
    schema = f"{tag}g int, {tag}ids binary, {tag}w int, {tag}m binary" + (f", {tag}cut binary" if extra else "")
    return df.repartition(groups).mapInArrow(_pack(tag, most, extra), schema)


def _open(ids: bytes, w: int, m: bytes):
    keys = np.frombuffer(ids, np.int64)
    size = 4 if len(keys) * w * 4 == len(m) else 8
    return keys, np.frombuffer(m, np.int32 if size == 4 else np.int64).reshape(len(keys), w).astype(np.int64)


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[1])
    return (a.astype(float) @ b.T.astype(float)).astype(np.int64) if most < 2**53 else a @ b.T


def _partials(q: np.ndarray, d: np.ndarray, lists: int) -> list[np.ndarray]:
    w = min(q.shape[1], d.shape[1])
    cuts = np.linspace(0, w, lists + 1).astype(int)
    return [_product(q[:, a:b], d[:, a:b]) for a, b in zip(cuts, cuts[1:])]


def _leaders(scores: np.ndarray, k: int) -> np.ndarray:
    return np.argpartition(-scores, k - 1, axis=1)[:, :k] if scores.shape[1] > k else np.tile(np.arange(scores.shape[1]), (len(scores), 1))


def _emit(qids, dids, rows, cols, scores):
    return pa.RecordBatch.from_arrays([pa.array(qids[rows]), pa.array(dids[cols]), pa.array(scores)], names=["query_id", "vec_id", "score"])


def _summed(parts: list[np.ndarray], rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """Scores of single pairs: their entries looked up in every list."""
    out = np.zeros(len(rows), np.int64)
    for p in parts:
        out += p[rows, cols]
    return out


def _gather(k: int, lists: int):
    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                (qi, q), (di, d) = _open(r["qids"], r["qw"], r["qm"]), _open(r["dids"], r["dw"], r["dm"])
                parts = _partials(q, d, lists)
                chosen = np.concatenate([_leaders(p, k + 1) for p in parts], axis=1)  # a query's leaders of every list
                rows, cols = np.repeat(np.arange(len(qi)), chosen.shape[1]), chosen.ravel()
                pair = np.unique(rows * np.int64(len(di)) + cols)
                rows, cols = pair // max(1, len(di)), pair % max(1, len(di))
                other = qi[rows] != di[cols]
                rows, cols = rows[other], cols[other]
                score = _summed(parts, rows, cols)
                order = np.lexsort((di[cols], -score, rows))
                rows, cols, score = rows[order], cols[order], score[order]
                best = np.arange(len(rows)) - np.searchsorted(rows, rows, "left") < k
                yield _emit(qi, di, rows[best], cols[best], score[best])

    return run


def _resolve(k: int, lists: int):
    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                (qi, q), (di, d) = _open(r["qids"], r["qw"], r["qm"]), _open(r["dids"], r["dw"], r["dm"])
                cutoff = np.frombuffer(r["qcut"], np.int64)
                uniform = np.floor_divide(cutoff, lists)[:, None]
                parts = _partials(q, d, lists)
                seen = [p >= uniform for p in parts]
                collected = np.logical_or.reduce(seen) & (qi[:, None] != di[None, :])
                bound = sum(np.where(s, p, uniform + 1) for s, p in zip(seen, parts))
                rows, cols = np.nonzero(collected & (bound >= cutoff[:, None]))
                exact = _summed(parts, rows, cols)
                ok = exact >= cutoff[rows]
                rows, cols, exact = rows[ok], cols[ok], exact[ok]
                order = np.lexsort((di[cols], -exact, rows))
                rows, cols, exact = rows[order], cols[order], exact[order]
                if len(np.unique(di)) == len(di):  # else equal ids could push others out
                    first = np.searchsorted(rows, rows, "left")
                    best = np.arange(len(rows)) - first < k
                    rows, cols, exact = rows[best], cols[best], exact[best]
                yield _emit(qi, di, rows, cols, exact)

    return run


def top_k(vectors: DataFrame, queries: DataFrame, k: int = K, lists: int = LISTS) -> DataFrame:
    """query_id, rank, vec_id, score: the k best of `vectors` for each of `queries` (both vec_id, embedding)."""
    data = eligible(vectors)
    asked = eligible(queries).groupBy("vec_id").agg(F.min("comps").alias("comps"))
    n, nq = data.count(), asked.count()
    g, h = max(1, -(-n // BLOCK_ROWS)), max(1, -(-nq // QUERY_ROWS))
    d = _blocks(data, "d", g, BLOCK_ROWS)

    def meet(qs: DataFrame) -> DataFrame:
        # a row a group: the vectors are the side that is held, the queries pass by
        q = qs.withColumn("to_d", F.explode(F.sequence(F.lit(0), F.lit(g - 1))))
        return q.join(d.hint("shuffle_hash"), F.col("dg") == F.col("to_d"))

    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    one = lambda df: df.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    out = "query_id long, vec_id long, score long"
    gathered = meet(_blocks(asked, "q", h, QUERY_ROWS)).select("qids", "qw", "qm", "dids", "dw", "dm").mapInArrow(_gather(k, lists), out)
    cut = one(gathered).withColumn("r", F.row_number().over(best)).where(F.col("r") == k).select("query_id", F.col("score").alias("cutoff"))
    told = asked.join(cut, F.col("vec_id") == F.col("query_id"), "left").select("vec_id", "comps", F.coalesce("cutoff", F.lit(NONE)).alias("cutoff"))
    resolved = meet(_blocks(told, "q", h, QUERY_ROWS, True)).select("qids", "qw", "qm", "qcut", "dids", "dw", "dm").mapInArrow(_resolve(k, lists), out)
    return one(resolved).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
