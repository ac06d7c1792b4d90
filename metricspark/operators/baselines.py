"""Baselines: exhaustive scan, pivot-key index, layered pivot index, one tree on one machine, a graph index per worker, a grid.

The pivot indexes follow the public descriptions of their families; the graph index is approximate and answers
nearest-neighbour queries only.
"""
from __future__ import annotations

import heapq
import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.metrics import Metric, pair_column, within
from ..sources.tables import accepted, discard, written
from .global_index import _descend, plan_tree
from .sampling import hash_sample, pair_distances
from .search import BLOCK, nearest_by_block, rank_answers, with_radius
from .sizes import MOST_ROWS, sized


class NotSupported(Exception):
    """The method has no such query."""


# ---- exhaustive scan: the ground truth ----


def scan_range(objects: DataFrame, metric: Metric, queries: DataFrame, r: float | None = None, dim: int | None = None) -> DataFrame:
    """[qid, oid, dist]: every object against every query: a broadcast batch of queries, or blocks of both sides where there are too many."""
    q = sized(with_radius(queries, r))
    j = objects.select("oid", "obj").crossJoin(q)
    d, ok = within(metric, F.col("q"), F.col("obj"), F.col("r"), dim)
    return j.withColumn("dist", d).where(ok if metric.name == "edit" else F.col("dist") <= F.col("r")).select("qid", "oid", "dist")


def scan_knn(objects: DataFrame, metric: Metric, queries: DataFrame, k: int, dim: int | None = None) -> DataFrame:
    """[qid, rank, oid, dist]: the k best a task, then the k best of these."""
    j = objects.select("oid", "obj").crossJoin(sized(queries.select("qid", "q")))
    return rank_answers(j.withColumn("dist", pair_column(metric, F.col("q"), F.col("obj"), dim)).withColumn("k", F.lit(k)))


# ---- pivot-key index ----


@dataclass(frozen=True)
class PivotKeyIndex:
    metric: Metric
    dim: int | None
    pivots: DataFrame  # [pivot, p_obj, p_max]
    objects: DataFrame  # [pivot, d_p, key, oid, obj], ordered by key
    spread: float


def _pivots(objects: DataFrame, n: int, seed: int) -> list:
    seen: dict = {}
    for r in hash_sample(objects, 2 * n, seed).select("obj").collect():
        seen.setdefault(r.obj if isinstance(r.obj, str) else tuple(r.obj), r.obj)
    return list(seen.values())[:n]


def pivot_key_build(objects: DataFrame, metric: Metric, n_pivots: int = 32, n_w: int = 10, seed: int = 5, dim: int | None = None) -> PivotKeyIndex:
    """Each object goes to its nearest pivot i; its key i * C + d orders the index, cut into ranges of keys."""
    spark = objects.sparkSession
    pivots = _pivots(objects, n_pivots, seed)
    kind = objects.schema["obj"].dataType.simpleString()
    p = spark.createDataFrame(list(enumerate(pivots)), f"pivot int, p_obj {kind}")
    allp = p.agg(F.sort_array(F.collect_list(F.struct("pivot", "p_obj"))).alias("ps"))  # a parameter's worth of rows
    near = objects.select("oid", "obj").crossJoin(F.broadcast(allp))
    near = near.withColumn("near", F.array_min(F.transform("ps", lambda x: F.struct(metric.column(F.col("obj"), x["p_obj"], dim).alias("d"), x["pivot"].alias("i")))))
    near = near.select(F.col("near.i").alias("pivot"), F.col("near.d").alias("d_p"), "oid", "obj")
    spread = float(near.agg(F.max("d_p")).first()[0] or 0.0) + 1.0
    keyed = near.withColumn("key", F.col("pivot") * spread + F.col("d_p"))
    kept = written(keyed.repartitionByRange(n_w, "key").sortWithinPartitions("key"), "pivot-key")
    cells = kept.groupBy(F.col("pivot").alias("c_")).agg(F.max("d_p").alias("p_max"))
    cells = p.join(cells, F.col("pivot") == F.col("c_")).select("pivot", "p_obj", "p_max")
    rows = cells.collect()  # one row a pivot
    return PivotKeyIndex(metric, dim, spark.createDataFrame(rows, cells.schema) if rows else cells, kept, spread)


def pivot_key_candidates(idx: PivotKeyIndex, queries: DataFrame) -> DataFrame:
    """[qid, q, r, oid, obj]: objects in the key interval of some cell that the query's ball can meet."""
    m = idx.metric
    cells = queries.crossJoin(F.broadcast(idx.pivots)).withColumn("d_q", m.column(F.col("q"), F.col("p_obj"), idx.dim))
    r = m.slack(F.col("r"))
    nearest = F.min("d_q").over(Window.partitionBy("qid"))
    cells = cells.withColumn("near_", nearest).where((F.col("d_q") - r <= F.col("p_max")) & ((F.col("d_q") - F.col("near_")) / 2 <= r))  # ball and hyperplane tests
    low, high = F.greatest(F.col("d_q") - r, F.lit(0.0)), F.least(F.col("d_q") + r, F.col("p_max"))
    cells = cells.select("qid", "q", "r", F.col("pivot").alias("c_"), (F.col("pivot") * idx.spread + low - 1e-9).alias("k0"), (F.col("pivot") * idx.spread + high + 1e-9).alias("k1"))
    return idx.objects.join(sized(cells), (F.col("pivot") == F.col("c_")) & F.col("key").between(F.col("k0"), F.col("k1"))).select("qid", "q", "r", "oid", "obj")


def _verified(cand: DataFrame, metric: Metric, dim) -> DataFrame:
    d, ok = within(metric, F.col("q"), F.col("obj"), F.col("r"), dim)
    return cand.withColumn("dist", d).where(ok if metric.name == "edit" else F.col("dist") <= F.col("r")).select("qid", "oid", "dist")


def pivot_key_range(idx: PivotKeyIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    return _verified(pivot_key_candidates(idx, with_radius(queries, r)), idx.metric, idx.dim)


def _widening(objects: DataFrame, metric: Metric, dim, queries: DataFrame, k: int, search) -> DataFrame:
    """Range searches with doubling radii until every query has k answers; queries still open beyond the sampled diameter are scanned."""
    n = objects.count()
    stats = pair_distances(objects, metric, 60, 3, dim).agg(F.percentile("d", F.lit(min(1.0, 2.0 * k / max(1, n)))).alias("r"), F.max("d").alias("m")).first()
    r, most = max(stats.r or 0.0, (stats.m or 1.0) / 1024, 1e-9), 4 * (stats.m or 1.0)
    left, done = queries.select("qid", "q"), None
    while True:
        found = written(search(left.withColumn("r", F.lit(float(r)))), "widening")
        full = found.groupBy(F.col("qid").alias("f_")).agg(F.count("*").alias("n_")).where(F.col("n_") >= min(k, n))
        ok = found.join(full, F.col("qid") == F.col("f_"), "left_semi")
        done = ok if done is None else done.unionByName(ok)
        left = written(left.join(full, F.col("qid") == F.col("f_"), "left_anti"), "open-queries")
        if left.isEmpty():
            return rank_answers(done.withColumn("k", F.lit(k)))
        if r > most:  # the sample says nothing of farther objects
            rest = scan_knn(objects, metric, left, k, dim).select("qid", "oid", "dist")
            return rank_answers(done.unionByName(rest).withColumn("k", F.lit(k)))
        r *= 2


def pivot_key_knn(idx: PivotKeyIndex, queries: DataFrame, k: int) -> DataFrame:
    return _widening(idx.objects.select("oid", "obj"), idx.metric, idx.dim, queries, k, lambda q: pivot_key_range(idx, q))


# ---- layered pivot index ----


@dataclass(frozen=True)
class LayeredPivotIndex:
    metric: Metric
    dim: int | None
    pivots: list
    boxes: DataFrame  # [box, lo, hi, n]: per box the least and largest distance to each pivot
    objects: DataFrame  # [box, v, oid, obj]


def layered_pivot_build(objects: DataFrame, metric: Metric, n_pivots: int = 4, box_rows: int = 500, n_w: int = 10, seed: int = 9, dim: int | None = None) -> LayeredPivotIndex:
    """Objects as vectors of distances to the pivots; pivot space is cut into blocks by quantiles of the distance to each pivot in turn (layer 1),
    as many as give about `box_rows` objects a block, blocks go to workers by number (layer 2), and every block keeps
    its box of least and largest distances (layer 3)."""
    pivots = _pivots(objects, n_pivots, seed)
    lit = lambda o: F.lit(o) if isinstance(o, str) else F.array(*[F.lit(float(x)) for x in o])
    mapped = written(objects.select("oid", "obj", F.array(*[metric.column(F.col("obj"), lit(p), dim) for p in pivots]).alias("v")), "pivot-vectors")
    n, rows = len(pivots), mapped.count()
    per = max(2, round(max(1, rows / box_rows) ** (1 / max(1, n))))
    # the cut points of a pivot's distances, all pivots at once: n * (per - 1) numbers
    qs = mapped.agg(*[F.percentile_approx(F.col("v")[k], [j / per for j in range(1, per)], 1000).alias(f"q{k}") for k in range(n)]).first() if n else []
    cell = F.lit(0).cast("long")
    for k in range(n):
        cuts = F.array(*[F.lit(float(x)) for x in qs[k] or []])
        cell = cell * per + F.size(F.filter(cuts, lambda x: F.col("v")[k] > x))
    boxed = written(mapped.withColumn("box", cell).repartition(n_w, "box").sortWithinPartitions("box"), "layered-pivot")
    discard(mapped)
    boxes = boxed.groupBy("box").agg(F.array(*[F.min(F.col("v")[k]) for k in range(n)]).alias("lo"), F.array(*[F.max(F.col("v")[k]) for k in range(n)]).alias("hi"), F.count("*").alias("n"))
    return LayeredPivotIndex(metric, dim, pivots, written(boxes, "boxes"), boxed)


def layered_pivot_candidates(idx: LayeredPivotIndex, queries: DataFrame) -> DataFrame:
    m, n = idx.metric, len(idx.pivots)
    lit = lambda o: F.lit(o) if isinstance(o, str) else F.array(*[F.lit(float(x)) for x in o])
    q = queries.select("qid", "q", "r", F.array(*[m.column(F.col("q"), lit(p), idx.dim) for p in idx.pivots]).alias("qv"))
    r = m.slack(F.col("r"))
    meet = F.lit(True)
    for k in range(n):
        meet = meet & (F.col("qv")[k] + r >= F.col("lo")[k]) & (F.col("qv")[k] - r <= F.col("hi")[k])
    hit = q.crossJoin(sized(idx.boxes)).where(meet).select("qid", "q", "r", "qv", F.col("box").alias("b_"))
    near = F.lit(True)
    for k in range(n):
        near = near & (F.abs(F.col("v")[k] - F.col("qv")[k]) <= r)
    return idx.objects.join(sized(hit), F.col("box") == F.col("b_")).where(near).select("qid", "q", "r", "oid", "obj", "box")


def layered_pivot_range(idx: LayeredPivotIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    return _verified(layered_pivot_candidates(idx, with_radius(queries, r)), idx.metric, idx.dim)


def layered_pivot_knn(idx: LayeredPivotIndex, queries: DataFrame, k: int) -> DataFrame:
    return _widening(idx.objects.select("oid", "obj"), idx.metric, idx.dim, queries, k, lambda q: layered_pivot_range(idx, q))


# ---- one tree on one machine ----

LEAF_OBJECTS = 200  # objects a leaf of the one tree on average
TOGETHER = 500  # queries that walk the one tree together
MOST_PAIRS = 2_000_000  # pairs of query and object that are measured at once
DESCEND_ROWS = 500_000


def _bounded(queries: DataFrame) -> list[tuple]:
    """The queries of a method that hands all of them to every task; more than MOST_ROWS are refused."""
    rows = queries.select("qid", "q").limit(MOST_ROWS + 1).collect()
    if len(rows) > MOST_ROWS:
        raise ValueError(f"more than {MOST_ROWS} queries; ask them in batches")
    return [(r.qid, r.q) for r in rows]


def _spread(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The numbers first, first + 1, ... of every run, one run after the other."""
    return np.repeat(first - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())


class OneTree:
    """An M-tree of all objects in arrays, level by level, walked by many queries at once.

    A level's nodes are ordered by parent, so children are runs; objects are ordered by leaf. With `k` only the k smallest ids of
    equal objects are kept: no other can be among the k nearest.
    """

    def __init__(self, metric: Metric, ids: np.ndarray, batch, fanout: int, n_p: int, k: int | None):
        self.metric, self.k = metric, k
        order = np.argsort(ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15), kind="stable")[: max(n_p, len(ids) // LEAF_OBJECTS)]
        tree = plan_tree(self._plain(metric.take(batch, order)), fanout, metric, 1 << 31)
        leaf, d_leaf = np.empty(len(ids), np.int32), np.empty(len(ids))
        radius, n = np.zeros(len(tree.nodes)), np.zeros(len(tree.nodes), np.int64)
        up = np.array([x.parent_id for x in tree.nodes])
        for lo in range(0, len(ids), DESCEND_ROWS):
            rows = slice(lo, lo + DESCEND_ROWS)
            at, d = _descend(metric, tree, metric.take(batch, rows))
            leaf[rows], d_leaf[rows] = at, d[:, -1]
            for level in range(tree.height - 1, -1, -1):
                np.maximum.at(radius, at, d[:, level])
                n += np.bincount(at, minlength=len(n))
                at = up[at]
        self.levels, above = [], np.array([-1])
        for level in range(1, tree.height + 1):
            here = [x for x in tree.nodes if x.level == level and n[x.node_id]]
            place = np.full(len(tree.nodes) + 1, -1)
            place[above] = np.arange(len(above))
            here.sort(key=lambda x: place[x.parent_id])
            at = np.array([x.node_id for x in here])
            first = np.searchsorted(place[up[at]], np.arange(len(above) + 1))
            self.levels.append((metric.batch([x.center for x in here]), radius[at], n[at], np.array([x.dist_to_parent for x in here]), first))
            above = at
        place = np.full(len(tree.nodes), -1)
        place[above] = np.arange(len(above))
        of = place[leaf]
        words = self._plain(batch) if metric.kind == "string" else None
        alike = [np.unique(np.array(words, object), return_inverse=True)[1]] if words else list(batch.T)
        order = np.lexsort((ids, *alike, of))
        if k is not None:
            new = np.ones(len(ids), bool)
            new[1:] = of[order[1:]] != of[order[:-1]]
            for column in alike:
                new[1:] |= column[order[1:]] != column[order[:-1]]
            starts = np.flatnonzero(new)
            order = order[np.arange(len(ids)) - np.repeat(starts, np.diff(np.append(starts, len(ids)))) < k]
        self.ids, self.batch, self.d_leaf = ids[order], metric.take(batch, order), d_leaf[order]
        self.first = np.searchsorted(of[order], np.arange(len(above) + 1))

    @staticmethod
    def _plain(batch) -> list:
        if not isinstance(batch, tuple):
            return list(batch)
        return [codes[:n].tobytes().decode("utf-32-le", "surrogatepass") for codes, n in zip(batch[0], batch[1].tolist())]

    def _distances(self, batch, rows: np.ndarray, queries, of: np.ndarray) -> np.ndarray:
        """Of object rows[i] to query of[i]; `of` ascends."""
        if self.metric.rows is not None:
            return self.metric.rows(batch[rows], queries[of])
        starts = np.flatnonzero(np.diff(of, prepend=-1))
        parts = [self.metric.kernel(self.metric.take(batch, rows[lo:hi]), queries[of[lo]]) for lo, hi in zip(starts, np.append(starts[1:], len(of)))]
        return np.concatenate(parts) if parts else np.empty(0)

    def search(self, queries, r: float | None = None):
        """Tables (query number, id, distance): all within r, or the k nearest and those that equal the last of them but for rounding."""
        m = len(queries)
        bound = np.full(m, math.inf if r is None else r + 1e-9)
        of, at, up = np.repeat(np.arange(m), len(self.levels[0][1])), np.tile(np.arange(len(self.levels[0][1])), m), None
        for depth, (centers, radius, n, to_parent, _) in enumerate(self.levels):
            if up is not None:
                near = np.abs(to_parent[at] - up) <= bound[of] + radius[at] + 1e-9
                of, at = of[near], at[near]
            d = self._distances(centers, at, queries, of)
            if r is None and len(of):
                upper = d + radius[at]
                order = np.lexsort((upper, of))
                starts = np.flatnonzero(np.diff(of, prepend=-1))
                held = np.cumsum(n[at][order])
                held -= np.repeat(held[starts] - n[at][order][starts], np.diff(np.append(starts, len(of))))
                least = np.minimum.reduceat(np.where(held >= self.k, upper[order], math.inf), starts)
                bound[of[starts]] = np.minimum(bound[of[starts]], least * (1 + 1e-9) + 1e-9)
            alive = d - radius[at] <= bound[of]
            of, at, d = of[alive], at[alive], d[alive]
            first = self.levels[depth + 1][4] if depth + 1 < len(self.levels) else self.first
            size = first[at + 1] - first[at]
            if depth + 1 < len(self.levels):
                at, of, up = _spread(first[at], size), np.repeat(of, size), np.repeat(d, size)
        total = np.cumsum(size)
        while len(of):
            cut = max(np.searchsorted(total, total[0] - size[0] + MOST_PAIRS), 1)
            cut = np.searchsorted(of, of[cut], side="left") if cut < len(of) else len(of)
            cut = cut or np.searchsorted(of, of[0], side="right")
            yield self._measured(queries, bound, r, of[:cut], first[at[:cut]], size[:cut], d[:cut])
            of, at, size, d, total = of[cut:], at[cut:], size[cut:], d[cut:], total[cut:]

    def _measured(self, queries, bound, r, of, first, size, d):
        rows, of, d = _spread(first, size), np.repeat(of, size), np.repeat(d, size)
        near = np.abs(self.d_leaf[rows] - d) <= bound[of] + 1e-9
        rows, of = rows[near], of[near]
        dist = self._distances(self.batch, rows, queries, of)
        near = dist <= (bound[of] if r is None else r)
        rows, of, dist = rows[near], of[near], dist[near]
        if r is None and len(of):
            order = np.lexsort((self.ids[rows], dist, of))
            rows, of, dist = rows[order], of[order], dist[order]
            starts = np.flatnonzero(np.diff(of, prepend=-1))
            size = np.diff(np.append(starts, len(of)))
            last = dist[starts + np.minimum(self.k, size) - 1]
            equal = np.flatnonzero((np.diff(of, prepend=-1) != 0) | (np.diff(dist, prepend=-1) != 0))
            nth = np.arange(len(of)) - np.repeat(equal, np.diff(np.append(equal, len(of))))
            kept = (dist <= np.repeat(last, size) + 2e-9) & (nth < self.k)  # ties are decided on rounded distances
            rows, of, dist = rows[kept], of[kept], dist[kept]
        return of, self.ids[rows], dist


def single_mtree(objects: DataFrame, metric: Metric, queries: DataFrame, k: int | None = None, r: float | None = None, n_p: int = 200, fanout: int = 20) -> DataFrame:
    """[qid, rank, oid, dist] or [qid, oid, dist] from one tree that a single task builds and searches; objects and queries must fit its memory.

    The tree has at least `n_p` leaves, more where they would hold over LEAF_OBJECTS on average. Any number of queries; they walk it in batches.
    """
    asked = queries.where("q is not null").select(F.lit(True).alias("asks"), F.col("qid").alias("id"), F.col("q").alias("obj"))
    rows = accepted(objects, metric, None).select(F.lit(False).alias("asks"), F.col("oid").alias("id"), "obj").unionByName(asked)

    def run(batches):
        ids, objs = {False: [], True: []}, {False: [], True: []}
        for b in batches:
            for asks in (False, True):
                part = b.filter(b.column(0) if asks else pc.invert(b.column(0)))
                if len(part):
                    ids[asks].append(part.column(1).to_numpy())
                    objs[asks] += part.column(2).to_pylist() if metric.kind == "string" else [metric.from_arrow(part.column(2))]
        if not ids[False]:
            return
        qid = np.concatenate(ids[True]) if ids[True] else np.empty(0, np.int64)
        qs = np.concatenate(objs[True]) if ids[True] and metric.kind == "vector" else objs[True]
        batch = metric.batch(objs[False]) if metric.kind == "string" else np.concatenate(objs[False])
        objs.clear()
        tree = OneTree(metric, np.concatenate(ids[False]), batch, fanout, n_p, k)
        for lo in range(0, len(qid), TOGETHER):
            for of, oid, dist in tree.search(qs[lo : lo + TOGETHER], r if k is None else None):
                yield pa.RecordBatch.from_arrays([pa.array(qid[lo + of]), pa.array(oid), pa.array(dist)], names=["qid", "oid", "dist"])

    found = rows.coalesce(1).mapInArrow(run, "qid long, oid long, dist double")
    return found if k is None else rank_answers(found.withColumn("k", F.lit(k)))


# ---- a small-world graph a worker ----


class SmallWorld:
    """A layered small-world graph: each node links to near ones found by a greedy beam search at insertion."""

    def __init__(self, metric: Metric, m: int = 8, ef: int = 40, seed: int = 1):
        self.metric, self.m, self.ef, self.rng = metric, m, ef, np.random.default_rng(seed)
        self.objs, self.levels, self.links, self.entry = [], [], [], -1

    def _dist(self, nodes: list[int], q) -> np.ndarray:
        return self.metric.kernel(self.metric.batch([self.objs[i] for i in nodes]), q)

    def _beam(self, q, start: list[int], level: int, ef: int) -> list[tuple[float, int]]:
        d = self._dist(start, q)
        front = [(float(x), i) for x, i in zip(d, start)]
        best = [(-x, i) for x, i in front]
        heapq.heapify(front)
        heapq.heapify(best)
        seen = set(start)
        while front:
            x, i = heapq.heappop(front)
            if x > -best[0][0] and len(best) >= ef:
                break
            new = [j for j in self.links[i].get(level, ()) if j not in seen]
            seen.update(new)
            for y, j in zip(self._dist(new, q) if new else [], new):
                if len(best) < ef or y < -best[0][0]:
                    heapq.heappush(front, (float(y), j))
                    heapq.heappush(best, (-float(y), j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-x, i) for x, i in best)

    def add(self, obj) -> None:
        q = obj if isinstance(obj, str) else np.asarray(obj, float)
        level, me = int(-math.log(max(self.rng.random(), 1e-12)) / math.log(self.m)), len(self.objs)
        self.objs.append(obj)
        self.links.append({})
        self.levels.append(level)
        if self.entry < 0:
            self.entry = me
            return
        at = [self.entry]
        for lv in range(self.levels[self.entry], level, -1):
            at = [self._beam(q, at, lv, 1)[0][1]]
        for lv in range(min(level, self.levels[self.entry]), -1, -1):
            near = self._beam(q, at, lv, self.ef)
            chosen = [i for _, i in near[: self.m]]
            self.links[me][lv] = list(chosen)
            for i in chosen:
                own = self.links[i].setdefault(lv, [])
                own.append(me)
                if len(own) > 2 * self.m:
                    c = self.objs[i]
                    d = self._dist(own, c if isinstance(c, str) else np.asarray(c, float))
                    self.links[i][lv] = [own[j] for j in np.argsort(d, kind="stable")[: 2 * self.m]]
            at = [i for _, i in near]
        if level > self.levels[self.entry]:
            self.entry = me

    def search(self, q, k: int, ef: int | None = None) -> list[tuple[float, int]]:
        if self.entry < 0:
            return []
        at = [self.entry]
        for lv in range(self.levels[self.entry], 0, -1):
            at = [self._beam(q, at, lv, 1)[0][1]]
        return self._beam(q, at, 0, max(k, ef or self.ef))[:k]


def graph_ann_knn(objects: DataFrame, metric: Metric, queries: DataFrame, k: int, n_w: int = 4, m: int = 8, ef: int = 40, group_rows: int = 20_000) -> DataFrame:
    """[qid, rank, oid, dist], approximate: a graph per group of at most about `group_rows` objects, all queries to all groups, best k merged."""
    groups = max(n_w, -(-objects.count() // group_rows))
    asked = _bounded(queries)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        g = SmallWorld(metric, m, ef)
        for o in pdf["obj"]:
            g.add(o if isinstance(o, str) else list(o))
        ids, rows = pdf["oid"].to_numpy(), []
        for qid, q in asked:
            rows += [(qid, int(ids[i]), float(d)) for d, i in g.search(q if isinstance(q, str) else np.asarray(q, float), k)]
        return pd.DataFrame(rows, columns=["qid", "oid", "dist"])

    dealt = objects.select("oid", "obj", F.pmod(F.xxhash64("oid", F.lit(17)), F.lit(groups)).alias("g_"))
    found = dealt.groupBy("g_").applyInPandas(run, "qid long, oid long, dist double")
    return rank_answers(found.withColumn("k", F.lit(k)))


def graph_ann_range(*_, **__):
    raise NotSupported("the graph index answers nearest-neighbour queries only")


# ---- grid over planar points ----


GRID = 3  # cells a radius: smaller cells meet fewer objects beyond it, at more rows a query


def grid_range(objects: DataFrame, queries: DataFrame, r: float) -> DataFrame:
    """[qid, oid, dist] for two-dimensional L2: an equi join on the cells that a query's ball can meet, GRID of them a radius.

    Cells are a little larger than that, so that rounding moves no answer out of their reach. Queries are the built side of a hash join by cell.
    """
    side = r * (1 + 1e-6) / GRID
    cell = lambda c, i: F.floor(F.col(c)[i] / F.lit(side))
    o = objects.select("oid", "obj", cell("obj", 0).alias("cx"), cell("obj", 1).alias("cy"))
    near = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in range(-GRID, GRID + 1) for j in range(-GRID, GRID + 1) if math.hypot(max(0, abs(i) - 1), max(0, abs(j) - 1)) <= GRID])
    q = queries.select("qid", "q", cell("q", 0).alias("x0"), cell("q", 1).alias("y0"), F.explode(near).alias("c"))
    q = q.select("qid", "q", (F.col("x0") + F.col("c.i")).alias("qx"), (F.col("y0") + F.col("c.j")).alias("qy"))
    dx, dy = F.col("obj")[0] - F.col("q")[0], F.col("obj")[1] - F.col("q")[1]
    return o.join(q.hint("shuffle_hash"), (F.col("cx") == F.col("qx")) & (F.col("cy") == F.col("qy"))).withColumn("dist", F.sqrt(dx * dx + dy * dy)).where(F.col("dist") <= r).select("qid", "oid", "dist")


# ---- naive nearest neighbours per slot ----


def per_slot_knn(idx, queries: DataFrame, k: int) -> DataFrame:
    """Every slot answers on its own without any bound; N_w full searches are merged. The costly contrast."""
    if idx.metric.kind == "vector":
        parts = max(1, math.ceil(idx.n / idx.n_w / BLOCK))  # a large slot is searched in parts
        block = F.col("slot") * parts + F.pmod(F.xxhash64("oid"), F.lit(parts))
        return rank_answers(nearest_by_block(idx.objects, idx.metric, queries, k, idx.n_w * parts, block, idx.dim))
    j = idx.objects.select("slot", "oid", "obj").crossJoin(sized(queries.select("qid", "q")))
    j = j.withColumn("dist", pair_column(idx.metric, F.col("q"), F.col("obj"), idx.dim))
    w = Window.partitionBy("qid", "slot").orderBy(F.round("dist", 9), "oid")
    return rank_answers(j.withColumn("r_", F.row_number().over(w)).where(F.col("r_") <= k).withColumn("k", F.lit(k)))
