"""Exact range and k-nearest-neighbour search over the index, as joins and filters.

Global candidates come level by level from the broadcast tree; candidates find their slot and bucket; local
clusters are pruned by an equi join on the partition; objects by an equi join on the local cluster, the stored-distance
filter, and last the metric itself. Each object lies in one bucket, so answers need no merging beyond a union.
"""
from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions import bounds
from ..functions.metrics import UNROLLED, Metric, edit_extremes, pair_column, within
from ..sources.tables import unfit, written
from .blocks import extreme_rows, nearest_rows, ranges
from .index import MetricIndex
from .intermediate import locate
from .sizes import MOST_BYTES


def with_radius(queries: DataFrame, r: float | None) -> DataFrame:
    """[qid, q, r]; `r` overrides, else the queries bring their own."""
    return queries.select("qid", "q", (F.lit(float(r)) if r is not None else F.col("r").cast("double")).alias("r"))


def level_of(idx: MetricIndex, level: int) -> DataFrame:
    """One level of the global tree, broadcast where its size, known from the tree, allows it; else Spark joins it."""
    n = idx.nodes.where(F.col("level") == level).select(F.col("node_id").alias("n_"), F.col("parent_id").alias("pa_"), "center", "radius", "dist_to_parent", F.col("n_objects").alias("no_"), F.col("pid").alias("np_"))
    here = [x for x in idx.tree.nodes if x.level == level and x.n_objects]
    size = sum(len(x.center) * (1 if idx.metric.kind == "string" else 8) + 64 for x in here)
    return F.broadcast(n) if size <= MOST_BYTES else n


def global_candidates(idx: MetricIndex, queries: DataFrame) -> DataFrame:
    """[qid, q, r, pid, validated, d_qc]: partitions no rule excludes. Queries meet the tree level by level; no shuffle of queries while levels are broadcast."""
    m, cand = idx.metric, None
    for level in range(1, idx.height + 1):
        n = level_of(idx, level)
        if cand is None:
            step = queries.crossJoin(n).withColumn("validated", F.lit(False))  # the top level has at most a fanout of nodes
        else:
            step = cand.join(n, F.col("node") == F.col("pa_"))
            step = step.where(F.col("validated") | ~bounds.parent_prunable(F.col("dist_to_parent"), F.col("d_qc"), F.col("radius"), m.slack(F.col("r")))).drop("d_qc")
        step = step.withColumn("d_qc", m.column(F.col("q"), F.col("center"), idx.dim))
        step = step.where(F.col("validated") | ~bounds.cluster_prunable(F.col("d_qc"), F.col("radius"), m.slack(F.col("r"))))
        step = step.withColumn("validated", F.col("validated") | bounds.cluster_valid(F.col("d_qc"), F.col("radius"), m.tight(F.col("r"))))
        cand = step.select("qid", "q", "r", F.col("n_").alias("node"), F.col("np_").alias("pid"), "validated", "d_qc")
    return (cand if cand is not None else queries.select("qid", "q", "r", F.lit(None).cast("long").alias("node"), F.lit(None).cast("long").alias("pid"), F.lit(False).alias("validated"), F.lit(0.0).alias("d_qc")).limit(0)).drop("node")


def local_levels(idx: MetricIndex, cand: DataFrame) -> list[tuple[DataFrame, DataFrame]]:
    """Per level of the local trees (tested, survivors): [qid, q, r, slot, bucket, pid, lnode_id, validated, d_ql] joined by partition, then by parent.

    Local trees differ in height: the leaf of a lower one is its own only child on the levels below it (`again`), so one chain of joins reaches all leaves.
    """
    m, out, now = idx.metric, [], None
    columns = ["qid", "q", "r", "slot", "bucket", "pid", "lnode_id", "validated", "d_ql"]
    for level in range(1, idx.local_height + 1):
        here = F.col("level") == level
        ln = idx.local_nodes.where(here | (F.col("is_leaf") & (F.col("level") < level)))
        ln = ln.select(F.col("pid").alias("lp_"), F.when(here, F.col("parent_id")).otherwise(F.col("lnode_id")).alias("lu_"), F.col("lnode_id").alias("ln_"), F.col("center").alias("lc_"), F.col("radius").alias("lr_"), F.when(here, F.col("dist_to_parent")).otherwise(0.0).alias("ld_"), (~here).alias("again"))
        if now is None:
            j = locate(cand, idx.placement.select("pid", "bucket", "slot")).join(ln, F.col("pid") == F.col("lp_"))
        else:
            j = now.join(ln, F.col("lnode_id") == F.col("lu_"))
            j = j.where(F.col("validated") | ~bounds.parent_prunable(F.col("ld_"), F.col("d_ql"), F.col("lr_"), m.slack(F.col("r")))).drop("d_ql", "lnode_id")
        j = j.withColumn("lnode_id", F.col("ln_")).withColumn("d_ql", m.column(F.col("q"), F.col("lc_"), idx.dim))
        kept = j.where(F.col("validated") | ~bounds.cluster_prunable(F.col("d_ql"), F.col("lr_"), m.slack(F.col("r"))))
        now = kept.withColumn("validated", F.col("validated") | bounds.cluster_valid(F.col("d_ql"), F.col("lr_"), m.tight(F.col("r")))).select(*columns)
        out.append((j, now))
    return out


def local_candidates(idx: MetricIndex, cand: DataFrame) -> DataFrame:
    """[qid, q, r, slot, bucket, pid, lnode_id, validated, d_ql]: local leaves that no rule excludes, by a walk down the local trees."""
    columns = ["qid", "q", "r", "slot", "bucket", "pid", "lnode_id", "validated", "d_ql"]
    if idx.local == "tree":
        return local_levels(idx, cand)[-1][1]
    ln = idx.local_nodes.select(F.col("pid").alias("lp_"), "lnode_id")
    j = locate(cand, idx.placement.select("pid", "bucket", "slot")).join(ln, F.col("pid") == F.col("lp_"))
    return j.withColumn("d_ql", F.col("d_qc") if idx.local == "flat" else F.lit(None).cast("double")).select(*columns)


def candidate_objects(idx: MetricIndex, lcand: DataFrame) -> DataFrame:
    """[qid, q, r, slot, bucket, oid, obj, validated, decided_by]: objects left to verify, and validated ones.

    The object files are joined on slot (dynamic partition pruning) and local cluster; `obj` is the only wide column
    and is read here for the first time.
    """
    m, r = idx.metric, F.col("r")
    o = idx.objects.select(F.col("slot").alias("os_"), F.col("lnode_id").alias("ol_"), F.col("d_leaf").alias("od_"), "oid", "obj", *(["dv", "pid"] if idx.local == "vantage" else []))
    if idx.local == "vantage":
        return _vantage_objects(idx, lcand, o)
    j = o.join(lcand, (F.col("os_") == F.col("slot")) & (F.col("ol_") == F.col("lnode_id")))
    if idx.local == "flat":
        return j.select("qid", "q", "r", "slot", "bucket", "oid", "obj", "validated", F.when(F.col("validated"), "validated_cluster").otherwise("verified").alias("decided_by"))
    j = j.where(F.col("validated") | ~bounds.object_prunable(F.col("od_"), F.col("d_ql"), m.slack(r)))
    by_object = bounds.object_valid(F.col("od_"), F.col("d_ql"), m.tight(r))
    decided = F.when(F.col("validated"), "validated_cluster").when(by_object, "validated_object").otherwise("verified")
    return j.select("qid", "q", "r", "slot", "bucket", "oid", "obj", (F.col("validated") | by_object).alias("validated"), decided.alias("decided_by"))


def _vantage_objects(idx: MetricIndex, lcand: DataFrame, o: DataFrame) -> DataFrame:
    """Objects whose distances to all vantage objects of their group differ from the query's by no more than r."""
    m = idx.metric
    v = idx.objects.where("rank_v >= 0").groupBy(F.col("lnode_id").alias("vl_")).agg(F.sort_array(F.collect_list(F.struct("rank_v", "obj"))).alias("vs_"))  # a fixed few a group
    q = lcand.join(v, F.col("lnode_id") == F.col("vl_")).withColumn("dq_", F.transform("vs_", lambda s: m.column(F.col("q"), s["obj"], None)))
    j = o.drop("pid").join(q, (F.col("os_") == F.col("slot")) & (F.col("ol_") == F.col("lnode_id")))
    near = F.forall(F.zip_with("dv", "dq_", lambda a, b: F.abs(a - b)), lambda x: x <= m.slack(F.col("r")))
    j = j.where(F.col("validated") | near)
    return j.select("qid", "q", "r", "slot", "bucket", "oid", "obj", "validated", F.when(F.col("validated"), "validated_cluster").otherwise("verified").alias("decided_by"))


def decided(idx: MetricIndex, objs: DataFrame, with_dist: bool = True) -> DataFrame:
    """[qid, oid, dist, decided_by] of candidate objects: the metric decides what no bound did."""
    d, ok = within(idx.metric, F.col("q"), F.col("obj"), F.col("r"), idx.dim)
    if with_dist:
        return objs.withColumn("dist", d).where(ok if idx.metric.name == "edit" else F.col("dist") <= F.col("r")).select("qid", "oid", "dist", "decided_by")
    objs = objs.withColumn("dist", F.when(~F.col("validated"), d))
    return objs.where(F.col("validated") | ((F.col("dist") >= 0) & (F.col("dist") <= F.col("r")))).select("qid", "oid", "dist", "decided_by")


def range_query(idx: MetricIndex, queries: DataFrame, r: float | None = None, with_dist: bool = True) -> DataFrame:
    """[qid, oid, dist, decided_by]: all objects within r, inclusive. Without `with_dist` validated ones need no distance and have null."""
    cand = global_candidates(idx, with_radius(queries, r))
    return decided(idx, candidate_objects(idx, local_candidates(idx, cand)), with_dist)


def range_count(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """[qid, n], zero for queries without answers."""
    n = range_query(idx, queries, r, with_dist=False).groupBy(F.col("qid").alias("k_")).agg(F.count("*").alias("n"))
    return queries.select("qid").join(n, F.col("qid") == F.col("k_"), "left").select("qid", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def range_exists(idx: MetricIndex, queries: DataFrame, r: float | None = None, other_than_self: bool = False) -> DataFrame:
    hits = range_query(idx, queries, r, with_dist=False)
    hits = hits.where("oid <> qid") if other_than_self else hits
    return queries.select("qid").join(hits.select(F.col("qid").alias("k_")), F.col("qid") == F.col("k_"), "left_semi")


def range_anti(idx: MetricIndex, queries: DataFrame, r: float | None = None, other_than_self: bool = False) -> DataFrame:
    hits = range_query(idx, queries, r, with_dist=False)
    hits = hits.where("oid <> qid") if other_than_self else hits
    return queries.select("qid").join(hits.select(F.col("qid").alias("k_")), F.col("qid") == F.col("k_"), "left_anti")


# ---- k nearest neighbours ----


def nearest_partitions(idx: MetricIndex, queries: DataFrame) -> DataFrame:
    """[qid, q, k, pid, d_qc, radius, n, d_k]: the partitions that may hold one of the k nearest, by a descent with a shrinking bound.

    On every level the least upper bounds (distance to the centre plus radius) of surviving nodes are counted up until they hold k
    objects; that upper bound, `d_k`, surely holds the k nearest, and nodes whose lower bound exceeds it are left out before their
    children are looked at. Children that the distance between centres excludes need no distance of their own.
    """
    m, cand = idx.metric, None
    for level in range(1, idx.height + 1):
        n = level_of(idx, level)
        if cand is None:
            step = queries.crossJoin(n).withColumn("d_k", F.lit(float("inf")))  # the top level has at most a fanout of nodes
        else:
            step = cand.join(n, F.col("node") == F.col("pa_"))
            step = step.where(~bounds.parent_prunable(F.col("dist_to_parent"), F.col("d_qc"), F.col("radius"), m.slack(F.col("d_k")))).drop("d_qc")
        step = step.withColumn("d_qc", m.column(F.col("q"), F.col("center"), idx.dim)).withColumn("upper_", bounds.upper(F.col("d_qc"), F.col("radius")))
        held = F.sum("no_").over(Window.partitionBy("qid").orderBy("upper_", "n_"))
        step = step.withColumn("held_", held)
        bound = F.min(F.when(F.col("held_") >= F.col("k"), F.col("upper_"))).over(Window.partitionBy("qid"))
        step = step.withColumn("d_k", F.least("d_k", F.coalesce(bound, F.lit(float("inf")))))
        step = step.where(bounds.lower(F.col("d_qc"), F.col("radius")) <= m.slack(F.col("d_k")))
        cand = step.select("qid", "q", "k", F.col("n_").alias("node"), F.col("np_").alias("pid"), "d_qc", "radius", F.col("no_").alias("n"), "d_k")
        if level < idx.height:
            cand = cand.drop("radius", "n")
    if cand is None:
        return queries.select("qid", "q", "k", F.lit(None).cast("long").alias("pid"), F.lit(0.0).alias("d_qc"), F.lit(0.0).alias("radius"), F.lit(0).cast("long").alias("n"), F.lit(0.0).alias("d_k")).limit(0)
    return cand.drop("node")


def probe_bound(idx: MetricIndex, leaves: DataFrame) -> DataFrame:
    """[qid, d_t]: the k-th distance inside the partition of the nearest centre; no row if that holds fewer than k."""
    near = leaves.groupBy("qid").agg(F.min_by("pid", F.struct("d_qc", "pid")).alias("pid"), F.first("q").alias("q"), F.first("k").alias("k"))
    near = locate(near, idx.placement.select("pid", "bucket", "slot"))
    o = idx.objects.select(F.col("slot").alias("os_"), F.col("pid").alias("op_"), F.col("oid").alias("o_"), F.col("obj").alias("oo_"))
    d = o.join(near, (F.col("os_") == F.col("slot")) & (F.col("op_") == F.col("pid"))).withColumn("d", idx.metric.column(F.col("q"), F.col("oo_"), idx.dim))
    r = F.row_number().over(Window.partitionBy("qid").orderBy("d", "o_"))
    return d.withColumn("r_", r).where("r_ = k").select("qid", F.col("d").alias("d_t"))


def knn_bounds(idx: MetricIndex, queries: DataFrame) -> DataFrame:
    """[qid, q, k, d_k, d_t, r, parts]: a radius that surely holds the k nearest, the least of both bounds (infinite if the index holds
    fewer), with the partitions (pid, d_qc, radius) that survived the descent."""
    leaves = nearest_partitions(idx, queries)
    dk = leaves.groupBy(F.col("qid").alias("qk_")).agg(F.min("d_k").alias("d_k"), F.collect_list(F.struct("pid", "d_qc", "radius")).alias("parts"))  # at most N_p a query
    dt = probe_bound(idx, leaves).withColumnRenamed("qid", "qt_")
    b = queries.join(dk, F.col("qid") == F.col("qk_"), "left").join(dt, F.col("qid") == F.col("qt_"), "left")
    bound = F.coalesce(F.least("d_k", "d_t"), F.lit(float("inf")))
    return b.select("qid", "q", "k", "d_k", "d_t", idx.metric.slack(bound).alias("r"), "parts")


def knn_candidates(idx: MetricIndex, bound: DataFrame) -> DataFrame:
    """[qid, q, r, pid, validated, d_qc]: the surviving partitions that the final radius does not exclude."""
    c = bound.select("qid", "q", "r", F.explode("parts").alias("p_")).select("qid", "q", "r", "p_.*")
    return c.where(~bounds.knn_prunable(F.col("d_qc"), F.col("radius"), F.col("r"))).select("qid", "q", "r", "pid", F.lit(False).alias("validated"), "d_qc")


def rank_answers(found: DataFrame, by: str = "oid") -> DataFrame:
    """[qid, rank, oid, dist]: partial top-k a task before the shuffle (window group limit), final top-k a query."""
    w = Window.partitionBy("qid").orderBy(F.round("dist", 9), by)
    return found.withColumn("rank", F.row_number().over(w)).where("rank <= k").select("qid", "rank", "oid", "dist")


def _slack(m: Metric, x: float) -> float:
    return x if m.integer_valued else x * (1 + 1e-9) + 1e-12


def _vectors(table: pa.Table, name: str, m: Metric):
    return m.from_arrow(table.column(name).combine_chunks())


def _kth_bound(d: np.ndarray, upper: np.ndarray, n: np.ndarray, k: int) -> float:
    """The least of the upper bounds that surely holds k objects; infinite if all together hold fewer."""
    order = np.argsort(upper, kind="stable")
    at = int(np.searchsorted(np.cumsum(n[order]), k))
    return float(upper[order[at]]) if at < len(order) else math.inf


def _home_bounds(m: Metric):
    """Per query the bound by the local leaves (`leaves`: center, radius, n) of its nearest partition."""

    def run(leaves: pa.Table, queries: pa.Table) -> pa.Table:
        qs, ks, bounds_ = _vectors(queries, "q", m), queries.column("k").to_pylist(), []
        if len(leaves):
            centers, radius, n = _vectors(leaves, "center", m), leaves.column("radius").to_numpy(), leaves.column("n").to_numpy()
            for q, k in zip(qs, ks):
                d = m.kernel(centers, q)
                bounds_.append(_kth_bound(d, d + radius, n, k))
        else:
            bounds_ = [math.inf] * len(queries)
        return pa.table({"qid": queries.column("qid"), "d_t": pa.array(bounds_, pa.float64())})

    return run


class _Cells:
    """The vantage objects and cells of one group, objects [oid, obj, dv, rank_v, cell] in the order of their cells.

    Vantage objects that were deleted take no part; objects without stored distances (inserted later) are never excluded.
    """

    def __init__(self, m: Metric, objs: pa.Table, batch):
        rank, stored = objs.column("rank_v").to_numpy(), objs.column("dv").combine_chunks()
        at = np.flatnonzero(rank >= 0)
        at = at[np.argsort(rank[at])]
        has = pc.list_value_length(stored).to_numpy() > 0
        self.vantages = m.take(batch, at)
        self.far = np.full((len(objs), len(at)), np.nan)
        if has.any():
            self.far[has] = stored.flatten().to_numpy().reshape(int(has.sum()), -1)[:, rank[at]]
        self.first = np.flatnonzero(np.diff(objs.column("cell").to_numpy(), prepend=-1))
        self.size = np.diff(np.append(self.first, len(objs)))
        low, high = (f.reduceat(self.far, self.first, axis=0) for f in (np.minimum, np.maximum))
        self.low, self.high = np.where(np.isnan(low), -np.inf, low), np.where(np.isnan(high), np.inf, high)

    def within(self, m: Metric, q, k: int, bound: float) -> tuple[np.ndarray, float]:
        """(objects that no vantage object excludes, the bound after the cells were counted up)."""
        d = m.kernel(self.vantages, q)
        bound = min(bound, _slack(m, _kth_bound(d, (self.high + d).min(axis=1, initial=np.inf), self.size, k)))
        reached = np.flatnonzero(np.maximum(self.low - d, d - self.high).max(axis=1, initial=0.0) <= bound)
        take = ranges(self.first[reached], self.size[reached])
        return take[~(np.abs(self.far[take] - d) > bound).any(axis=1)], bound


def _near_rows(m: Metric, dim: int | None):
    """The k nearest of one local tree for every query that reaches it: a walk down the tree with a shrinking bound, then the stored-distance test, then the metric.

    Groups with vantage objects have their cells and the stored distances to the vantage objects instead of the walk.
    """
    exact = m.rows if m.rows is not None and (dim or UNROLLED + 1) > UNROLLED else m.kernel

    def run(rows: pa.Table, queries: pa.Table) -> pa.Table:
        out_q, out_o, out_d = [], [], []
        is_node = rows.column("level").is_valid()
        nodes, objs = rows.filter(is_node), rows.filter(pc.invert(is_node))
        if not len(objs) or not len(queries):
            return pa.table({"qid": pa.array([], pa.int64()), "oid": pa.array([], pa.int64()), "dist": pa.array([], pa.float64()), "k": pa.array([], pa.int32())})
        vantage = "rank_v" in objs.column_names
        objs = objs.sort_by([("cell" if vantage else "lnode_id", "ascending")])
        oid, batch, d_leaf, of = objs.column("oid").to_numpy(), _vectors(objs, "obj", m), objs.column("d_leaf").to_numpy(), objs.column("lnode_id").to_numpy()
        walk = len(nodes) > 0
        cells = _Cells(m, objs, batch) if vantage else None
        if walk:
            nodes = nodes.sort_by([("lnode_id", "ascending")])
            ids, level, parent_id = (nodes.column(c).to_numpy() for c in ("lnode_id", "level", "parent_id"))
            radius, to_parent, leaf = nodes.column("radius").to_numpy(), nodes.column("dist_to_parent").to_numpy(), nodes.column("is_leaf").to_numpy()
            centers, n_nodes = _vectors(nodes, "obj", m), len(nodes)
            first, last = np.searchsorted(of, ids), np.searchsorted(of, ids, side="right")
            up = np.minimum(np.searchsorted(ids, parent_id), n_nodes - 1)
            up = np.where((parent_id >= 0) & (ids[up] == parent_id), up, -1)
            n = np.where(leaf, last - first, 0)
            for lv in sorted(set(level.tolist()), reverse=True):
                mine = np.flatnonzero((level == lv) & (up >= 0))
                np.add.at(n, up[mine], n[mine])
            steps = [np.flatnonzero((level == lv) & (n > 0)) for lv in sorted(set(level.tolist()))]
            roots = [s[up[s] < 0] for s in steps]
            below = [s[up[s] >= 0] for s in steps]
        for qid, q, k, bound in zip(queries.column("qid").to_pylist(), _vectors(queries, "q", m), queries.column("k").to_pylist(), queries.column("r").to_pylist()):
            if walk:
                d, alive = np.full(n_nodes, np.inf), np.zeros(n_nodes, bool)
                for top, rest in zip(roots, below):
                    at = up[rest]
                    rest = rest[alive[at]]
                    rest = rest[np.abs(to_parent[rest] - d[up[rest]]) <= bound + radius[rest]]
                    here = np.concatenate([top, rest])
                    if not len(here):
                        continue
                    d[here] = m.kernel(m.take(centers, here), q)
                    bound = min(bound, _slack(m, _kth_bound(d[here], d[here] + radius[here], n[here], k)))
                    alive[here] = d[here] - radius[here] <= bound
                reached = np.flatnonzero(alive & leaf)
                reached = reached[d[reached] - radius[reached] <= bound]
                size = last[reached] - first[reached]
                if not size.sum():
                    continue
                take = ranges(first[reached], size)
                take = take[np.abs(d_leaf[take] - np.repeat(d[reached], size)) <= bound]
                dist = exact(m.take(batch, take), q)
            elif cells:
                take, bound = cells.within(m, q, k, bound)
                dist = exact(m.take(batch, take), q)
            else:
                take, dist = None, exact(batch, q)
            near = np.flatnonzero(dist <= bound)
            if not len(near):
                continue
            if len(near) > k:
                near = near[dist[near] <= np.partition(dist[near], k - 1)[k - 1] + 2e-9]  # ties are decided on rounded distances
            who = oid[near if take is None else take[near]]
            order = np.lexsort((who, dist[near]))
            who, far = who[order], dist[near][order]
            starts = np.flatnonzero(np.concatenate([[True], far[1:] != far[:-1]]))
            kept = np.arange(len(far)) - np.repeat(starts, np.diff(np.append(starts, len(far)))) < k  # of equal distances the k smallest oids
            out_q.append(np.full(kept.sum(), qid, np.int64))
            out_o.append(who[kept])
            out_d.append(far[kept])
        cat = lambda parts, kind: np.concatenate(parts) if parts else np.empty(0, kind)
        found = pa.table({"qid": cat(out_q, np.int64), "oid": cat(out_o, np.int64), "dist": cat(out_d, float)})
        k = queries.column("k")[0].as_py()
        return found.append_column("k", pa.array(np.full(len(found), k, np.int32))) if len(set(queries.column("k").to_pylist())) == 1 else _with_k(found, queries)

    return run


def _with_k(found: pa.Table, queries: pa.Table) -> pa.Table:
    of = dict(zip(queries.column("qid").to_pylist(), queries.column("k").to_pylist()))
    return found.append_column("k", pa.array([of[q] for q in found.column("qid").to_pylist()], pa.int32()))


def _dealt(df: DataFrame, n: int, key: str):
    """`df` in groups of `key` over `n` tasks; the number is said, so that few small groups aren't put into one task by their bytes."""
    return df.repartition(n, key).groupBy(key)


def knn_by_partition(idx: MetricIndex, q: DataFrame) -> DataFrame:
    """[qid, oid, dist, k]: of every local tree that a query reaches its k nearest within the bound, for vectors.

    Objects are shuffled once, to their local tree (without local trees once more, to their partition, for the bound); queries go to the
    trees. No pair of query and object leaves a task unless it is among the k nearest there, so nothing is sorted or kept but answers.
    """
    m, spread = idx.metric, max(1, min(400, len(idx.tree.leaves())))
    q = q.withColumnsRenamed({"qid": "oid", "q": "obj"}).where(unfit(m, idx.dim).isNull()).withColumnsRenamed({"oid": "qid", "obj": "q"})
    q = q.repartition(spread, "qid")  # the descent's windows are by query
    leaves = nearest_partitions(idx, q)
    reached = leaves.groupBy("qid").agg(F.first("q").alias("q"), F.first("k").alias("k"), F.min("d_k").alias("d_k"), F.collect_list(F.struct("d_qc", "pid", "radius")).alias("parts"))  # at most N_p a query
    reached = written(reached, "reached")
    if idx.local == "tree":
        held = idx.objects.groupBy(F.col("lnode_id").alias("l_")).agg(F.count("*").alias("n"))  # counted, since deletes leave the nodes as they are
        near = idx.local_nodes.where("is_leaf").join(held, F.col("lnode_id") == F.col("l_")).select("pid", "center", "radius", "n")
    else:
        near = idx.objects.select("pid", F.col("obj").alias("center"), F.lit(0.0).alias("radius"), F.lit(1).cast("long").alias("n"))
    home = reached.select("qid", "q", "k", F.array_min("parts")["pid"].alias("pid"))
    bound = _dealt(near, spread, "pid").cogroup(_dealt(home, spread, "pid")).applyInArrow(_home_bounds(m), "qid long, d_t double")
    to = reached.join(bound.withColumnRenamed("qid", "qb_"), F.col("qid") == F.col("qb_"))
    to = to.select("qid", "q", "k", m.slack(F.least("d_k", "d_t")).alias("r"), F.explode("parts").alias("p_")).where(~bounds.knn_prunable(F.col("p_.d_qc"), F.col("p_.radius"), F.col("r")))
    tree = F.shiftright("lnode_id", 20).alias("g")  # one a partition but for the largest, see local_index.CHOP
    trees = idx.local_nodes.select(F.col("pid").alias("t_"), tree).distinct()
    to = to.join(trees, F.col("p_.pid") == F.col("t_")).select("g", "qid", "q", "k", "r")
    rows = idx.objects.select(tree, "lnode_id", "oid", "obj", "d_leaf", *(["dv", "rank_v", "cell"] if idx.local == "vantage" else []))
    if idx.local == "tree":
        nodes = idx.local_nodes.select(tree, "lnode_id", F.col("center").alias("obj"), "parent_id", "level", "is_leaf", "dist_to_parent", "radius")
        rows = rows.unionByName(nodes, allowMissingColumns=True)
    else:
        rows = rows.withColumn("level", F.lit(None).cast("int"))
    return _dealt(rows, spread, "g").cogroup(_dealt(to, spread, "g")).applyInArrow(_near_rows(m, idx.dim), "qid long, oid long, dist double, k int")


SAMPLED = 64  # queries whose descent shows whether pruning is worth its rows
REACHED = 0.5  # share of the partitions from which on a plain comparison of blocks is less work
PRODUCT_ROWS, PRODUCT_QUERIES = 20_000, 20_000  # objects and queries that meet in a task
STRIP, RUN, AT_ONCE = 4096, 32, 256  # objects of one product, objects that stand for each other in the first pass, queries of one product


def nothing_prunes(idx: MetricIndex, queries: DataFrame) -> bool:
    """Whether a hash sample of the queries [qid, q, k] reaches most partitions of the index. It chooses between two exact ways."""
    lane = F.xxhash64("qid", F.lit(23))
    some = written(queries.where("q is not null").withColumn("h_", lane).orderBy("h_", "qid").limit(SAMPLED).drop("h_"), "sampled")
    reached = nearest_partitions(idx, some).groupBy("qid").agg(F.count("*").alias("n")).agg(F.avg("n").alias("n")).first().n
    return (reached or 0) >= REACHED * sum(x.n_objects > 0 for x in idx.tree.leaves())


def _nearest_by_products(m: Metric):
    """The k nearest of a block of objects for a block of queries, for L2.

    The first pass takes squares of distances from one matrix product and keeps the least of every run of objects: the k-th least of these
    bounds the k-th distance from above, rounding allowed for. Only runs within the bound are measured by the metric itself.
    """

    def run(objs: pa.Table, asked: pa.Table) -> pa.Table:
        out = {"qid": [], "oid": [], "dist": [], "k": []}
        if len(objs) and len(asked):
            x, oid, qs, qid, ks = _vectors(objs, "obj", m), objs.column("oid").to_numpy(), _vectors(asked, "q", m), asked.column("qid").to_numpy(), asked.column("k").to_numpy()
            squares = (x * x).sum(axis=1)
            runs = -(-len(x) // RUN)
            wide = np.zeros((runs * RUN, x.shape[1] + 1))
            wide[: len(x), :-1], wide[: len(x), -1], wide[len(x) :, -1] = x, squares, np.inf
            for lo in range(0, len(qs), AT_ONCE):
                q, k = qs[lo : lo + AT_ONCE], ks[lo : lo + AT_ONCE]
                lifted = np.vstack([-2 * q.T, np.ones(len(q))])
                least = np.concatenate([(wide[a : a + STRIP] @ lifted).reshape(-1, RUN, len(q)).min(axis=1) for a in range(0, len(wide), STRIP)])
                own = (q * q).sum(axis=1)
                err = 1e-12 * (own + squares.max()) + 1e-300
                bound = np.full(len(q), np.inf)
                for n in np.unique(k[k <= runs]).tolist():
                    mine = k == n
                    bound[mine] = np.partition(least[:, mine], n - 1, axis=0)[n - 1]
                far = np.sqrt(np.maximum(bound + own + err, 0)) + 4e-9  # ties are decided on rounded distances
                far[own + squares.max() > 1e300] = np.inf  # products may overflow: all are measured
                which, at = np.nonzero((least.T + own[:, None] <= (far * far + err)[:, None]) | np.isinf(far)[:, None])
                pairs = [np.arange(a, min(a + MOST_RUNS, len(which))) for a in range(0, len(which), MOST_RUNS)]
                found = []
                for part in pairs:
                    of, rows = np.repeat(which[part], RUN), (at[part][:, None] * RUN + np.arange(RUN)).ravel()
                    of, rows = of[rows < len(x)], rows[rows < len(x)]
                    d = m.rows(x[rows], q[of])
                    near = d <= far[of]
                    found.append((of[near], rows[near], d[near]))
                of, rows, d = (np.concatenate(c) for c in zip(*found))
                order = np.lexsort((oid[rows], d, of))
                of, rows, d = of[order], rows[order], d[order]
                starts = np.flatnonzero(np.diff(of, prepend=-1))
                size = np.diff(np.append(starts, len(of)))
                last = d[starts + np.minimum(k[of[starts]], size) - 1]
                equal = np.flatnonzero((np.diff(of, prepend=-1) != 0) | (np.diff(d, prepend=-1) != 0))
                nth = np.arange(len(of)) - np.repeat(equal, np.diff(np.append(equal, len(of))))
                kept = (d <= np.repeat(last, size) + 2e-9) & (nth < k[of])
                for name, column in (("qid", qid[lo + of[kept]]), ("oid", oid[rows[kept]]), ("dist", d[kept]), ("k", k[of[kept]])):
                    out[name].append(column)
        kinds = {"qid": np.int64, "oid": np.int64, "dist": np.float64, "k": np.int32}
        return pa.table({name: np.concatenate(out[name]).astype(t) if out[name] else np.empty(0, t) for name, t in kinds.items()})

    return run


MOST_RUNS = 20_000  # runs of objects that are measured at once


def knn_by_products(idx: MetricIndex, queries: DataFrame, most: int) -> DataFrame:
    """[qid, rank, oid, dist] of [qid, q, k], k at most `most`: all pairs in blocks of both sides, for vectors that the index cannot prune.

    Equal vectors are asked once, and of equal objects the `most` smallest oids are met; answers go to all that asked.
    """
    q = queries.withColumnsRenamed({"qid": "oid", "q": "obj"}).where(unfit(idx.metric, idx.dim).isNull()).withColumnsRenamed({"oid": "qid", "obj": "q"})
    asked = written(_asked_once(q), "asked-once")
    objs = _without_copies(idx, most).objects.select("oid", "obj")
    blocks = lambda df, rows: max(1, math.ceil(df.count() / rows))
    n, m = blocks(objs, PRODUCT_ROWS), blocks(asked, PRODUCT_QUERIES)
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    group = (F.col("a").cast("long") * m + F.col("b")).alias("g")
    o = objs.select("oid", "obj", F.pmod(F.xxhash64("oid"), F.lit(n)).alias("a"), every(m).alias("b")).select("oid", "obj", group)
    to = asked.select("qid", "q", "k", F.pmod(F.xxhash64("qid"), F.lit(m)).alias("b"), every(n).alias("a")).select("qid", "q", "k", group)
    found = _dealt(o, n * m, "g").cogroup(_dealt(to, n * m, "g")).applyInArrow(_nearest_by_products(idx.metric), "qid long, oid long, dist double, k int")
    return _for_all(rank_answers(found), asked, q)


BLOCK = 300_000  # objects that are compared with a query at once


def nearest_by_block(objects: DataFrame, metric: Metric, queries: DataFrame, k: int, blocks: int, block, dim: int | None = None) -> DataFrame:
    """[qid, oid, dist, k]: the k nearest of every block for every query, whatever other blocks hold; `block` numbers the blocks of objects from 0 on. For vectors.

    Inside a block, runs of neighbours of both sides exclude each other (`blocks`); a metric that has no NumPy form for that measures all pairs.
    """
    none = lambda kind: F.lit(None).cast(kind)
    rows = objects.select(block.cast("long").alias("g"), none("long").alias("lnode_id"), "oid", "obj", none("double").alias("d_leaf"), none("int").alias("level"))
    asked = queries.select("qid", "q", F.lit(k).cast("int").alias("k"), F.lit(math.inf).alias("r"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("g"))
    measured = _near_rows(metric, dim)
    run = nearest_rows(metric, k, measured) if metric.crossed and dim and dim <= UNROLLED else measured
    return _dealt(rows, blocks, "g").cogroup(_dealt(asked, blocks, "g")).applyInArrow(run, "qid long, oid long, dist double, k int")


EXTREME_ROWS = 200_000  # objects and queries that meet in a task


def _both_dealt(objects: DataFrame, queries: DataFrame, by: tuple[str, str], most: tuple[int, int], run) -> DataFrame:
    """[oid, nearest, farthest]: `run` for every block of objects [oid, obj] with every block of queries [qid, q], dealt by hash; then the least and greatest of an object."""
    n, m = (max(1, math.ceil(df.count() / rows)) for df, rows in zip((objects, queries), most))
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    o = objects.select("oid", "obj", F.pmod(F.xxhash64(by[0]), F.lit(n)).cast("int").alias("a"), every(m).alias("b"))
    q = queries.select("q", F.pmod(F.xxhash64(by[1]), F.lit(m)).cast("int").alias("b"), every(n).alias("a"))
    dealt = lambda df: df.select(*[c for c in df.columns if c not in "ab"], (F.col("a").cast("long") * m + F.col("b")).alias("g"))
    found = _dealt(dealt(o), n * m, "g").cogroup(_dealt(dealt(q), n * m, "g")).applyInArrow(run, "oid long, d0 double, d1 double")
    return found.groupBy("oid").agg(F.min("d0").alias("nearest"), F.max("d1").alias("farthest"))


def extremes_by_block(objects: DataFrame, metric: Metric, queries: DataFrame) -> DataFrame:
    """[oid, nearest, farthest]: the least and greatest distance of every object to all queries, for short vectors. Pairs are measured unless the distances of their runs show that they are neither (`blocks`)."""
    return _both_dealt(objects, queries, ("oid", "qid"), (EXTREME_ROWS, EXTREME_ROWS), extreme_rows(metric))


EDIT_TEXTS, EDIT_QUERIES = 4_000, 50_000  # texts and queries that meet in a task


def edit_extremes_by_block(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """[oid, nearest, farthest]: the least and greatest edit distance of every object to the queries, all pairs measured in blocks of both sides."""
    objects, queries = objects.where("obj is not null"), queries.where("q is not null")

    def run(texts: pa.Table, asked: pa.Table) -> pa.Table:
        if not len(texts) or not len(asked):
            return pa.table({"oid": pa.array([], pa.int64()), "d0": pa.array([], pa.float64()), "d1": pa.array([], pa.float64())})
        least, most = edit_extremes(texts.column("obj").to_pylist(), asked.column("q").to_pylist())
        return pa.table({"oid": texts.column("oid"), "d0": pa.array(least, pa.float64()), "d1": pa.array(most, pa.float64())})

    return _both_dealt(objects, queries, ("obj", "q"), (EDIT_TEXTS, EDIT_QUERIES), run)


def _without_copies(idx: MetricIndex, k: int) -> MetricIndex:
    """The index with the k smallest oids of equal objects: no other copy is among the k nearest, and bounds that hold for all objects hold here.

    The window keeps k rows a task before its shuffle. Written, since two joins read it.
    """
    lane = Window.partitionBy("slot", "lnode_id", "obj").orderBy("oid")
    kept = idx.objects.withColumn("copy_", F.row_number().over(lane)).where(F.col("copy_") <= k).drop("copy_")
    if idx.local == "vantage":  # its vantage objects are read from the same table
        kept = kept.unionByName(idx.objects.where("rank_v >= 0")).distinct()
    return idx.with_objects(written(kept, "without-copies"))


def _asked_once(queries: DataFrame) -> DataFrame:
    """Of equal queries [qid, q, k] the one of the smallest qid."""
    return queries.where("q is not null").groupBy("q", "k").agg(F.min("qid").alias("qid")).select("qid", "q", "k")


def _for_all(found: DataFrame, asked: DataFrame, queries: DataFrame) -> DataFrame:
    """Answers [qid, ...] to the queries `asked` once for all of `queries`, as [qid, ...]."""
    once = asked.select(F.col("qid").alias("of_"), F.col("q").alias("q_"), F.col("k").alias("k_"))
    same = queries.join(once, (F.col("q") == F.col("q_")) & (F.col("k") == F.col("k_"))).select(F.col("qid").alias("to_"), "of_")
    return found.join(same, F.col("qid") == F.col("of_")).withColumn("qid", F.col("to_")).drop("to_", "of_")


def knn_query(idx: MetricIndex, queries: DataFrame, k: int | None = None, by: str = "oid") -> DataFrame:
    """[qid, rank, oid, dist]: the k nearest, ties by (distance, oid). A pruned descent gives a bound and partitions, then they are searched within it.

    Equal strings are asked once, and no more than k copies of an equal object are met.
    """
    q = queries.select("qid", "q", (F.lit(int(k)) if k is not None else F.col("k").cast("int")).alias("k"))
    if idx.metric.kind == "vector" and by == "oid":
        if idx.metric.products and (idx.dim or 0) > UNROLLED and nothing_prunes(idx, q):
            return knn_by_products(idx, q, (k if k is not None else q.agg(F.max("k")).first()[0]) or 1)
        return rank_answers(knn_by_partition(idx, q))
    asked, most = q, k
    if idx.metric.kind == "string":
        asked = written(_asked_once(q), "asked-once")
        most = k if k is not None else asked.agg(F.max("k")).first()[0]
        idx = _without_copies(idx, most or 1)
    bound = knn_bounds(idx, asked)
    objs = candidate_objects(idx, local_candidates(idx, knn_candidates(idx, bound)))
    found = objs.withColumn("dist", pair_column(idx.metric, F.col("q"), F.col("obj"), idx.dim)).where("dist <= r")
    ks = asked.select(F.col("qid").alias("kq_"), "k")
    found = found.join(ks, F.col("qid") == F.col("kq_"))
    found = rank_answers(found if by == "oid" else found.withColumn(by, F.col("obj")), by)
    return _for_all(found, asked, q) if idx.metric.kind == "string" else found


def knn_via_range(idx: MetricIndex, queries: DataFrame, k: int) -> DataFrame:
    """The same from two passes: the k-th distance, then a range query with it."""
    kth = knn_query(idx, queries, k).groupBy(F.col("qid").alias("b_")).agg(F.max("dist").alias("r0_"))
    q = queries.select("qid", "q").join(kth, F.col("qid") == F.col("b_")).select("qid", "q", F.col("r0_").alias("r"))
    return rank_answers(range_query(idx, q).withColumn("k", F.lit(k)))


def knn_join(left: DataFrame, idx: MetricIndex, k: int) -> DataFrame:
    """Every row of `left` [oid, obj] as a query."""
    return knn_query(idx, left.select(F.col("oid").alias("qid"), F.col("obj").alias("q")), k)


def range_join(idx: MetricIndex, r: float) -> DataFrame:
    """[oid, oid2, dist], oid < oid2: all pairs of the index within r."""
    q = idx.objects.select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    return range_query(idx, q, r).where("qid < oid").select(F.col("qid").alias("oid"), F.col("oid").alias("oid2"), "dist")


def best_first(tree, objects_of, metric: Metric, q, k: int) -> list[tuple[float, int]]:
    """Best-first search in one process, by lower bounds in a priority queue (single tree baseline, checks).

    `objects_of(leaf)` gives (ids, batch) of a leaf. Returns the k nearest as (distance, id).
    """
    one = lambda c: float(metric.kernel(metric.batch([c]), q)[0])
    heap, best = [], []
    for n in tree.top():
        d = one(tree.nodes[n].center)
        heapq.heappush(heap, (max(0.0, d - tree.nodes[n].radius), n))
    while heap:
        low, n = heapq.heappop(heap)
        if len(best) == k and low > -best[0][0] + 1e-9:
            break
        node = tree.nodes[n]
        if node.children:
            for c in node.children:
                child = tree.nodes[c]
                if child.n_objects:
                    heapq.heappush(heap, (max(0.0, one(child.center) - child.radius), c))
            continue
        ids, batch = objects_of(n)
        if not len(ids):
            continue
        for d, i in zip(metric.kernel(batch, q), ids):
            item = (-float(d), -int(i))
            if len(best) < k:
                heapq.heappush(best, item)
            elif item > best[0]:
                heapq.heapreplace(best, item)
    return sorted((-d, -i) for d, i in best)

