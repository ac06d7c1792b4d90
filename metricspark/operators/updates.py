"""Inserts, deletes and compaction. Answers always equal those of an index built anew over the edited objects.

Inserted objects descend the existing tree, take the place of their partition and the nearest leaf of its local tree, and
only widen radii, up to the local root. A partition that overflows is split: random objects of it become centres beside the old
one, its objects (and no others) are dealt out among them and get new local trees. Deletes are anti-joined tombstones: radii stay
valid, only looser. Compaction writes everything afresh.
"""
from __future__ import annotations

import copy
from dataclasses import replace

from pyspark.sql import DataFrame, Window, functions as F

from ..sources.tables import accepted, written
from . import global_index, local_index
from .index import OBJECT_COLUMNS, MetricIndex, build_index
from .sampling import hash_key

OVERFLOW = 4  # a partition may grow to so many times its share before it is split


def _routed(idx: MetricIndex, tree, objects: DataFrame) -> DataFrame:
    """The new objects with their leaf; sizes and radii of the tree are brought up to date."""
    routed = written(global_index.assign(accepted(objects, idx.metric, idx.dim), tree, idx.metric), "routed")
    rows = routed.groupBy("leaf").agg(F.count("*").alias("n"), *[F.max(F.col("d_anc")[k]).alias(f"r{k}") for k in range(tree.height)]).collect()  # at most one row a leaf
    for r in rows:
        at = r.leaf
        for k in range(tree.height - 1, -1, -1):
            node = tree.nodes[at]
            node.radius, node.n_objects = max(node.radius, r[f"r{k}"]), node.n_objects + r.n
            at = node.parent_id
    return routed


def _in_local_trees(idx: MetricIndex, routed: DataFrame, tree, placement: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(new object rows, local nodes with widened radii and new counts)."""
    spark, m = routed.sparkSession, idx.metric
    leaf = spark.createDataFrame([(n.node_id, n.pid, n.center) for n in tree.leaves()], f"n_ long, pid long, pc_ {routed.schema['obj'].dataType.simpleString()}")
    routed = routed.join(F.broadcast(leaf), F.col("leaf") == F.col("n_"))  # a row a partition
    place = placement.select(F.col("pid").alias("p_"), "bucket", "slot")
    near = idx.local_nodes.where("is_leaf").select(F.col("pid").alias("lp_"), "lnode_id", F.col("center").alias("lc_"))
    j = routed.join(F.broadcast(place), F.col("pid") == F.col("p_")).join(near, F.col("pid") == F.col("lp_"), "left")
    # a partition that had been empty gets its first local node, around its own centre
    j = j.withColumn("d_leaf", m.column(F.col("obj"), F.coalesce("lc_", "pc_"), idx.dim)).withColumn("lnode_id", F.coalesce("lnode_id", F.shiftleft(F.col("pid"), 32)))
    best = j.withColumn("r_", F.row_number().over(Window.partitionBy("oid").orderBy("d_leaf", "lnode_id"))).where("r_ = 1")
    fresh = written(best.select("slot", "bucket", "pid", "lnode_id", F.lit(0).alias("cell"), "d_leaf", "d_center", "oid", "obj", F.array().cast("array<double>").alias("dv"), F.lit(-1).cast("long").alias("rank_v")).select(*OBJECT_COLUMNS), "inserted")
    known = idx.local_nodes.select(F.col("lnode_id").alias("k_"))
    centers = leaf.select(F.col("pid").alias("np_"), F.col("pc_").alias("center"))
    added = fresh.join(known, F.col("lnode_id") == F.col("k_"), "left_anti").groupBy("slot", "bucket", "pid", "lnode_id").agg(F.max("d_leaf").alias("radius"), F.count("*").alias("n_objects")).join(F.broadcast(centers), F.col("pid") == F.col("np_"))
    added = added.select("slot", "bucket", "pid", "lnode_id", F.lit(-1).cast("long").alias("parent_id"), F.lit(1).alias("level"), F.lit(True).alias("is_leaf"), F.lit(0.0).alias("dist_to_parent"), "radius", "n_objects", "center")
    # from the leaf up: each node on the way covers the object
    grown, now = None, fresh.select("obj", F.col("lnode_id").alias("at_"))
    nodes = idx.local_nodes.select(F.col("lnode_id").alias("id_"), F.col("parent_id").alias("up_"), F.col("center").alias("c_"))
    for _ in range(idx.local_height):
        now = now.join(nodes, F.col("at_") == F.col("id_"))
        step = now.groupBy(F.col("id_").alias("t_")).agg(F.max(m.column(F.col("obj"), F.col("c_"), idx.dim)).alias("m_"), F.count("*").alias("c0_"))
        grown = step if grown is None else grown.unionByName(step)
        now = now.select("obj", F.col("up_").alias("at_")).where("at_ >= 0")
    grown = grown.groupBy("t_").agg(F.max("m_").alias("m_"), F.sum("c0_").alias("c0_"))
    local = idx.local_nodes.join(grown, F.col("lnode_id") == F.col("t_"), "left").withColumn("radius", F.greatest("radius", F.coalesce("m_", F.lit(0.0)))).withColumn("n_objects", F.col("n_objects") + F.coalesce("c0_", F.lit(0)))
    return fresh, written(local.select(*local_index.NODE_COLUMNS).unionByName(added.select(*local_index.NODE_COLUMNS)), "local-nodes")


def _placed(idx: MetricIndex, tree) -> DataFrame:
    """The placement with partitions that were empty so far; they go to the slot of the least objects."""
    rows = idx.placement.collect()  # one row a partition
    have, load = {r.pid for r in rows}, dict.fromkeys(range(idx.n_w), 0)
    for r in rows:
        load[r.slot] = load.get(r.slot, 0) + r.n_objects
    more, bucket = [], max((r.bucket for r in rows), default=-1) + 1
    for n in tree.leaves():
        if n.n_objects and n.pid not in have:
            slot = min(load, key=lambda s: (load[s], s))
            load[slot] += n.n_objects
            more.append((n.pid, n.dist_to_parent, n.n_objects, bucket, slot, n.node_id))
            bucket += 1
    return idx.placement.unionByName(idx.placement.sparkSession.createDataFrame(more, "pid long, dist_to_parent double, n_objects long, bucket int, slot int, node_id long").select(*idx.placement.columns)) if more else idx.placement


def split_overflow(idx: MetricIndex, seed: int = 77) -> MetricIndex:
    """`idx` with partitions over OVERFLOW times their share split at random objects of theirs; only these are moved and written."""
    cap = OVERFLOW * global_index.capacity(max(1, idx.n), idx.n_p)
    over = {n.pid: (n, -(-n.n_objects // cap)) for n in idx.tree.leaves() if n.n_objects > cap and n.radius > 0}
    if not over:
        return idx
    spark, m = idx.objects.sparkSession, idx.metric
    mine = written(idx.objects.where(F.col("pid").isin(*over)).select("pid", "oid", "obj", "d_center"), "overfull")
    lane = Window.partitionBy("pid").orderBy(hash_key(seed), "oid")
    picked = mine.where("d_center > 0").withColumn("r_", F.row_number().over(lane)).where(F.col("r_") <= max(k for _, k in over.values())).select("pid", "r_", "obj").collect()
    tree = copy.deepcopy(idx.tree)
    families: dict[int, list[int]] = {pid: [n.node_id] for pid, (n, _) in over.items()}
    next_pid = max(n.pid for n in tree.leaves()) + 1
    for r in sorted(picked, key=lambda r: (r.pid, r.r_)):
        if r.r_ <= over[r.pid][1]:
            new = global_index.add_leaf(tree, families[r.pid][0], r.obj, m)
            if new is not None:
                tree.nodes[new].pid, next_pid = next_pid, next_pid + 1
                families[r.pid].append(new)
    families = {pid: ids for pid, ids in families.items() if len(ids) > 1}
    if not families:
        return idx
    mine = mine.where(F.col("pid").isin(*families))
    centers = spark.createDataFrame([(pid, i, tree.nodes[i].center) for pid, ids in families.items() for i in ids], f"f_ long, leaf long, c_ {mine.schema['obj'].dataType.simpleString()}")
    met = mine.join(F.broadcast(centers), F.col("pid") == F.col("f_")).withColumn("d_", m.column(F.col("obj"), F.col("c_"), idx.dim))  # a few rows a split partition
    dealt = written(met.groupBy("oid").agg(F.first("obj").alias("obj"), F.min_by(F.struct("leaf", "d_"), F.struct("d_", "leaf")).alias("n_")).select("oid", "obj", "n_.leaf", F.col("n_.d_").alias("d_center")), "split")
    rows = {r.leaf: r for r in dealt.groupBy("leaf").agg(F.count("*").alias("n"), F.max("d_center").alias("r")).collect()}
    for ids in families.values():
        for i in ids:
            tree.nodes[i].n_objects, tree.nodes[i].radius = (rows[i].n, rows[i].r) if i in rows else (0, 0.0)
    nodes = global_index.nodes_frame(spark, tree)
    slim = replace(idx, tree=tree, placement=idx.placement.where(~F.col("pid").isin(*families)))
    placement = spark.createDataFrame(_placed(slim, tree).collect(), idx.placement.schema)  # one row a partition
    made = written(local_index.build(dealt, placement, m, idx.fanout, 42, idx.local).drop("chop"), "split-partitions")
    objects = idx.objects.where(~F.col("pid").isin(*families)).unionByName(made.where("part = 'object'").select(*OBJECT_COLUMNS))
    new_local = made.where("part = 'node'").withColumnRenamed("obj", "center").select(*local_index.NODE_COLUMNS)
    local = written(idx.local_nodes.where(~F.col("pid").isin(*families)).unionByName(new_local), "local-nodes")
    return replace(idx, tree=tree, nodes=nodes, placement=placement, objects=objects, local_nodes=local, local_height=local.agg(F.max("level").alias("h")).first().h or 1)


def insert(idx: MetricIndex, objects: DataFrame) -> MetricIndex:
    """`idx` with [oid, obj] added; only the new objects are routed and only small tables, and partitions that overflow, are rewritten."""
    if idx.local != "tree":
        raise ValueError("updates need local trees")
    if not idx.n:
        return build_index(objects, idx.metric, idx.dim, idx.n_p, idx.n_w, idx.fanout)
    tree = copy.deepcopy(idx.tree)
    routed = _routed(idx, tree, objects)
    placement = _placed(replace(idx, tree=tree), tree)
    fresh, local = _in_local_trees(idx, routed, tree, placement)
    n = idx.n + fresh.count()
    nodes = global_index.nodes_frame(idx.objects.sparkSession, tree)
    return split_overflow(replace(idx, n=n, nodes=nodes, tree=tree, placement=placement, local_nodes=local, objects=idx.objects.select(*OBJECT_COLUMNS).unionByName(fresh)))


def delete(idx: MetricIndex, oids: DataFrame) -> MetricIndex:
    """`idx` without the objects of `oids` [oid]. Counts of clusters are lowered, so that bounds by counts stay true."""
    gone = oids.select(F.col("oid").alias("gone_")).distinct()
    objects = idx.objects.join(gone, F.col("oid") == F.col("gone_"), "left_anti")
    lost = idx.objects.join(gone, F.col("oid") == F.col("gone_"), "left_semi").groupBy("pid").agg(F.count("*").alias("n")).collect()  # at most one row a partition
    tree = copy.deepcopy(idx.tree)
    by_pid = {n.pid: n for n in tree.leaves()}
    for r in lost:
        node = by_pid[r.pid]
        while True:
            node.n_objects -= r.n
            if node.parent_id < 0:
                break
            node = tree.nodes[node.parent_id]
    nodes = global_index.nodes_frame(idx.objects.sparkSession, tree)
    return replace(idx, n=idx.n - sum(r.n for r in lost), tree=tree, nodes=nodes, objects=objects)


def compact(idx: MetricIndex) -> MetricIndex:
    """A fresh index of the same objects: deltas folded in, partitions packed and dealt again."""
    return build_index(idx.objects.select("oid", "obj"), idx.metric, idx.dim, idx.n_p, idx.n_w, idx.fanout, local=idx.local)
