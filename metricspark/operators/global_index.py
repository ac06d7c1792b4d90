"""Stage 1: a small tree of random centres on the driver, and the objects' descent to their nearest leaf.

The tree has about N_p leaves, so it fits the driver whatever the number of objects; `max_nodes` guards that. Overfull leaves
are found on a bounded sample, before any object moves, so the objects descend once: level by level to the
nearest centre (ties to the later one), in blocks of Arrow batches, a narrow map without a shuffle. The descent is
written once, one aggregate of N_p rows gives sizes and exact covering radii on all levels, and if a leaf is
still overfull only the objects under its parent are compared with the new centres.
"""
from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.metrics import Metric
from ..sources.tables import discard, written
from .sampling import hash_key, hash_sample

MAX_NODES = 100_000
BROADCAST_NODES = 20_000  # a larger leaf level is joined, not shipped
SAMPLE_PER_LEAF, SAMPLE_MORE = 64, 50_000  # objects that the first splits look at: so many a leaf, so many beside the centres at most
BLOCK_ROWS = 50_000  # objects that descend together


def capacity(n: int, n_p: int) -> int:
    """Objects a partition may hold before it is split."""
    return max(1, -(-n // n_p))


@dataclass
class Node:
    node_id: int
    parent_id: int
    level: int
    center: object
    dist_to_parent: float
    children: list[int] = field(default_factory=list)
    radius: float = 0.0
    n_objects: int = 0
    pid: int = -1


@dataclass
class Tree:
    nodes: list[Node]
    height: int
    kind: str

    def leaves(self) -> list[Node]:
        return [n for n in self.nodes if n.level == self.height and not n.children and n.node_id >= 0]

    def top(self) -> list[int]:
        return [n.node_id for n in self.nodes if n.level == 1]


def _key(center) -> tuple:
    return (center,) if isinstance(center, str) else tuple(center)


def _nearest(metric: Metric, objs, centers: list) -> tuple[np.ndarray, np.ndarray]:
    """(index of the nearest centre, distance) of each object; of equally near centres the last."""
    batch = metric.batch(objs) if isinstance(objs, list) else objs
    best = dist = None
    for k, c in enumerate(centers):
        d = metric.kernel(batch, c if isinstance(c, str) else np.asarray(c, float))
        if best is None:
            best, dist = np.zeros(len(d), int), d
        else:
            closer = d <= dist
            best, dist = np.where(closer, k, best), np.where(closer, d, dist)
    return best, dist


def plan_tree(leaf_centers: list, fanout: int, metric: Metric, max_nodes: int = MAX_NODES) -> Tree:
    """Levels of centres from the leaves up: each upper level is a sub-sample, each centre hangs under its nearest."""
    leaf_centers = list({_key(c): c for c in leaf_centers}.values())
    if len(leaf_centers) > max_nodes:
        raise ValueError(f"{len(leaf_centers)} centres; raise max_nodes or lower n_p")
    levels = [leaf_centers]
    while len(levels[0]) > fanout:
        below = levels[0]
        levels.insert(0, below[: max(1, math.ceil(len(below) / fanout))])
    nodes: list[Node] = []
    above: list[int] = []
    for depth, centers in enumerate(levels, 1):
        if above:
            which, dist = _nearest(metric, centers, [nodes[a].center for a in above])
        ids = []
        for k, c in enumerate(centers):
            parent = above[which[k]] if above else -1
            nodes.append(Node(len(nodes), parent, depth, c, float(dist[k]) if above else 0.0))
            if above:
                nodes[parent].children.append(nodes[-1].node_id)
            ids.append(nodes[-1].node_id)
        above = ids
    return Tree(nodes, len(levels), metric.kind)


def tree_from_levels(levels: list[list], metric: Metric) -> Tree:
    """A tree over given centres, top level first (worked examples and tests)."""
    nodes: list[Node] = []
    above: list[int] = []
    for depth, centers in enumerate(levels, 1):
        if above:
            which, dist = _nearest(metric, centers, [nodes[a].center for a in above])
        ids = []
        for k, c in enumerate(centers):
            parent = above[which[k]] if above else -1
            nodes.append(Node(len(nodes), parent, depth, c, float(dist[k]) if above else 0.0))
            if above:
                nodes[parent].children.append(nodes[-1].node_id)
            ids.append(nodes[-1].node_id)
        above = ids
    return Tree(nodes, len(levels), metric.kind)


def _descend(metric: Metric, tree: Tree, objs) -> tuple[np.ndarray, np.ndarray]:
    """(leaf id, distances on each level) by nearest centre on every level; `objs` is a list or a batch of the metric."""
    batch = metric.batch(objs) if isinstance(objs, list) else objs
    n = len(batch[1]) if isinstance(batch, tuple) else len(batch)
    at, dists = np.full(n, -1), np.zeros((n, tree.height))
    for level in range(tree.height):
        order = np.argsort(at, kind="stable")
        nodes, first = np.unique(at[order], return_index=True)
        for node, lo, hi in zip(nodes.tolist(), first.tolist(), [*first.tolist()[1:], n]):
            rows = order[lo:hi]
            below = tree.top() if node < 0 else tree.nodes[node].children
            if below:
                k, d = _nearest(metric, metric.take(batch, rows), [tree.nodes[i].center for i in below])
                at[rows], dists[rows, level] = np.array(below)[k], d
    return at, dists


def _in_blocks(batches, rows: int = BLOCK_ROWS):
    """Arrow batches joined to blocks of about `rows` rows, so that a group of a block is worth a call of the kernel."""
    held, n = [], 0
    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _lists(d: np.ndarray) -> pa.ListArray:
    """The rows of a matrix as lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(len(d) + 1, dtype=np.int32) * np.int32(d.shape[1])), pa.array(np.ascontiguousarray(d, float).ravel()))


ASSIGNED = "oid long, obj {}, leaf long, d_center double, d_anc array<double>"


def assign(objects: DataFrame, tree: Tree, metric: Metric) -> DataFrame:
    """[oid, obj, leaf, d_center, d_anc]: each object with its leaf and its distances on the way down."""
    obj = objects.schema["obj"].dataType.simpleString()
    shipped = objects.sparkSession.sparkContext.broadcast(tree)

    def run(batches):
        for batch in _in_blocks(batches):
            leaf, d = _descend(metric, shipped.value, metric.from_arrow(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(leaf.astype(np.int64)), pa.array(d[:, -1]), _lists(d)], names=["oid", "obj", "leaf", "d_center", "d_anc"])

    return objects.select("oid", "obj").mapInArrow(run, ASSIGNED.format(obj))


def reroute(assigned: DataFrame, tree: Tree, fresh: dict[int, list[int]], metric: Metric) -> DataFrame:
    """`assigned` after new leaves `fresh` {parent: leaves} joined the tree: objects under these parents move if a new centre is as near."""
    obj = assigned.schema["obj"].dataType.simpleString()
    parent = np.array([n.parent_id for n in tree.nodes])
    shipped = assigned.sparkSession.sparkContext.broadcast((parent, {p: [(i, tree.nodes[i].center) for i in ids] for p, ids in fresh.items()}))

    def run(batches):
        for batch in _in_blocks(batches):
            up, added = shipped.value
            leaf, d = batch.column(2).to_numpy().copy(), batch.column(3).to_numpy().copy()
            above = up[leaf]
            for p, centers in added.items():
                rows = np.flatnonzero(above == p)
                if len(rows):
                    k, near = _nearest(metric, metric.from_arrow(batch.column(1).take(pa.array(rows))), [c for _, c in centers])
                    moved = near <= d[rows]
                    leaf[rows[moved]], d[rows[moved]] = np.array([i for i, _ in centers])[k[moved]], near[moved]
            anc = batch.column(4)
            every = anc.flatten().to_numpy(zero_copy_only=False).reshape(len(anc), -1).copy()
            every[:, -1] = d
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(leaf), pa.array(d), _lists(every)], names=["oid", "obj", "leaf", "d_center", "d_anc"])

    return assigned.select("oid", "obj", "leaf", "d_center", "d_anc").mapInArrow(run, ASSIGNED.format(obj))


def assign_by_join(objects: DataFrame, tree: Tree, metric: Metric, dim: int | None = None) -> DataFrame:
    """The same as `assign` for trees whose leaves outgrow a broadcast.

    Only the upper levels are shipped. The leaves' centres under each upper node, about a fanout of them, form one row that
    meets the node's objects in an equi join. The objects are shuffled once by node; AQE splits crowded nodes, since
    the other side has one row a node.
    """
    if tree.height < 2:
        return assign(objects, tree, metric)
    upper = [n.node_id for n in tree.nodes if n.level < tree.height]
    number = {n: k for k, n in enumerate(upper)}
    top = Tree([Node(number[i], number.get(tree.nodes[i].parent_id, -1), tree.nodes[i].level, tree.nodes[i].center, tree.nodes[i].dist_to_parent, [number[c] for c in tree.nodes[i].children if c in number]) for i in upper], tree.height - 1, tree.kind)
    kind = objects.schema["obj"].dataType.simpleString()
    rows = [(number[n.node_id], [(c, tree.nodes[c].center) for c in n.children]) for n in tree.nodes if n.level == tree.height - 1 and n.children]
    groups = objects.sparkSession.createDataFrame(rows, f"node_ long, centers_ array<struct<leaf:bigint,center:{kind}>>")
    own = assign(objects, top, metric).select("oid", "obj", F.col("leaf").alias("up_"), "d_anc")
    joined = own.join(groups.hint("merge"), F.col("up_") == F.col("node_"))
    # of equally near centres the later one, as in `assign`
    near = F.array_min(F.transform("centers_", lambda c: F.struct(metric.column(F.col("obj"), c["center"], dim).alias("d"), (-c["leaf"]).alias("minus"))))
    found = joined.withColumn("near_", near)
    return found.select("oid", "obj", (-F.col("near_.minus")).alias("leaf"), F.col("near_.d").alias("d_center"), F.concat("d_anc", F.array("near_.d")).alias("d_anc"))


def summarise(assigned: DataFrame, tree: Tree) -> None:
    """Sizes and covering radii into the tree. Radii come from the very distances of the descent, so they cover subtrees exactly."""
    rows = assigned.groupBy("leaf").agg(F.count("*").alias("n"), *[F.max(F.col("d_anc")[k]).alias(f"r{k}") for k in range(tree.height)]).collect()  # one row a leaf
    for n in tree.nodes:
        n.radius, n.n_objects = 0.0, 0
    for r in rows:
        at = r.leaf
        for k in range(tree.height - 1, -1, -1):
            node = tree.nodes[at]
            node.radius, node.n_objects = max(node.radius, r[f"r{k}"]), node.n_objects + r.n
            at = node.parent_id


def add_leaf(tree: Tree, sibling: int, center, metric: Metric) -> int | None:
    """A new leaf beside `sibling` around `center`, unless that is a centre there already."""
    old = tree.nodes[sibling]
    beside = tree.nodes[old.parent_id].children if old.parent_id >= 0 else tree.top()
    if _key(center) in {_key(tree.nodes[c].center) for c in beside}:
        return None
    d = float(_nearest(metric, [center], [tree.nodes[old.parent_id].center])[1][0]) if old.parent_id >= 0 else 0.0
    tree.nodes.append(Node(len(tree.nodes), old.parent_id, old.level, center, d))
    if old.parent_id >= 0:
        tree.nodes[old.parent_id].children.append(tree.nodes[-1].node_id)
    return tree.nodes[-1].node_id


def split_on_sample(tree: Tree, metric: Metric, sample: list, n_p: int, rounds: int = 4) -> None:
    """Random splits of leaves that hold over twice their share of the sample: some of their objects become centres."""
    cap = 2 * capacity(len(sample), n_p)
    batch = metric.batch(sample)
    for _ in range(rounds):
        leaf, d = _descend(metric, tree, batch)
        ids, n = np.unique(leaf, return_counts=True)
        changed = False
        for node, size in zip(ids[n > cap].tolist(), n[n > cap].tolist()):
            rows = np.flatnonzero(leaf == node)
            for i in rows[d[rows, -1] > 0][: -(-size // cap)]:
                changed |= add_leaf(tree, node, sample[i], metric) is not None
        if not changed:
            return


def split_oversize(assigned: DataFrame, tree: Tree, metric: Metric, cap: int, seed: int) -> dict[int, list[int]]:
    """New leaves {parent: leaves} around random objects of overfull leaves."""
    over = {n.node_id: -(-n.n_objects // cap) for n in tree.leaves() if n.n_objects > cap and n.radius > 0}
    if not over:
        return {}
    rows = assigned.where(F.col("leaf").isin(*over) if len(over) < 500 else F.col("leaf").isNotNull()).where("d_center > 0")
    lane = Window.partitionBy("leaf").orderBy(hash_key(seed), "oid")
    picked = rows.withColumn("r_", F.row_number().over(lane)).where(F.col("r_") <= max(over.values())).select("leaf", "r_", "obj").collect()
    fresh: dict[int, list[int]] = {}
    for r in sorted(picked, key=lambda r: (r.leaf, r.r_)):
        if r.leaf in over and r.r_ <= over[r.leaf]:
            new = add_leaf(tree, r.leaf, r.obj, metric)
            if new is not None:
                fresh.setdefault(tree.nodes[r.leaf].parent_id, []).append(new)
    return fresh


def bulk_load(objects: DataFrame, metric: Metric, n_p: int, fanout: int, seed: int, rounds: int = 2, max_nodes: int = MAX_NODES, dim: int | None = None, broadcast_nodes: int = BROADCAST_NODES) -> tuple[Tree, DataFrame, int]:
    """(tree, assigned, number of objects): random centres, splits by a sample, one descent, bounded rounds of splits of what is still overfull."""
    sample = [r.obj for r in hash_sample(objects, n_p + min(n_p * SAMPLE_PER_LEAF, SAMPLE_MORE), seed).select("obj").collect()]  # bounded by parameters
    if not sample:
        return Tree([], 0, metric.kind), objects.select("oid", "obj", F.lit(None).cast("long").alias("leaf"), F.lit(0.0).alias("d_center"), F.array(F.lit(0.0)).alias("d_anc")), 0
    tree = plan_tree(sample[:n_p], fanout, metric, max_nodes)
    split_on_sample(tree, metric, sample, n_p)
    routed = assign(objects, tree, metric) if len(tree.nodes) <= broadcast_nodes else assign_by_join(objects, tree, metric, dim)
    assigned = written(routed, "assigned")
    summarise(assigned, tree)
    n = sum(x.n_objects for x in tree.leaves())
    cap = 3 * capacity(n, n_p)
    for k in range(rounds):
        fresh = split_oversize(assigned, tree, metric, cap, seed + 100 + k)
        if not fresh:
            break
        again = written(reroute(assigned, tree, fresh, metric), "assigned")
        discard(assigned)
        assigned = again
        summarise(assigned, tree)
    for pid, leaf in enumerate(tree.leaves()):
        leaf.pid = pid
    return tree, assigned, n


NODE_SCHEMA = "node_id long, parent_id long, level int, center {}, radius double, dist_to_parent double, n_objects long, is_leaf boolean, pid long"


def nodes_frame(spark, tree: Tree) -> DataFrame:
    """The tree as a table of about N_p rows; empty subtrees are left out."""
    kind = "string" if tree.kind == "string" else "array<double>"
    rows = [(n.node_id, n.parent_id, n.level, n.center, n.radius, n.dist_to_parent, n.n_objects, n.level == tree.height, n.pid) for n in tree.nodes if n.n_objects]
    return spark.createDataFrame(rows, NODE_SCHEMA.format(kind))


def verify(index) -> DataFrame:
    """(rule, tested, violated): every object in one partition, inside its radii of both trees on every level, once."""
    objs, m, dim = index.objects, index.metric, index.dim
    leaves = index.nodes.where("is_leaf").select(F.col("pid").alias("p_"), F.col("node_id").alias("n_"))
    joined = objs.join(F.broadcast(leaves), F.col("pid") == F.col("p_"), "left")  # one row a partition
    count = lambda df, rule, bad: df.agg(F.lit(rule).alias("rule"), F.count("*").alias("tested"), F.coalesce(F.sum(bad.cast("long")), F.lit(0)).alias("violated"))

    def climb(start, nodes, height):
        """Each object with every node above it, by parent links; `start` has at_."""
        out, now = None, start
        for _ in range(height):
            now = now.join(nodes, F.col("at_") == F.col("id_"))
            step = now.select("oid", F.when(m.column(F.col("obj"), F.col("c_"), dim) > F.col("rad_") + 1e-9, 1).otherwise(0).alias("bad_"))
            out = step if out is None else out.unionByName(step)
            now = now.select("oid", "obj", F.col("up_").alias("at_"))
        per = out.groupBy("oid").agg(F.max("bad_").alias("bad_"))
        return objs.select(F.col("oid").alias("o_")).join(per, F.col("o_") == F.col("oid"), "left")

    def shape(df, key, parent):
        return df.select(F.col(key).alias("id_"), F.col(parent).alias("up_"), F.col("center").alias("c_"), F.col("radius").alias("rad_"))

    above = climb(joined.select("oid", "obj", F.col("n_").alias("at_")), F.broadcast(shape(index.nodes, "node_id", "parent_id")), index.height)
    out = count(joined, "has one partition", F.col("p_").isNull())
    out = out.unionByName(count(above, "within covering radius", F.coalesce(F.col("bad_"), F.lit(1)) > 0))
    if index.local == "tree":
        local = climb(objs.select("oid", "obj", F.col("lnode_id").alias("at_")), shape(index.local_nodes, "lnode_id", "parent_id"), index.local_height)
        out = out.unionByName(count(local, "within local radius", F.coalesce(F.col("bad_"), F.lit(1)) > 0))
        own = index.local_nodes.where("is_leaf").select(F.col("lnode_id").alias("l_"), F.col("center").alias("lc_"))
        inside = objs.join(own, F.col("lnode_id") == F.col("l_"), "left")
        wrong = F.abs(m.column(F.col("obj"), F.col("lc_"), dim) - F.col("d_leaf")) > 1e-9
        out = out.unionByName(count(inside, "stored distance is right", F.coalesce(wrong, F.lit(True))))
    dup = objs.groupBy("oid").agg(F.count("*").alias("n")).agg(F.lit("no object twice").alias("rule"), F.count("*").alias("tested"), F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("violated"))
    return out.unionByName(dup)


def verify_nearest(index) -> DataFrame:
    """(level, tested, violated): on every level of the global tree the object hangs under the nearest of the centres it could choose from."""
    objs, m, dim = index.objects, index.metric, index.dim
    nodes = index.nodes.select("node_id", "parent_id", "level", "center")
    leaves = index.nodes.where("is_leaf").select(F.col("pid").alias("p_"), F.col("node_id").alias("n_"))
    now = objs.select("oid", "obj", "pid").join(F.broadcast(leaves), F.col("pid") == F.col("p_")).select("oid", "obj", F.col("n_").alias("at_"))
    out = None
    for level in range(index.height, 0, -1):
        here = nodes.where(F.col("level") == level)
        own = now.join(F.broadcast(here), F.col("at_") == F.col("node_id")).select("oid", "obj", F.col("parent_id").alias("up_"), m.column(F.col("obj"), F.col("center"), dim).alias("d_"))
        beside = own.join(F.broadcast(here.select(F.col("parent_id").alias("s_"), F.col("center").alias("c_"))), F.col("up_") == F.col("s_"))
        best = beside.groupBy("oid").agg(F.min(m.column(F.col("obj"), F.col("c_"), dim)).alias("best_"), F.first("d_").alias("d_"))
        step = best.agg(F.lit(level).alias("level"), F.count("*").alias("tested"), F.coalesce(F.sum((F.col("d_") > F.col("best_") + 1e-9).cast("long")), F.lit(0)).alias("violated"))
        out = step if out is None else out.unionByName(step)
        now = own.select("oid", "obj", F.col("up_").alias("at_"))
    return out
