"""Stage 3: local trees. One shuffle moves the objects to their bucket; each partition becomes a tree of its own inside it.

"tree": an M-tree a partition: random centres, about one a `fanout` of objects, under levels of sub-samples of them, every node with at most
about `fanout` children; objects hang at the nearest centre level by level and keep their distance to the last one.
Nodes keep covering radius, distance to their parent's centre and number of objects. "flat": no local structure.
"vantage": per partition, distances to vantage objects, cut into cells on the first.
A partition is at most a few times N / N_p objects; identical objects that no centre splits are cut by hash.

Objects and local nodes come out of one pass and are written together, told apart by `part`.
"""
from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.metrics import Metric
from .global_index import _descend, _key, _lists, plan_tree

CHOP = 200_000  # most objects of a group in one task
VANTAGES = 3
NODE_COLUMNS = ["slot", "bucket", "pid", "lnode_id", "parent_id", "level", "is_leaf", "dist_to_parent", "radius", "n_objects", "center"]


def _order(oids: np.ndarray, seed: int) -> np.ndarray:
    mixed = (oids.astype(np.uint64) ^ np.uint64(seed * 0x9E3779B9)) * np.uint64(0xBF58476D1CE4E5B9)
    return np.lexsort((oids, mixed ^ (mixed >> np.uint64(31))))


def tree_of(metric: Metric, objs: list, batch, order, fanout: int):
    """(tree, leaf of each object, distance to its centre): a tree over random distinct centres, radii and counts filled in."""
    want, seen, chosen = max(1, math.ceil(len(objs) / fanout)), set(), []
    for i in order:
        key = _key(objs[i])
        if key not in seen:
            seen.add(key)
            chosen.append(objs[i])
        if len(chosen) == want:
            break
    tree = plan_tree(chosen, max(2, fanout), metric, 1 << 20)
    at, d = _descend(metric, tree, batch)
    node, up = at.copy(), np.array([x.parent_id for x in tree.nodes])
    for level in range(tree.height - 1, -1, -1):
        ids, where = np.unique(node, return_inverse=True)
        most = np.zeros(len(ids))
        np.maximum.at(most, where, d[:, level])
        for k, (i, n) in enumerate(zip(ids.tolist(), np.bincount(where).tolist())):
            tree.nodes[i].radius, tree.nodes[i].n_objects = float(most[k]), n
        node = up[node]
    return tree, at, d[:, -1]


def _cluster(metric: Metric, fanout: int, seed: int, local: str):
    def run(rows: pa.Table) -> pa.Table:
        n, at = len(rows), [c for c in rows.column_names if c != "chop"]
        one = {c: rows.column(c)[0].as_py() for c in ("slot", "bucket", "pid", "chop")}
        base = one["pid"] << 32 | one["chop"] << 20
        batch, oids = metric.from_arrow(rows.column("obj").combine_chunks()), rows.column("oid").to_numpy()
        objs = rows.column("obj").to_pylist() if metric.kind == "string" else batch
        order = _order(oids, seed)
        if local == "vantage":
            dv = np.stack([metric.kernel(batch, objs[i]) for i in order[:VANTAGES]], axis=1)
            cells = max(1, math.ceil(n / (fanout * 4)))
            cell = np.argsort(np.argsort(dv[:, 0], kind="stable"), kind="stable") * cells // n
            rank = np.full(n, -1)
            rank[order[:VANTAGES]] = np.arange(len(order[:VANTAGES]))
            return _made(rows.select(at), n, {"lnode_id": np.full(n, base), "cell": cell, "d_leaf": dv[:, 0], "dv": _lists(dv), "rank_v": rank, **OBJECT})
        tree, leaf, d = tree_of(metric, objs, batch, order, fanout)
        out = _made(rows.select(at), n, {"lnode_id": base | leaf.astype(np.int64), "cell": 0, "d_leaf": d, "dv": None, "rank_v": -1, **OBJECT})
        nodes = [x for x in tree.nodes if x.n_objects]
        own = pa.table({**{c: pa.array([one[c]] * len(nodes), rows.schema.field(c).type) for c in ("slot", "bucket", "pid")}, "oid": pa.array([-1] * len(nodes), pa.int64()), "obj": pa.array([x.center if isinstance(x.center, str) else list(x.center) for x in nodes], rows.schema.field("obj").type), "d_center": [0.0] * len(nodes)})
        made = _made(own, len(nodes), {
            "lnode_id": [base | x.node_id for x in nodes], "cell": 0, "d_leaf": 0.0, "dv": None, "rank_v": -1, "part": "node", "parent_id": [base | x.parent_id if x.parent_id >= 0 else -1 for x in nodes],
            "level": [x.level for x in nodes], "is_leaf": [x.level == tree.height for x in nodes], "dist_to_parent": [x.dist_to_parent for x in nodes],
            "radius": [x.radius for x in nodes], "n_objects": [x.n_objects for x in nodes],
        })
        return pa.concat_tables([out, made.cast(out.schema)])

    return run


OBJECT = {"part": "object", "parent_id": -1, "level": 0, "is_leaf": False, "dist_to_parent": 0.0, "radius": 0.0, "n_objects": 0}
KINDS = {"lnode_id": pa.int64(), "cell": pa.int32(), "d_leaf": pa.float64(), "dv": pa.list_(pa.float64()), "rank_v": pa.int64(), "part": pa.string(), "parent_id": pa.int64(), "level": pa.int32(), "is_leaf": pa.bool_(), "dist_to_parent": pa.float64(), "radius": pa.float64(), "n_objects": pa.int64()}


def _made(rows: pa.Table, n: int, columns: dict) -> pa.Table:
    """`rows` with more columns; a single value stands for all rows, None for empty lists."""
    for name, kind in KINDS.items():
        x = columns[name]
        if x is None:
            x = _lists(np.empty((n, 0)))
        elif not isinstance(x, pa.Array):
            x = pa.repeat(pa.scalar(x, kind), n) if np.isscalar(x) else pa.array(x, kind)
        rows = rows.append_column(pa.field(name, kind), x.cast(kind))
    return rows


def build(assigned: DataFrame, placement: DataFrame, metric: Metric, fanout: int, seed: int, local: str = "tree") -> DataFrame:
    """Objects and local nodes of [oid, obj, leaf, d_center], ready to be written. `placement` has one row a partition."""
    kind = assigned.schema["obj"].dataType.simpleString()
    p = placement.select(F.col("pid").alias("p_"), "node_id", "bucket", "slot", "n_objects")
    moved = assigned.join(F.broadcast(p), F.col("leaf") == F.col("node_id"))
    chop = F.pmod(F.xxhash64("oid"), F.greatest(F.ceil(F.col("n_objects") / CHOP), F.lit(1))).cast("int")
    moved = moved.select("slot", "bucket", F.col("p_").alias("pid"), chop.alias("chop"), "oid", "obj", "d_center")
    schema = f"slot int, bucket int, pid long, oid long, obj {kind}, d_center double, lnode_id long, cell int, d_leaf double, dv array<double>, rank_v long, part string, parent_id long, level int, is_leaf boolean, dist_to_parent double, radius double, n_objects long"
    if local == "flat":
        own = {"lnode_id": F.col("pid") * F.lit(1 << 32), "cell": F.lit(0), "d_leaf": F.col("d_center"), "dv": F.array().cast("array<double>"), "rank_v": F.lit(-1).cast("long"), "part": F.lit("object"), "parent_id": F.lit(-1).cast("long"), "level": F.lit(0), "is_leaf": F.lit(False), "dist_to_parent": F.lit(0.0), "radius": F.lit(0.0), "n_objects": F.lit(0).cast("long")}
        return moved.select("*", *[c.alias(n) for n, c in own.items()]).repartition("slot", "bucket")
    return moved.groupBy("slot", "bucket", "pid", "chop").applyInArrow(_cluster(metric, fanout, seed, local), schema)


def local_nodes(written: DataFrame, objects: DataFrame, nodes: DataFrame, local: str) -> DataFrame:
    """NODE_COLUMNS of the local nodes; an index without local trees has its partitions instead."""
    if local == "tree":
        return written.where("part = 'node'").withColumnRenamed("obj", "center").select(*NODE_COLUMNS)
    leaves = nodes.where("is_leaf").select(F.col("pid").alias("p_"), "center", "radius")
    groups = objects.groupBy("slot", "bucket", "pid", "lnode_id").agg(F.count("*").alias("n_objects")).join(F.broadcast(leaves), F.col("pid") == F.col("p_"))
    return groups.select("slot", "bucket", "pid", "lnode_id", F.lit(-1).cast("long").alias("parent_id"), F.lit(1).alias("level"), F.lit(True).alias("is_leaf"), F.lit(0.0).alias("dist_to_parent"), "radius", "n_objects", "center")
