"""The three-stage index as tables: nodes, placement, local nodes, and objects in files by slot."""
from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.metrics import Metric, metric as metric_by_name
from ..sources.tables import accepted, discard, new_path, written
from . import global_index, intermediate, local_index

OBJECT_COLUMNS = ["slot", "bucket", "pid", "lnode_id", "cell", "d_leaf", "d_center", "oid", "obj", "dv", "rank_v"]
ROW_SCHEMA = "bucket int, pid long, lnode_id long, cell int, d_leaf double, d_center double, oid long, obj {}, dv array<double>, rank_v long, parent_id long, level int, is_leaf boolean, dist_to_parent double, radius double, n_objects long, part string, slot int"


@dataclass(frozen=True)
class MetricIndex:
    metric: Metric
    dim: int | None
    n: int
    n_p: int
    n_w: int
    fanout: int
    local: str
    height: int
    nodes: DataFrame
    placement: DataFrame
    objects: DataFrame
    local_nodes: DataFrame
    tree: global_index.Tree
    local_height: int = 1
    path: str | None = None
    options: dict = field(default_factory=dict)

    def with_objects(self, objects: DataFrame) -> "MetricIndex":
        return replace(self, objects=objects)


def build_index(objects: DataFrame, metric: Metric, dim: int | None = None, n_p: int = 200, n_w: int = 10, fanout: int = 20, seed: int = 42, placement: str = "packed", balance: str = "objects", leaf_capacity: int | None = None, local: str = "tree", path: str | None = None, max_nodes: int = global_index.MAX_NODES, broadcast_nodes: int = global_index.BROADCAST_NODES) -> MetricIndex:
    """Build and write the index of [oid, obj]. Objects are moved once, by bucket; everything else is of the order of N_p rows.

    Objects that are null, not finite or of another length are left out; `sources.tables.rejected` counts them.
    """
    spark = objects.sparkSession
    clean = accepted(objects, metric, dim)
    tree, assigned, n = global_index.bulk_load(clean, metric, n_p, fanout, seed, max_nodes=max_nodes, dim=dim, broadcast_nodes=broadcast_nodes)
    nodes = global_index.nodes_frame(spark, tree)
    leaves = nodes.where("is_leaf")
    cap = leaf_capacity or intermediate.default_leaf_capacity(max(1, sum(x.n_objects > 0 for x in tree.leaves())), n_w, fanout)
    from . import variants  # it searches, so it needs this module first

    placed = {"packed": lambda: intermediate.deal(intermediate.pack(leaves, cap, balance), n_w), "random": lambda: variants.random_placement(leaves, n_w, seed), "homogeneous": lambda: variants.homogeneous_placement(leaves, n_w)}[placement]()
    placed = placed.join(leaves.select(F.col("pid").alias("np_"), "node_id"), F.col("pid") == F.col("np_")).drop("np_")
    rows = placed.collect()  # one row a partition: the plan of the placement, fixed from here on
    placed = spark.createDataFrame(rows, placed.schema)
    path = path or new_path(spark, "index")
    kind = objects.schema["obj"].dataType.simpleString()
    made = local_index.build(assigned, placed, metric, fanout, seed, local).drop("chop")
    made.sortWithinPartitions("slot", "part", "bucket", "lnode_id", "d_leaf").write.partitionBy("part", "slot").parquet(f"{path}/objects")
    if hasattr(assigned, "_written_at"):
        discard(assigned)
    rows = _read_rows(spark, path, kind)
    kept = rows.where("part = 'object'").select(*OBJECT_COLUMNS)
    out_local = local_index.local_nodes(rows, kept, nodes, local)
    out_local.write.parquet(f"{path}/local_nodes")
    local_nodes = spark.read.schema(out_local.schema).parquet(f"{path}/local_nodes")
    local_height = local_nodes.agg(F.max("level").alias("h")).first().h or 1
    placed.write.parquet(f"{path}/placement")
    nodes.write.parquet(f"{path}/nodes")
    manifest = {"metric": metric.name, "dim": dim, "n": n, "n_p": n_p, "n_w": n_w, "fanout": fanout, "seed": seed, "local": local, "placement": placement, "height": tree.height, "local_height": local_height}
    spark.createDataFrame([(json.dumps(manifest),)], "manifest string").write.parquet(f"{path}/manifest")
    return MetricIndex(metric, dim, n, n_p, n_w, fanout, local, tree.height, nodes, placed, kept, local_nodes, tree, local_height, path, manifest)


def _read_rows(spark: SparkSession, path: str, kind: str) -> DataFrame:
    return spark.read.schema(ROW_SCHEMA.format(kind)).parquet(f"{path}/objects")


def open_index(spark: SparkSession, path: str) -> MetricIndex:
    """An index written by `build_index`, from its files and manifest alone."""
    m = json.loads(spark.read.parquet(f"{path}/manifest").first().manifest)
    metric = metric_by_name(m["metric"])
    nodes = spark.read.parquet(f"{path}/nodes")
    tree = global_index.Tree([], m["height"], metric.kind)
    for r in sorted(nodes.collect(), key=lambda r: r.node_id):  # about N_p rows
        while len(tree.nodes) < r.node_id:
            tree.nodes.append(global_index.Node(-1, -2, -1, None, 0.0))
        tree.nodes.append(global_index.Node(r.node_id, r.parent_id, r.level, r.center, r.dist_to_parent, [], r.radius, r.n_objects, r.pid))
    for x in tree.nodes:
        if x.parent_id >= 0:
            tree.nodes[x.parent_id].children.append(x.node_id)
    rows = _read_rows(spark, path, "string" if metric.kind == "string" else "array<double>")
    return MetricIndex(metric, m["dim"], m["n"], m["n_p"], m["n_w"], m["fanout"], m["local"], m["height"], nodes, spark.read.parquet(f"{path}/placement"), rows.where("part = 'object'").select(*OBJECT_COLUMNS), spark.read.parquet(f"{path}/local_nodes"), tree, m["local_height"], path, m)


__all__ = ["MetricIndex", "build_index", "open_index", "written"]
