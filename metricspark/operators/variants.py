"""Ablations of the placement: each gives [pid, dist_to_parent, n_objects, bucket, slot] or a slot per object."""
from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from . import search


def random_placement(parts: DataFrame, n_w: int, seed: int = 3) -> DataFrame:
    """Tree leaves dealt at random; no intermediate order."""
    p = parts.select("pid", "dist_to_parent", "n_objects")
    return p.withColumn("bucket", F.col("pid").cast("int")).withColumn("slot", F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(n_w)).cast("int"))


def homogeneous_placement(parts: DataFrame, n_w: int) -> DataFrame:
    """Whole neighbourhoods to one worker: contiguous runs of partitions in tree order with equal shares of objects."""
    w = Window.orderBy("parent_id", "pid")
    total = F.sum("n_objects").over(Window.partitionBy())
    before = F.sum("n_objects").over(w) - F.col("n_objects") / 2
    slot = F.least(F.floor(before * n_w / total), F.lit(n_w - 1)).cast("int")
    return parts.withColumn("slot", slot).withColumn("bucket", F.col("pid").cast("int")).select("pid", "dist_to_parent", "n_objects", "bucket", "slot")


def cluster_id_round_robin(objects: DataFrame, n_w: int) -> DataFrame:
    """Objects in order of their cluster, dealt in turn. Numbering is per cluster, offset by the cluster's id, so no global sort is made."""
    r = F.row_number().over(Window.partitionBy("pid").orderBy("oid")) + F.col("pid")
    return objects.withColumn("slot", F.pmod(r, F.lit(n_w)).cast("int"))


def heterogeneous_placement(objects: DataFrame, n_w: int, seed: int = 3) -> DataFrame:
    """Objects spread evenly by hash; no partition can be left out globally."""
    return objects.withColumn("slot", F.pmod(F.xxhash64("oid", F.lit(seed)), F.lit(n_w)).cast("int"))


def replicated_placement(placement: DataFrame, n_w: int, copies: int = 2) -> DataFrame:
    """Every partition on `copies` slots: balances by choice of copy, at as much storage."""
    each = placement.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    return each.withColumn("slot", F.pmod(F.col("slot") + F.col("copy") * F.lit(max(1, n_w // copies)), F.lit(n_w)).cast("int"))


def range_by_object(idx, place, queries: DataFrame, r: float) -> DataFrame:
    """Range search over objects placed one by one by `place`: no slot can be left out, so every candidate cluster is asked on all of them."""
    placed = idx.with_objects(place(idx.objects.drop("slot"), idx.n_w))
    lcand = search.local_candidates(idx, search.global_candidates(idx, search.with_radius(queries, r)))
    everywhere = lcand.drop("slot").withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(idx.n_w - 1))))
    return search.decided(idx, search.candidate_objects(placed, everywhere))


def range_replicated(idx, queries: DataFrame, r: float, copies: int = 2) -> DataFrame:
    """Range search over partitions kept on several slots: each query asks one copy of a partition, chosen by its hash, so copies share the load."""
    spread = replicated_placement(idx.placement, idx.n_w, copies).select(F.col("pid").alias("rp_"), F.col("copy").alias("copy_"), F.col("slot").alias("rs_"))
    objects = idx.objects.drop("slot").join(F.broadcast(spread), F.col("pid") == F.col("rp_")).withColumnRenamed("rs_", "slot").drop("rp_", "copy_")  # a few rows a partition
    lcand = search.local_candidates(idx, search.global_candidates(idx, search.with_radius(queries, r)))
    mine = lcand.drop("slot").withColumn("c_", F.pmod(F.xxhash64("qid"), F.lit(copies)))
    mine = mine.join(F.broadcast(spread), (F.col("pid") == F.col("rp_")) & (F.col("c_") == F.col("copy_"))).withColumnRenamed("rs_", "slot").drop("rp_", "copy_", "c_")
    return search.decided(idx, search.candidate_objects(idx.with_objects(objects), mine))
