"""Samples that don't depend on the layout of the data: the smallest hashes of the ids."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def hash_key(seed: int, oid: str = "oid") -> Column:
    return F.xxhash64(F.col(oid), F.lit(seed))


def hash_sample(objects: DataFrame, n: int, seed: int) -> DataFrame:
    """The `n` objects of smallest hash: a top-n per task and a merge, no full sort."""
    return objects.orderBy(hash_key(seed), "oid").limit(n)


def share(objects: DataFrame, percent: int, seed: int = 0) -> DataFrame:
    """About `percent` of the objects, the same ones on every run and layout."""
    return objects.where(F.pmod(hash_key(seed), F.lit(100)) < percent)


def pick_centers(objects: DataFrame, n: int, seed: int) -> list:
    """Random centres on the driver; `n` is about the number of partitions, never the number of objects."""
    return [r.obj for r in hash_sample(objects, n, seed).select("obj").collect()]


def pair_distances(objects: DataFrame, metric, n: int = 200, seed: int = 11, dim: int | None = None) -> DataFrame:
    """`d` over n * n pairs of two independent samples; `n` is a parameter."""
    a = hash_sample(objects, n, seed).select(F.col("oid").alias("ai"), F.col("obj").alias("ao"))
    b = hash_sample(objects, n, seed + 1).select(F.col("oid").alias("bi"), F.col("obj").alias("bo"))
    return a.crossJoin(F.broadcast(b)).where("ai <> bi").select(metric.column(F.col("ao"), F.col("bo"), dim).alias("d"))


def distance_stats(objects: DataFrame, metric, n: int = 200, seed: int = 11, dim: int | None = None) -> DataFrame:
    """(n, mean, variance, max, intrinsic_dim) of sampled distances."""
    d = pair_distances(objects, metric, n, seed, dim)
    return d.agg(F.count("*").alias("n"), F.avg("d").alias("mean"), F.var_pop("d").alias("variance"), F.max("d").alias("max")).withColumn("intrinsic_dim", F.col("mean") ** 2 / (2 * F.col("variance")))


def radius_for(objects: DataFrame, metric, percent: float, mode: str = "selectivity", n: int = 200, seed: int = 11, dim: int | None = None) -> float:
    """A radius for `percent`: of the pairs answered ("selectivity") or of the largest distance ("max_share")."""
    d = pair_distances(objects, metric, n, seed, dim)
    agg = F.percentile("d", F.lit(percent / 100)) if mode == "selectivity" else F.max("d") * (percent / 100)
    return float(d.agg(agg.alias("r")).first().r)
