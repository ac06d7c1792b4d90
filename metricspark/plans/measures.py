"""What searches and builds cost: counts by stage, load over slots, time, storage, recall."""
from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import bounds
from ..operators import search
from ..operators.index import MetricIndex


def stage_counts(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """One row: tests and survivors of a range search by stage, over all queries."""
    q = search.with_radius(queries, r)
    cand = search.global_candidates(idx, q)
    lcand = search.local_candidates(idx, cand)
    objs = search.candidate_objects(idx, lcand)
    n_q = q.agg(F.count("*").alias("n_queries"))
    c = cand.agg(F.count("*").alias("candidate_partitions"), F.coalesce(F.sum(F.col("validated").cast("long")), F.lit(0)).alias("validated_partitions"))
    lo = lcand.agg(F.count("*").alias("candidate_clusters"))
    o = objs.agg(F.count("*").alias("reached"), F.coalesce(F.sum((F.col("decided_by") == "verified").cast("long")), F.lit(0)).alias("verified"), F.coalesce(F.sum((F.col("decided_by") != "verified").cast("long")), F.lit(0)).alias("validated"))
    out = n_q.crossJoin(c).crossJoin(lo).crossJoin(o)  # four tables of one row each
    return out.withColumn("global_tests", F.col("n_queries") * F.lit(len(idx.tree.top()))).withColumn("objects", F.lit(idx.n))


def pruning(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """[stage, filtered, validated, survived, distance_calls] summed over the queries."""
    m, q = idx.metric, search.with_radius(queries, r)
    leaves = idx.nodes.where("is_leaf").select("pid", "center", "radius")
    alld = q.crossJoin(F.broadcast(leaves)).withColumn("d", m.column(F.col("q"), F.col("center"), idx.dim))
    pr, va = bounds.cluster_prunable(F.col("d"), F.col("radius"), m.slack(F.col("r"))), bounds.cluster_valid(F.col("d"), F.col("radius"), m.tight(F.col("r")))
    cut = lambda x: F.coalesce(F.sum(x.cast("long")), F.lit(0))
    a = alld.agg(F.lit("partitions").alias("stage"), cut(pr).alias("filtered"), cut(va).alias("validated"), cut(~pr & ~va).alias("survived"), F.count("*").alias("distance_calls"))
    cand = search.global_candidates(idx, q)
    b = None
    for tested, _ in search.local_levels(idx, cand.where("not validated")):
        pr, va = bounds.cluster_prunable(F.col("d_ql"), F.col("lr_"), m.slack(F.col("r"))), bounds.cluster_valid(F.col("d_ql"), F.col("lr_"), m.tight(F.col("r")))
        step = tested.where("not validated and not again").select(pr.alias("pr"), va.alias("va"))
        b = step if b is None else b.unionByName(step)
    b = b.agg(F.lit("clusters").alias("stage"), cut(F.col("pr")).alias("filtered"), cut(F.col("va")).alias("validated"), cut(~F.col("pr") & ~F.col("va")).alias("survived"), F.count("*").alias("distance_calls"))
    lcand = search.local_candidates(idx, cand).where("not validated")
    o = idx.objects.select(F.col("slot").alias("os_"), F.col("lnode_id").alias("ol_"), "d_leaf")
    k = o.join(lcand, (F.col("os_") == F.col("slot")) & (F.col("ol_") == F.col("lnode_id")))
    pr, va = bounds.object_prunable(F.col("d_leaf"), F.col("d_ql"), m.slack(F.col("r"))), bounds.object_valid(F.col("d_leaf"), F.col("d_ql"), m.tight(F.col("r")))
    c = k.agg(F.lit("objects").alias("stage"), cut(pr).alias("filtered"), cut(va).alias("validated"), cut(~pr & ~va).alias("survived"), cut(~pr & ~va).alias("distance_calls"))
    return a.unionByName(b).unionByName(c)


def workload(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """[slot, shipped, verified, validated, answers]: the work that each slot has with these queries; idle slots count with zeros."""
    q = search.with_radius(queries, r)
    cand = search.locate(search.global_candidates(idx, q), idx.placement.select("pid", "bucket", "slot"))
    shipped = cand.groupBy(F.col("slot").alias("s1_")).agg(F.count("*").alias("shipped"))
    objs = search.candidate_objects(idx, search.local_candidates(idx, search.global_candidates(idx, q)))
    d = idx.metric.column(F.col("q"), F.col("obj"), idx.dim)
    done = objs.groupBy(F.col("slot").alias("s2_")).agg(F.sum((F.col("decided_by") == "verified").cast("long")).alias("verified"), F.sum((F.col("decided_by") != "verified").cast("long")).alias("validated"), F.sum((d <= F.col("r")).cast("long")).alias("answers"))
    slots = idx.objects.sparkSession.range(idx.n_w).select(F.col("id").cast("int").alias("slot"))
    out = slots.join(shipped, F.col("slot") == F.col("s1_"), "left").join(done, F.col("slot") == F.col("s2_"), "left")
    return out.select("slot", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("shipped", "verified", "validated", "answers")])


def load_deviation(work: DataFrame, column: str = "verified") -> DataFrame:
    """[mean, stddev, variation] over slots."""
    return work.agg(F.avg(column).alias("mean"), F.stddev_pop(column).alias("stddev")).withColumn("variation", F.col("stddev") / F.when(F.col("mean") > 0, F.col("mean")))


def placement_balance(idx: MetricIndex) -> DataFrame:
    """[slot, partitions, n_objects]."""
    return idx.placement.groupBy("slot").agg(F.count("*").alias("partitions"), F.sum("n_objects").alias("n_objects"))


def shipped(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """[n]: (query, partition) pairs sent to workers."""
    return search.global_candidates(idx, search.with_radius(queries, r)).agg(F.count("*").alias("n"))


def distance_calls(idx: MetricIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """[stage, distance_calls]."""
    return pruning(idx, queries, r).select("stage", "distance_calls")


def timed(action) -> tuple[object, float]:
    t = time.perf_counter()
    out = action()
    return out, time.perf_counter() - t


def timed_build(build) -> tuple[MetricIndex, float]:
    """Index and seconds of a build; writing the files is part of it, so everything has run."""
    return timed(build)


def query_time(answer, n_queries: int) -> float:
    """Seconds a query of one batch."""
    return timed(lambda: answer().write.format("noop").mode("overwrite").save())[1] / max(1, n_queries)


def throughput(answer, n_queries: int) -> float:
    """Queries a minute when all are asked at once."""
    return n_queries / max(1e-9, timed(lambda: answer().write.format("noop").mode("overwrite").save())[1]) * 60


def update_cost(seconds: float, n: int) -> float:
    """Milliseconds an update."""
    return 1000 * seconds / max(1, n)


def speedup(seconds: dict[int, float]) -> dict[int, float]:
    """Against the run with the fewest workers."""
    first = seconds[min(seconds)]
    return {w: first / s for w, s in sorted(seconds.items())}


def index_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of an index's files, in any file system that Spark reads."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return int(p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength())


def index_rows(idx: MetricIndex) -> DataFrame:
    """[part, n]: entries on the primary node, in the ordered index, in local nodes, objects."""
    spark = idx.objects.sparkSession
    one = lambda name, df: df.agg(F.lit(name).alias("part"), F.count("*").alias("n"))
    del spark
    return one("global", idx.nodes).unionByName(one("intermediate", idx.placement)).unionByName(one("local_nodes", idx.local_nodes)).unionByName(one("objects", idx.objects))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """[recall]: share of the exact neighbours that `found` has."""
    f = found.select(F.col("qid").alias("fq_"), F.col("oid").alias("fo_")).distinct()
    j = exact.join(f, (F.col("qid") == F.col("fq_")) & (F.col("oid") == F.col("fo_")), "left")
    return j.agg(F.avg(F.col("fo_").isNotNull().cast("double")).alias("recall"))


def model_error(predicted: DataFrame, counted: DataFrame) -> DataFrame:
    """[n_p, predicted, counted, ratio] from [n_p, predicted] and [n_p, counted]."""
    c = counted.select(F.col("n_p").alias("c_"), "counted")
    return predicted.join(c, F.col("n_p") == F.col("c_")).select("n_p", "predicted", "counted", (F.col("predicted") / F.col("counted")).alias("ratio"))
