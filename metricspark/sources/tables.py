"""Input tables, tables written to the shared folder, and the object sets."""
from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions import metrics


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see; sessions that name none (tests) get a local one."""
    return spark.conf.get("spark.checkpoint.dir", None) or "/tmp/checkpoints"


def new_path(spark: SparkSession, tag: str) -> str:
    """A fresh path in the shared folder, removed when the JVM ends."""
    path = f"{shared_dir(spark)}/metricspark/{tag}-{uuid.uuid4().hex}"
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    return path


def written(df: DataFrame, tag: str) -> DataFrame:
    """Write and read back: lineage is cut and a lost executor costs nothing already done."""
    path = new_path(df.sparkSession, tag)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def discard(*frames: DataFrame) -> None:
    """Remove tables made by `written` that nothing reads any more."""
    for df in frames:
        at = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._written_at)
        at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


@dataclass(frozen=True)
class ObjectSet:
    """A table of objects [oid, obj] with its metric and frozen queries."""

    name: str
    metric: metrics.Metric
    dim: int | None
    r: float
    scale: tuple


ORIGIN_US = 1_704_067_200_000_000  # 2024-01-01 UTC in microseconds
MONTH_US = 2_592_000_000_000.0
LETTERS = "abcdefghijklmnopqrstuvwxyz"


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of the wall clock, whatever the session's time zone."""
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts.cast("timestamp_ntz"))


def event_points(spark, sf_dir) -> DataFrame:
    e = table(spark, sf_dir, "events").where("ts is not null and value is not null")
    return e.select(F.col("event_id").alias("oid"), F.array((micros(F.col("ts")) - ORIGIN_US) / F.lit(MONTH_US), F.col("value") / 100).alias("obj"))


def order_points(spark, sf_dir) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    days = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date"))
    return o.select(F.col("o_orderkey").alias("oid"), F.array(F.col("o_totalprice") / 500000, days / F.lit(2500.0)).alias("obj"))


def line_vectors(spark, sf_dir) -> DataFrame:
    """oid hashes the whole row: no smaller key is unique here. At 100 TB use a real key, since 64 bits would collide."""
    t = table(spark, sf_dir, "lineitem")
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    return t.select(F.xxhash64(*t.columns).alias("oid"), F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") * 10, F.col("l_tax") * 12.5, days / F.lit(2500.0)).alias("obj"))


def embed(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("oid"), F.transform("embedding", lambda x: x.cast("double")).alias("obj"))


def letters(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents").where(F.length("text") > 0)
    low = F.lower("text")
    return d.select(F.col("doc_id").alias("oid"), F.array(*[(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / F.length("text") for c in LETTERS]).alias("obj"))


def letters_of(df: DataFrame, oid: str, text: str) -> DataFrame:
    low = F.lower(text)
    return df.where(F.length(text) > 0).select(F.col(oid).alias("oid"), F.array(*[(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / F.length(text) for c in LETTERS]).alias("obj"))


def words(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    w = d.select(F.explode(F.split(F.lower("text"), r"\s+")).alias("obj")).where(F.col("obj").rlike("^[a-z]{1,34}$")).distinct()
    return w.select(F.xxhash64("obj").alias("oid"), "obj")


def urls(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "pages").where("url is not null").select(F.col("page_id").alias("oid"), F.col("url").alias("obj"))


def part_names(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "part").where("p_name is not null").select(F.col("p_partkey").alias("oid"), F.col("p_name").alias("obj"))


LOADERS = {"event_points": event_points, "order_points": order_points, "line_vectors": line_vectors, "embed_l2": embed, "embed_l1": embed, "letters_l1": letters, "words": words, "urls": urls, "part_names": part_names}
SETS = {
    "event_points": ObjectSet("event_points", metrics.l2(), 2, 0.05, ()),
    "order_points": ObjectSet("order_points", metrics.l2(), 2, 0.05, ()),
    "line_vectors": ObjectSet("line_vectors", metrics.l2(), 5, 0.3, ()),
    "embed_l2": ObjectSet("embed_l2", metrics.l2(), 64, 1.17, ()),
    "embed_l1": ObjectSet("embed_l1", metrics.l1(), 64, 7.4, ()),
    "letters_l1": ObjectSet("letters_l1", metrics.l1(), 26, 0.045, ()),
    "words": ObjectSet("words", metrics.edit(), None, 2.0, ()),
    "urls": ObjectSet("urls", metrics.edit(), None, 3.0, ()),
    "part_names": ObjectSet("part_names", metrics.edit(), None, 3.0, ()),
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """[oid long, obj]: `obj` is array<double> or string."""
    return LOADERS[name](spark, sf_dir).select(F.col("oid").cast("long").alias("oid"), "obj")


def frozen_queries(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """[qid, q]: every object whose id is divisible by 50; of words those whose md5 is, since they have no id; of lines those of such orders."""
    s = load(spark, sf_dir, name)
    if name == "words":
        s = s.where(F.conv(F.substring(F.md5("obj"), 1, 7), 16, 10).cast("long") % 50 == 0)
    elif name == "line_vectors":
        t = table(spark, sf_dir, "lineitem").where("l_orderkey % 50 = 0")
        s = s.join(t.select(F.xxhash64(*t.columns).alias("k_")), F.col("oid") == F.col("k_"), "left_semi")
    else:
        s = s.where("oid % 50 = 0")
    return s.select(F.col("oid").alias("qid"), F.col("obj").alias("q"))


def rejected(objects: DataFrame, m: metrics.Metric, dim: int | None) -> DataFrame:
    """(reason, n): objects that cannot take part, and why."""
    return objects.select(unfit(m, dim).alias("reason")).where("reason is not null").groupBy("reason").agg(F.count("*").alias("n"))


def accepted(objects: DataFrame, m: metrics.Metric, dim: int | None) -> DataFrame:
    return objects.where(unfit(m, dim).isNull()).select("oid", "obj")


def unfit(m: metrics.Metric, dim: int | None) -> Column:
    """Why a row [oid, obj] cannot take part; null if it can."""
    o = F.col("obj")
    if m.kind == "string":
        return F.when(o.isNull() | F.col("oid").isNull(), "null")
    bad = F.exists(o, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    out = F.when(o.isNull() | F.col("oid").isNull(), "null").when(bad, "not finite")
    return out.when(F.size(o) != dim, "wrong length") if dim else out
