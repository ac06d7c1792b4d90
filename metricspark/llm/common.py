"""Shared pieces of the corpus operators: table access, tables written to the shared folder, hold-out folds."""
from __future__ import annotations

import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see; only sessions that name none (tests) get a local one."""
    return spark.conf.get("spark.checkpoint.dir", None) or "/tmp/checkpoints"


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def written(df: DataFrame, tag: str) -> DataFrame:
    """Write `df` as Parquet to the shared folder and read it back, which cuts its lineage.

    The table survives lost executors and goes when the JVM ends; `discard` removes it earlier. Nothing reads the shuffles behind
    it again, so they go at the end of the write and not when the driver's garbage happens to be collected.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/metricspark/{tag}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def discard(*frames: DataFrame) -> None:
    """Remove tables made by `written` that nothing reads any more."""
    for df in frames:
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._written_at)
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def fold(doc_id: Column, n: int) -> Column:
    return F.crc32(doc_id.cast("string")) % n


BATCH_ROWS = 2000
BATCH_BYTES = 64 << 20


def small_batches(spark: SparkSession) -> None:
    """At most BATCH_ROWS texts and about BATCH_BYTES in an Arrow batch (runtime settings): both sides of the pipe hold whole batches."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    limit = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch")
    if not limit.isdigit() or int(limit) > BATCH_BYTES:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def lean(fn):
    """`fn` for `mapInArrow`, with memory that Arrow's pool has free given back after each batch: workers live through all stages, and the pool would keep it."""

    def run(batches):
        def each():
            for batch in batches:
                yield batch
                del batch
                pa.default_memory_pool().release_unused()

        yield from fn(each())
        pa.default_memory_pool().release_unused()

    return run


def text_batches(df: DataFrame, fn, schema: str) -> DataFrame:
    """`mapInArrow` over (doc_id long, text string) with null texts read as empty ones."""
    small_batches(df.sparkSession)
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).mapInArrow(fn, schema)


def labelled_documents(docs: DataFrame, labels: DataFrame, target: str, folds: int, out_fold: int, per_class: dict[int, int]) -> DataFrame:
    """(doc_id, text, y), written: at most `per_class[c]` documents of each class, chosen by hash from rows outside the held-out fold.

    This is the only place where a classifier sees fewer rows than there are; the bounds are parameters of the
    callers. Texts are whole, of any length. Of rows of one doc_id the least text stands; of several labels the greatest.
    """
    known = labels.where(F.col(target).isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(target).cast("int").alias("y")).where(fold(F.col("doc_id"), folds) != out_fold)
    known = known.groupBy("doc_id").agg(F.max("y").alias("y"))
    picked = None
    for y, n in per_class.items():
        part = known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
        picked = part if picked is None else picked.unionByName(part)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # `picked` has at most sum(per_class) rows of two numbers
    return written(texts.join(F.broadcast(picked), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y")), "labelled")
