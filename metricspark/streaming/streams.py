"""Streams over `events`: continuous inserts, standing range queries, windows, late and repeated rows, running top-k."""
from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.metrics import Metric, within
from ..operators import search, updates
from ..operators.index import MetricIndex
from ..operators.sizes import sized
from ..sources.tables import MONTH_US, ORIGIN_US, micros, new_path

EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    """`events` as a stream of [event_id, ts timestamp, user_id, event_type, value, oid, obj]; event time must be a zoned timestamp."""
    raw = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/events.parquet*")
    return with_points(raw.withColumn("ts", F.col("ts").cast("timestamp")))


def with_points(events: DataFrame) -> DataFrame:
    return events.withColumn("oid", F.col("event_id")).withColumn("obj", F.array((micros(F.col("ts")) - ORIGIN_US) / F.lit(MONTH_US), F.col("value") / 100))


def run_to_end(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Process what is there and stop; the rows as a table. Appended rows go to files in the shared folder; only the bounded states of
    other modes are held in the driver's memory."""
    spark = stream.sparkSession
    if mode == "append":
        path = new_path(spark, f"sink-{name}")
        q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", new_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", new_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


FOLD = 16  # batches kept as additions before the index is written afresh


def continuous_inserts(stream: DataFrame, index: MetricIndex, folder: str | None = None) -> MetricIndex:
    """Feed an index batch by batch, durably under `folder` (a new one in the shared folder if not given).

    Every batch's objects are written under their batch number, which overwrites what a failed attempt left, and the stream's checkpoint
    lies beside them; so a restart with the same folder goes on where the stream stopped, and no batch counts twice. The
    index returned is the given one with all batches inserted; every FOLD batches they are inserted at one go, so plans stay shallow.
    """
    spark = stream.sparkSession
    folder = folder or new_path(spark, "stream-inserts")
    obj = stream.schema["obj"].dataType.simpleString()

    def step(batch: DataFrame, number: int) -> None:
        batch.select("oid", "obj").write.mode("overwrite").parquet(f"{folder}/objects/batch={number}")

    q = stream.select("oid", "obj").writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return replay(spark, index, folder, obj)


def replay(spark: SparkSession, index: MetricIndex, folder: str, obj: str) -> MetricIndex:
    """`index` with the batches under `folder`, FOLD of them at a time."""
    root = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/objects")
    store = root.getFileSystem(spark._jsc.hadoopConfiguration())
    if not store.exists(root):
        return index
    numbers = sorted(int(x.getPath().getName().partition("=")[2]) for x in store.listStatus(root) if x.isDirectory())
    schema = f"oid long, obj {obj}"
    for at in range(0, len(numbers), FOLD):
        index = updates.insert(index, spark.read.schema(schema).parquet(*[f"{folder}/objects/batch={n}" for n in numbers[at : at + FOLD]]))
    return index


def stream_range(stream_queries: DataFrame, index: MetricIndex, r: float) -> DataFrame:
    """A stream of [qid, q] against the tables of a still index: stream-static joins."""
    return search.range_query(index, stream_queries, r)


def standing_queries(stream: DataFrame, queries: DataFrame, metric: Metric, r: float, dim: int | None = None) -> DataFrame:
    """[qid, oid, dist]: arriving objects against registered queries."""
    q = sized(search.with_radius(queries, r))
    d, ok = within(metric, F.col("q"), F.col("obj"), F.col("r"), dim)
    return stream.crossJoin(q).withColumn("dist", d).where(ok if metric.name == "edit" else F.col("dist") <= F.col("r")).select("qid", "oid", "dist")


def tumbling(stream: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    return _window(stream.withWatermark("ts", late), F.window("ts", length))


def sliding(stream: DataFrame, length: str = "1 day", step: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return _window(stream.withWatermark("ts", late), F.window("ts", length, step))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """[user_id, w_start, w_end, n]."""
    g = stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "n")


def _window(stream: DataFrame, w) -> DataFrame:
    g = stream.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("w.start").alias("w_start"), "event_type", "n", "total")


def deduplicated(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def late_rows(stream: DataFrame, name: str, late: str = "1 hour", length: str = "1 day") -> DataFrame:
    """[batch, n_input, n_late]: rows that came after the watermark had passed their window, as the state operators count them, batch by batch."""
    spark = stream.sparkSession
    q = tumbling(stream, length, late).writeStream.format("noop").outputMode("update").option("checkpointLocation", new_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    rows = [(p["batchId"], p["numInputRows"], sum(o["numRowsDroppedByWatermark"] for o in p["stateOperators"])) for p in map(dict, q.recentProgress)]
    return spark.createDataFrame([tuple(map(int, r)) for r in rows], "batch long, n_input long, n_late long")


def rate_points(spark: SparkSession, rows_per_second: int = 10) -> DataFrame:
    """[oid, ts, obj]: made-up planar points from the rate source, for load tests without input files."""
    r = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    unit = lambda seed: F.pmod(F.xxhash64("value", F.lit(seed)), F.lit(1 << 20)) / F.lit(float(1 << 20))
    return r.select(F.col("value").alias("oid"), F.col("timestamp").alias("ts"), F.array(unit(1), unit(2)).alias("obj"))


def purchases_after_clicks(stream: DataFrame, minutes: int = 60, near: float = 10.0, late: str = "1 hour") -> DataFrame:
    """Interval join of the stream with itself: purchases of a user within `minutes` of a click and near it in value."""
    c = stream.where("event_type = 'click'").withWatermark("ts", late).select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click"), F.col("value").alias("cv"))
    p = stream.where("event_type = 'purchase'").withWatermark("ts", late).select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"), F.col("event_id").alias("purchase"), F.col("value").alias("pv"))
    return c.join(p, F.expr(f"cu = pu and pt >= ct and pt <= ct + interval {minutes} minutes and abs(cv - pv) <= {near}")).select("click", "purchase")


class RunningTopK(StatefulProcessor):
    """Keeps the k nearest objects met so far of one query, in keyed state that expires."""

    def __init__(self, k: int, ttl_ms: int | None = None):
        self.k, self.ttl = k, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        schema = T.StructType([T.StructField("oids", T.ArrayType(T.LongType())), T.StructField("dists", T.ArrayType(T.DoubleType()))])
        self.best = handle.getValueState("best", schema, ttlDurationMs=self.ttl)

    def handleInputRows(self, key, rows, timerValues):
        have = self.best.get() if self.best.exists() else ([], [])
        items = list(zip(have[1], have[0]))
        for pdf in rows:
            items += list(zip(pdf["dist"].tolist(), pdf["oid"].tolist()))
        items = sorted(set(items))[: self.k]
        self.best.update(([i for _, i in items], [d for d, _ in items]))
        yield pd.DataFrame({"qid": [key[0]] * len(items), "rank": list(range(1, len(items) + 1)), "oid": [i for _, i in items], "dist": [d for d, _ in items]})

    def close(self) -> None:
        pass


def running_top_k(stream: DataFrame, queries: DataFrame, metric: Metric, k: int, dim: int | None = None, ttl_ms: int | None = None) -> DataFrame:
    """[qid, rank, oid, dist] after each batch. Needs the state store of RocksDB in the session."""
    pairs = stream.crossJoin(sized(queries)).withColumn("dist", metric.column(F.col("q"), F.col("obj"), dim)).select("qid", "oid", "dist")
    return pairs.groupBy("qid").transformWithStateInPandas(RunningTopK(k, ttl_ms), "qid long, rank int, oid long, dist double", "Update", "none")
