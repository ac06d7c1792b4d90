"""`spark.read.format("metric_index")`: an index's objects by slot, with filters on slot, bucket and pid pushed down."""
from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition

KEYS = ("slot", "bucket", "pid")


class MetricIndexSource(DataSource):
    """Options: path (a folder that Python on the executors can open), kind ("array<double>" or "string")."""

    @classmethod
    def name(cls) -> str:
        return "metric_index"

    def schema(self) -> str:
        return f"slot int, bucket int, pid bigint, lnode_id bigint, d_leaf double, oid bigint, obj {self.options.get('kind', 'array<double>')}"

    def reader(self, schema):
        return MetricIndexReader(self.options["path"])


class SlotPartition(InputPartition):
    def __init__(self, slot: int, folder: str):
        self.slot, self.folder = slot, folder


class MetricIndexReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.wanted = path, {}

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute[0] in KEYS:
                self.wanted[f.attribute[0]] = f.value
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path)
        found = [i.path for i in store.get_file_info(fs.FileSelector(f"{root}/objects/part=object")) if i.type == fs.FileType.Directory]
        slots = [(int(p.rpartition("slot=")[2]), p) for p in sorted(found)]
        return [SlotPartition(s, p) for s, p in slots if self.wanted.get("slot", s) == s]

    def read(self, partition):
        import pyarrow.compute as pc
        import pyarrow.dataset as ds
        from pyarrow import fs

        store = fs.FileSystem.from_uri(self.path)[0] if "://" in self.path else fs.LocalFileSystem()
        keep = None
        for c in ("bucket", "pid"):
            if c in self.wanted:
                e = pc.field(c) == self.wanted[c]
                keep = e if keep is None else keep & e
        for b in ds.dataset(partition.folder, format="parquet", filesystem=store).to_batches(columns=["bucket", "pid", "lnode_id", "d_leaf", "oid", "obj"], filter=keep):
            for r in b.to_pylist():
                yield (partition.slot, r["bucket"], r["pid"], r["lnode_id"], r["d_leaf"], r["oid"], r["obj"])


def register(spark: SparkSession) -> None:
    """Register the format; sources in Python get filters only where this runtime setting is on."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(MetricIndexSource)
