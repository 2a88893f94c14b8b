"""A versioned sketch store: Parquet by bucket of set_id, each bucket's current version named by a small pointer table."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import FAULTS, RESERVE


class SketchStore:
    """Buckets that a batch touches are written anew under the batch id; others stay. The pointer (bucket, batch_id) is written last and names
    the version to read, so a batch that stopped half-way is as if it had not begun."""

    def __init__(self, spark: SparkSession, path: str, buckets: int = 64, files: int = 4):
        self.spark, self.path, self.buckets, self.files = spark, path.rstrip("/"), buckets, files

    @staticmethod
    def buckets_for(sets: int, words: int, bytes_each: int = 256 << 20) -> int:
        """Buckets so that one holds about ``bytes_each`` of sketches of ``words`` 8-byte words: choose it when a store is laid out."""
        return max(1, -(-sets * words * 8 // bytes_each))

    def bucket(self, set_id):
        return F.pmod(F.xxhash64(set_id), F.lit(self.buckets)).cast("int")

    def _exists(self, path: str) -> bool:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p)

    def _versions(self) -> list[int]:
        root = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/pointer")
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(root)]
        return sorted(int(n.split("=")[1]) for n in names if n.startswith("v=") and self._exists(f"{self.path}/pointer/{n}/_SUCCESS"))

    def committed(self, batch_id: int) -> bool:
        return self._exists(f"{self.path}/pointer/v={batch_id}/_SUCCESS")

    def _pointer(self) -> dict[int, int]:
        """bucket -> version; as many rows as buckets."""
        done = self._versions()
        if not done:
            return {}
        return {r["bucket"]: r["version"] for r in self.spark.read.schema("bucket int, version long").parquet(f"{self.path}/pointer/v={done[-1]}").collect()}

    def _read(self, pointer: dict[int, int]) -> DataFrame:
        if not pointer:
            return self.spark.createDataFrame([], RESERVE)
        paths = [f"{self.path}/data/v={v}/bucket={b}" for b, v in pointer.items()]
        return self.spark.read.schema(RESERVE).parquet(*[p for p in paths if self._exists(p)] or [f"{self.path}/empty"])

    def read(self) -> DataFrame:
        return self._read(self._pointer())

    def read_touched(self, updates: DataFrame) -> DataFrame:
        """Sketches in the buckets that the updates touch: other buckets' files are not opened."""
        touched = {r[0] for r in updates.select(self.bucket(F.col("set_id"))).distinct().collect()}  # as many as buckets
        self._touched = touched
        return self._read({b: v for b, v in self._pointer().items() if b in touched})

    def commit(self, sketch: DataFrame | None, faults: DataFrame | None, batch_id: int) -> None:
        pointer = self._pointer()
        if sketch is not None:
            # A bucket's sets are spread over ``files`` tasks and files, so a large bucket is no single task's load.
            spread = F.pmod(F.xxhash64("set_id", F.lit(1)), F.lit(self.files))
            rows = sketch.withColumn("bucket", self.bucket(F.col("set_id"))).repartition(F.col("bucket"), spread)
            rows.write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/data/v={batch_id}")
            pointer |= {b: batch_id for b in self._touched}
            pointer = {b: v for b, v in pointer.items() if self._exists(f"{self.path}/data/v={v}/bucket={b}")}
        if faults is not None:
            faults.withColumn("batch_id", F.lit(batch_id)).write.mode("overwrite").parquet(f"{self.path}/faults/v={batch_id}")
        rows = self.spark.createDataFrame([(b, v) for b, v in pointer.items()], "bucket int, version long")
        rows.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/pointer/v={batch_id}")

    def vacuum(self, keep: int = 2) -> None:
        """Delete sketches that none of the last ``keep`` pointers names, and older pointers; fault logs stay. To be called while no
        batch runs."""
        done = self._versions()
        named: set[tuple[int, int]] = set()
        for v in done[-keep:]:
            rows = self.spark.read.schema("bucket int, version long").parquet(f"{self.path}/pointer/v={v}").collect()
            named |= {(r["version"], r["bucket"]) for r in rows}
        path = self.spark._jvm.org.apache.hadoop.fs.Path
        root = path(f"{self.path}/data")
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        for version in fs.listStatus(root) if fs.exists(root) else []:
            name = version.getPath().getName()
            if not name.startswith("v=") or int(name[2:]) > (done[-1] if done else -1):
                continue  # not committed yet
            buckets = [s.getPath().getName() for s in fs.listStatus(version.getPath())]
            for bucket in buckets:
                if bucket.startswith("bucket=") and (int(name[2:]), int(bucket[7:])) not in named:
                    fs.delete(path(f"{self.path}/data/{name}/{bucket}"), True)
        for v in done[:-keep]:
            fs.delete(path(f"{self.path}/pointer/v={v}"), True)

    def faults(self) -> DataFrame:
        # Every batch up to the last pointer is committed: batches are written in order.
        last = self._versions()[-1:]
        root = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/faults")
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        names = [s.getPath().getName() for s in fs.listStatus(root)] if last and fs.exists(root) else []
        kept = [f"{self.path}/faults/{n}" for n in names if n.startswith("v=") and int(n[2:]) <= last[0] and self._exists(f"{self.path}/faults/{n}/_SUCCESS")]
        return self.spark.read.schema(FAULTS).parquet(*kept) if kept else self.spark.createDataFrame([], FAULTS)


def written(df: DataFrame, name: str = "rows") -> DataFrame:
    """``df`` written once as Parquet in the folder that the cluster names in ``spark.checkpoint.dir`` and read back, for what a query reads
    more than once. Where none is named, a cluster uses its warehouse, one machine a temporary folder."""
    spark = df.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        made = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = made.get() if made.isDefined() else None
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"
        else:
            root = "file://" + tempfile.mkdtemp(prefix="setstream-")
    path = f"{root.rstrip('/')}/setstream-core/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int = 64, key: str = "set_id") -> None:
    """A table bucketed and sorted by key, so that later joins on it need no exchange on this side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
