"""Session helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Bytes of text that one numpy kernel call works on; longer Arrow batches are cut into runs of whole rows.
CHUNK_BYTES = 2 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` as the cluster names it.

    Where that is unset, a cluster gets a folder in its warehouse; only on one machine (tests) a local temporary
    folder is made and set.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        jvm = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = jvm.get() if jvm.isDefined() else None
    if not named and not spark.sparkContext.master.startswith("local"):
        named = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"
    if not named:
        named = "file://" + tempfile.mkdtemp(prefix="setstream-")
        spark.sparkContext.setCheckpointDir(named)
        spark.conf.set("spark.checkpoint.dir", named)
    return named


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage: write ``df`` once as Parquet under the shared folder and read it back.

    A lost executor then costs a re-read, not a recomputation; unlike ``checkpoint()`` the rows are computed once.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/setstream/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._setstream_path = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what ``materialise`` wrote for ``df``; to be called when nothing will read it again."""
    path = getattr(df, "_setstream_path", None)
    if path:
        spark = df.sparkSession
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def clean(spark: SparkSession) -> None:
    """Delete everything that operators have written to the shared folder; to be called when no result of theirs will be read."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/setstream")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def partitions(spark: SparkSession) -> int:
    """Shuffle partitions as the session sets them."""
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def sheltered(docs: DataFrame, *roles: str) -> DataFrame:
    """``docs`` with all columns but ``roles`` renamed out of the way of an operator's own names; see ``restored``."""
    return docs.toDF(*[c if c in roles else f"_kept{i}" for i, c in enumerate(docs.columns)])


def restored(found: DataFrame, docs: DataFrame, *roles: str) -> DataFrame:
    """The columns of ``docs``, with their names, out of what an operator made of its sheltered form."""
    return found.select(*sheltered(docs, *roles).columns).toDF(*docs.columns)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
