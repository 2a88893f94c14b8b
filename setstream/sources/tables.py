"""Readers of the given tables, of update streams and of other formats; narrow columns only."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import EVENTS, UPDATES


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_updates(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Update triples in Parquet, JSON lines or CSV with the fixed schema."""
    reader = spark.read.schema(UPDATES)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def stream_updates(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(UPDATES).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_updates(spark: SparkSession, rows_per_second: int = 1000, sets: int = 100, universe: int = 10_000) -> DataFrame:
    """Endless synthetic updates from the rate source; one in four is a deletion."""
    x = F.xxhash64("value")
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    op = F.when(F.pmod(F.xxhash64("value", F.lit(1)), F.lit(4)) == 0, -1).otherwise(1)
    return rows.select(F.col("value").alias("seq"), F.pmod(x, F.lit(sets)).alias("set_id"), F.pmod(F.xxhash64("value", F.lit(2)), F.lit(universe)).alias("element"), op.alias("op"), F.col("timestamp").alias("ts"))
