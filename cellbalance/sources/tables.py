"""Readers and writers: Parquet tables, traces as CSV or JSON, streams of files, decision logs and cut vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import SCHEMAS


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def trace_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMAS["trace"]).option("header", True).csv(path)


def trace_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMAS["trace"]).json(path)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a stream, with a zoned timestamp: watermarks take no zone-less one."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", 1)
    return raw.parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def write_cuts(cuts: DataFrame, path: str, version: int) -> None:
    """Append one version of a cut vector to a log of versions."""
    cuts.withColumn("version", F.lit(version)).write.mode("append").partitionBy("version").parquet(path)


def read_cuts(spark: SparkSession, path: str, version: int | None = None) -> DataFrame:
    cuts = spark.read.schema("k int, b long, version int").parquet(path)
    return cuts if version is None else cuts.filter(F.col("version") == version).select("k", "b")


def write_migrated(df: DataFrame, path: str) -> None:
    """Cells or particles, partitioned by slot: a later rebalancing rewrites only the slots that change."""
    df.write.mode("overwrite").partitionBy("slot").parquet(path)


def write_decisions(decisions: DataFrame, path: str) -> None:
    decisions.write.mode("append").partitionBy("run_id").parquet(path)
