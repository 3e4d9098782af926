"""Scans and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from critgraph import schemas


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_text_trace(spark: SparkSession, path: str, form: str = "csv") -> DataFrame:
    """A trace from CSV with a header, or JSON lines, by the declared schema (never inferred)."""
    reader = spark.read.schema(schemas.TRACE)
    return reader.json(path) if form == "json" else reader.option("header", True).csv(path)


def write_trace(trace: DataFrame, path: str, buckets: int = 64) -> None:
    """A trace as Parquet, laid out by program and range of seq and sorted, so that slices prune row groups."""
    trace.repartitionByRange(buckets, "program_id", "seq").sortWithinPartitions("program_id", "seq").write.parquet(path)


def write_bucketed(trace: DataFrame, name: str, buckets: int = 64) -> None:
    """A trace as a table bucketed by program and sorted: later joins and sweeps by program need no shuffle."""
    trace.write.bucketBy(buckets, "program_id").sortBy("program_id", "seq").mode("overwrite").saveAsTable(name)


def write_paths(path_rows: DataFrame, path: str) -> None:
    path_rows.write.json(path)
