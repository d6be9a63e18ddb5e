"""Hypergraphs and results in files: edge lines, incidence files, literal lists, stored counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

INCIDENCE = "e long, v long"


def from_lists(spark: SparkSession, lists: list[list[int]]) -> DataFrame:
    """(e, v) rows of literal edges; e counts from 1."""
    return spark.createDataFrame([(k, v) for k, members in enumerate(lists, 1) for v in members], INCIDENCE)


def read_edge_lines(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """(e, v) rows of a text with one edge in a line.  e hashes the line: equal lines are equal edges anyway."""
    lines = spark.read.text(path).where(F.length(F.trim("value")) > 0)
    return lines.select(F.xxhash64("value").alias("e"), F.explode(F.split(F.trim("value"), sep)).alias("v")).select("e", F.col("v").cast("long").alias("v")).distinct()


def write_edge_lines(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.select(F.array_join(F.transform("members", lambda m: m.cast("string")), sep).alias("value")).write.mode("overwrite").text(path)


def read_incidence(spark: SparkSession, path: str, fmt: str, schema: str = INCIDENCE) -> DataFrame:
    """(e, v) rows stored as csv, json, orc or parquet; the schema is stated, never inferred."""
    return spark.read.format(fmt).schema(schema).load(path)


def write_rows(df: DataFrame, path: str | None, fmt: str = "parquet") -> None:
    """A result to any format; ``noop`` runs the plan and keeps nothing (for timing)."""
    writer = df.write.format(fmt).mode("overwrite")
    writer.save() if fmt == "noop" else writer.save(path)


def write_counts(counts: DataFrame, path: str | None, fmt: str = "parquet") -> None:
    """Counts (pattern, cnt) as one small file in the order of the patterns."""
    write_rows(counts.select(F.col("pattern").cast("int").alias("pattern"), F.col("cnt").cast("long").alias("cnt")).coalesce(1).sortWithinPartitions("pattern"), path, fmt)
