"""Readers of edge lists and writers of results."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifjoin.sources.graphs import EDGE, as_edges


def read_edges(spark: SparkSession, path: str, format: str = "parquet", src: str = "src", dst: str = "dst", **options) -> DataFrame:
    """Edges from parquet, orc, json, csv, a table, or text lines of two numbers (``#`` starts a comment)."""
    if format == "text":
        parts = F.split(F.trim("value"), r"[\s,]+")
        lines = spark.read.text(path).filter(~F.col("value").startswith("#") & (F.trim("value") != ""))
        return as_edges(lines.select(F.expr("try_cast(split(trim(value), '[\\\\s,]+')[0] as bigint)").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst")), "src", "dst")
    if format == "table":
        return as_edges(spark.table(path), src, dst)
    reader = spark.read.options(**options)
    if format in ("csv", "json"):
        reader = reader.schema(f"`{src}` long, `{dst}` long")
    return as_edges(reader.format(format).load(path), src, dst)


def edges_of(spark: SparkSession, pairs: Iterable[Sequence[int]]) -> DataFrame:
    """Rows in memory as edges."""
    return spark.createDataFrame([(int(a), int(b)) for a, b in pairs], EDGE)


def read_update_stream(spark: SparkSession, path: str, max_files: int = 1) -> DataFrame:
    """A file stream of signed edges ``(ts, src, dst, w)``."""
    return spark.readStream.schema("ts timestamp, src long, dst long, w int").option("maxFilesPerTrigger", max_files).parquet(path)


def rate_edges(spark: SparkSession, rows_per_second: int = 1000, vertices: int = 10_000) -> DataFrame:
    """An endless stream of pseudorandom edges, for soak tests."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    ends = [F.pmod(F.xxhash64("value", F.lit(k)), F.lit(vertices)).alias(n) for k, n in enumerate(("src", "dst"))]
    return rows.select(F.col("timestamp").alias("ts"), *ends, F.lit(1).alias("w")).filter("src <> dst")


def write_matches(df: DataFrame, path: str, format: str = "parquet", by: Sequence[str] = (), mode: str = "overwrite") -> None:
    """Matches or signed changes to files; ``noop`` runs the plan and keeps nothing."""
    writer = df.write.mode(mode).format(format)
    if format == "noop":
        writer.save()
        return
    (writer.partitionBy(*by) if by else writer).save(path)
