"""The given tables, edge lists in files, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges(spark: SparkSession, path: str, fmt: str, src: str, dst: str, weight: str | None = None, **options) -> DataFrame:
    """Edges in parquet, csv, json, orc or text (two numbers a line)."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"[\s,]+")
        raw = spark.read.text(path).where("trim(value) <> '' AND NOT startswith(value, '#')")
        return raw.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"), *([parts[2].cast("double").alias("weight")] if weight else []))
    kind = f"`{src}` BIGINT, `{dst}` BIGINT" + (f", `{weight}` DOUBLE" if weight else "")
    reader = spark.read.format(fmt).options(**options)
    df = reader.schema(kind).load(path) if fmt in ("csv", "json") else reader.load(path)
    return df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), *([F.col(weight).cast("double").alias("weight")] if weight else []))


def read_adjacency(spark: SparkSession, path: str, vid: str = "vid", neighbours: str = "neighbours") -> DataFrame:
    return spark.read.parquet(path).select(F.col(vid).alias("src"), F.explode(neighbours).alias("dst"))


def write_result(df: DataFrame, path: str, mode: str = "overwrite", partition_by: list[str] | None = None, bucket_by: tuple[int, str] | None = None, table: str | None = None) -> None:
    w = df.write.mode(mode)
    if partition_by:
        w = w.partitionBy(*partition_by)
    if bucket_by:
        w.bucketBy(*bucket_by).sortBy(bucket_by[1]).option("path", path).saveAsTable(table)
    else:
        w.parquet(path)


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for t in TABLES:
        read_table(spark, sf_dir, t).createOrReplaceTempView(t)


def stream_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a file stream."""
    schema = read_table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
