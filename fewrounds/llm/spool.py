"""Intermediate tables written to the shared folder, which cut lineage and outlive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The shared folder the cluster names; where none is set, one of our own, in local mode only."""
    context = spark.sparkContext
    base = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not base:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp()
        context.setCheckpointDir(base)
    return base.rstrip("/")


def kept(df: DataFrame) -> DataFrame:
    """The rows written as Parquet and read back."""
    path = f"{folder(df.sparkSession)}/kept-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame | None) -> None:
    """Deletes the files of a kept table that nothing reads any more."""
    if df is not None:
        jvm, context = df.sparkSession._jvm, df.sparkSession.sparkContext
        for name in {f.rsplit("/", 1)[0] for f in df.inputFiles() if "/kept-" in f}:
            path = jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def placed(df: DataFrame) -> DataFrame:
    """The rows checkpointed with their partitions and order as they are."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(folder(df.sparkSession))
    return df.checkpoint()
