"""Lineage cuts: tables in the shared folder that outlive lost executors."""

from __future__ import annotations

import tempfile
import threading
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_own = threading.local()  # the tables that this thread has written


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


def cut(df: DataFrame) -> DataFrame:
    """The rows written as Parquet and read back."""
    path = f"{folder(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made().append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def cut_and_count(df: DataFrame) -> tuple[DataFrame, int]:
    """The rows written and read back, and their number, which the writing job counts on its way."""
    seen = Observation()
    out = cut(df.observe(seen, F.count(F.lit(1)).alias("n")))
    return out, seen.get["n"]


def _made() -> list[str]:
    if not hasattr(_own, "made"):
        _own.made = []
    return _own.made


def mark() -> int:
    """A point in time for ``sweep``."""
    return len(_made())


def sweep(spark: SparkSession, since: int, *alive: DataFrame) -> None:
    """Deletes the tables that this thread has cut since a mark, but those that ``alive`` still read.  The engine drops
    shuffle files when the driver's memory of their stages is collected, so that is asked for too."""
    held = {part for df in alive for file in df.inputFiles() for part in file.split("/") if part.startswith("cut-")}
    context, rest = spark.sparkContext, []
    for path in _made()[since:]:
        if path.rsplit("/", 1)[1] in held:
            rest.append(path)
        else:
            at = context._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(context._jsc.hadoopConfiguration()).delete(at, True)
    _made()[since:] = rest
    context._jvm.System.gc()
