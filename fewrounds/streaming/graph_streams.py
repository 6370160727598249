"""Streams: windowed degrees and sketches, incremental components and forests, runs, joins, late rows."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..operators.components import as_links, canonical_labels, complete_partition
from ..operators.graphs import canonical_edges
from ..plans.spool import cut, folder
from ..sources.tables import stream_table


def watermarked(events: DataFrame, delay: str = "1 hour", ts: str = "ts") -> DataFrame:
    return events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def windowed_degrees(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", gap: str = "1 hour") -> DataFrame:
    """Events a user and window; kind: tumbling, sliding or session."""
    w = F.window("ts", size) if kind == "tumbling" else F.window("ts", size, slide) if kind == "sliding" else F.session_window("ts", gap)
    out = events.groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("d"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "d")


def windowed_sketch(events: DataFrame, size: str = "1 day") -> DataFrame:
    """XOR of the event ids of a window."""
    return events.groupBy(F.window("ts", size).alias("w")).agg(F.bit_xor("event_id").alias("x"), F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "x", "n")


def drained(df: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Runs a stream over all there is and gives its result as a table in the shared folder.  ``complete``: each batch
    replaces the result; ``update``: the last row of each of ``keys`` counts.  Nothing passes through the driver."""
    spark: SparkSession = df.sparkSession
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")

    def store(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    q = df.writeStream.foreachBatch(store).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    kind = StructType([*df.schema.fields, StructField("batch", LongType())])
    rows = spark.read.schema(kind).parquet(f"{base}/out")
    if mode == "complete":
        return rows.join(F.broadcast(rows.agg(F.max("batch").alias("batch"))), "batch").drop("batch")
    rest = [c for c in df.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("r")).select(*keys, "r.*").select(*df.columns)


class IncrementalForest:
    """A spanning forest that takes batches of edges: the new forest is that of the old one and the batch.  A version a
    batch id, so a repeated batch changes nothing, and a restart goes on from the last whole version in the folder."""

    def __init__(self, spark: SparkSession, root: str | None = None, weighted: bool = False):
        self.spark, self.weighted = spark, weighted
        self.root = root or f"{folder(spark)}/forest-{uuid.uuid4().hex}"
        self.done = self._last()

    def _last(self) -> int:
        context = self.spark.sparkContext
        at = context._jvm.org.apache.hadoop.fs.Path(self.root)
        fs = at.getFileSystem(context._jsc.hadoopConfiguration())
        if not fs.exists(at):
            return -1
        names = [s.getPath().getName() for s in fs.listStatus(at)]
        whole = [int(n[1:]) for n in names if n.startswith("v") and fs.exists(context._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{n}/_SUCCESS"))]
        return max(whole, default=-1)

    def path(self, version: int) -> str:
        return f"{self.root}/v{version}"

    def current(self) -> DataFrame:
        kind = "src long, dst long" + (", weight double" if self.weighted else "")
        return self.spark.read.schema(kind).parquet(self.path(self.done)) if self.done >= 0 else self.spark.createDataFrame([], kind)

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        new = canonical_edges(self.current().unionByName(canonical_edges(batch, weight="weight" if self.weighted else None)), weight="weight" if self.weighted else None)
        new = cut(new)
        _, forest = complete_partition(as_links(new), weighted=self.weighted)
        new.join(forest, ["src", "dst"], "left_semi").write.mode("overwrite").parquet(self.path(batch_id))
        self.done = batch_id

    def labels(self, vertices: DataFrame) -> DataFrame:
        found, _ = complete_partition(as_links(self.current()))
        return canonical_labels(vertices, found)


def incremental(stream: DataFrame, weighted: bool = False, root: str | None = None) -> IncrementalForest:
    """Drains a stream of edges into a forest."""
    keeper = IncrementalForest(stream.sparkSession, root, weighted)
    state = f"{keeper.root}-state"
    q = stream.writeStream.foreachBatch(keeper.absorb).option("checkpointLocation", state).trigger(availableNow=True).start()
    q.awaitTermination()
    return keeper


def user_runs(events: DataFrame, gap_seconds: int = 3600, forget_seconds: int = 30 * 86400) -> DataFrame:
    """user_id, runs, events by keyed state: a run ends when the user is silent for longer than the gap.  A user whom the
    watermark has left behind by ``forget_seconds`` is forgotten; the counts sent last stand."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        runs, n, last = state.get if state.exists else (0, 0, None)
        for t in sorted(t for f in frames for t in f["us"].tolist()):
            runs += last is None or t - last > gap_seconds * 1_000_000
            n, last = n + 1, t if last is None else max(t, last)
        state.update((runs, n, last))
        state.setTimeoutTimestamp(max(last // 1000, state.getCurrentWatermarkMs()) + forget_seconds * 1000)
        yield pd.DataFrame({"user_id": [key[0]], "runs": [runs], "events": [n]})

    keyed = events.select("user_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    return keyed.groupBy("user_id").applyInPandasWithState(step, "user_id long, runs long, events long", "runs long, n long, last long", "update", "EventTimeTimeout")


def interval_stream_join(events: DataFrame, first: str, second: str, seconds: int) -> DataFrame:
    """A user's event of one type followed within some seconds by one of another type."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = events.where(F.col("event_type") == second).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    return a.join(b, F.expr(f"a_user = b_user AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {seconds} SECONDS")).select("a_id", "b_id", F.col("a_user").alias("user_id"))


def dedupe_stream(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def late_rows(query) -> int:
    """Rows that a finished query's watermark has dropped."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def late_report(parts: list[DataFrame], path: str, size: str = "1 hour", delay: str = "1 hour") -> tuple[int, int]:
    """Rows dropped by the watermark and rows counted, when the parts (event_id, user_id, ts) arrive file by file."""
    spark = parts[0].sparkSession
    for k, part in enumerate(parts):
        part.coalesce(1).write.parquet(f"{path}/in/part={k}")
        stream = watermarked(spark.readStream.schema(parts[0].schema).option("recursiveFileLookup", "true").parquet(f"{path}/in"), delay)
        counts = stream.groupBy(F.window("ts", size).alias("w")).agg(F.count(F.lit(1)).alias("n"))

        def store(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

        q = counts.writeStream.foreachBatch(store).option("checkpointLocation", f"{path}/state").outputMode("update").trigger(availableNow=True).start()
        q.awaitTermination()
        dropped = late_rows(q)
    rows = spark.read.parquet(f"{path}/out").groupBy("w").agg(F.max_by("n", "batch").alias("n"))
    return dropped, rows.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def events_stream(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    return watermarked(stream_table(spark, sf_dir, "events"), delay)
