"""Relational building blocks: joins, aggregations, windows, ranks and sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

BROADCAST_BYTES = 64 << 20


def placed(df: DataFrame) -> DataFrame:
    """Checkpointed with partitions and order as they are."""
    from ..plans.spool import folder

    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(folder(df.sparkSession))
    return df.checkpoint()


def global_rank(df: DataFrame, order: list[str | Column], name: str = "rank") -> DataFrame:
    """Rank from 1 over all rows: range partitions, places in them, and an offset a partition (one number each)."""
    ranged = placed(df.repartitionByRange(*order).sortWithinPartitions(*order)).withColumn("_id", F.monotonically_increasing_id())
    part = F.shiftright("_id", 33)
    counts = {r["p"]: r["n"] for r in ranged.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}
    offset, total = {}, 0
    for p in sorted(counts):
        offset[p], total = total, total + counts[p]
    if not offset:
        return ranged.select(*df.columns, F.lit(1).cast("long").alias(name))
    starts = F.create_map(*(F.lit(x) for kv in offset.items() for x in kv))
    return ranged.select(*df.columns, (F.element_at(starts, part).cast("long") + F.col("_id").bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias(name))


def prefix_sum(df: DataFrame, order: list[str], value: str, name: str) -> DataFrame:
    """Running sum over all rows in order: sums within range partitions plus an offset a partition."""
    ranged = placed(df.repartitionByRange(*order).sortWithinPartitions(*order)).withColumn("_p", F.spark_partition_id())
    sums = {r["_p"]: r["s"] for r in ranged.groupBy("_p").agg(F.sum(value).alias("s")).collect()}
    offset, total = {}, 0
    for p in sorted(sums):
        offset[p], total = total, total + (sums[p] or 0)
    if not offset:
        return ranged.select(*df.columns, F.lit(0).cast("long").alias(name))
    starts = F.create_map(*(F.lit(x) for kv in offset.items() for x in kv))
    inner = F.sum(value).over(W.partitionBy("_p").orderBy(*order).rowsBetween(W.unboundedPreceding, 0))
    return ranged.select(*df.columns, (F.element_at(starts, F.col("_p")) + inner).cast("long").alias(name))


def checked_broadcast_join(large: DataFrame, small: DataFrame, on, how: str = "inner", most: int = BROADCAST_BYTES) -> DataFrame:
    """Broadcasts the small side if its planned size is within bounds; else a merge join that can split skew."""
    size = int(str(small._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return large.join(F.broadcast(small) if size <= most else small.hint("merge"), on, how)


def shuffle_hash_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b.hint("shuffle_hash"), on, how)


def sort_merge_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b.hint("merge"), on, how)


def range_join(points: DataFrame, point: str, ranges: DataFrame, low: str, high: str, width: int) -> DataFrame:
    """Rows with low <= point <= high, by bins of ``width``: each range is dealt to the bins it meets."""
    bins = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.withColumn("_bin", F.floor(F.col(point) / width)).join(bins, "_bin").where(f"{point} BETWEEN {low} AND {high}").drop("_bin")


def interval_join(a: DataFrame, b: DataFrame, ts_a: str, ts_b: str, seconds: int, by: list[str]) -> DataFrame:
    """Pairs of equal keys with 0 <= ts_b - ts_a <= seconds, by time buckets."""
    at = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    step = seconds * 1_000_000
    left = a.withColumn("_k", F.explode(F.array(F.floor(at(ts_a) / step), F.floor(at(ts_a) / step) + 1)))
    return left.join(b.withColumn("_k", F.floor(at(ts_b) / step)), [*by, "_k"]).where(at(ts_b) - at(ts_a) >= 0).where(at(ts_b) - at(ts_a) <= step).drop("_k")


def asof_join(left: DataFrame, right: DataFrame, ts: str, by: list[str], value: str, tie: str) -> DataFrame:
    """The latest value of right at or before each left row, by one sort a key."""
    both = left.withColumns({"_side": F.lit(1), value: F.lit(None)}).unionByName(right.withColumn("_side", F.lit(0)), allowMissingColumns=True)
    w = W.partitionBy(*by).orderBy(ts, "_side", tie).rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def salted_join(hot: DataFrame, cold: DataFrame, key: str, salts: int) -> DataFrame:
    """Each hot key spread over ``salts`` partitions; the cold side is repeated for each."""
    a = hot.withColumn("_salt", F.pmod(F.xxhash64(*hot.columns), F.lit(salts)).cast("int"))
    b = cold.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")


def two_level_agg(df: DataFrame, key: str, value: str, salts: int) -> DataFrame:
    part = df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_salt")).agg(F.sum(value).alias("s"), F.count(F.lit(1)).alias("n"))
    return part.groupBy(key).agg(F.sum("s").alias("total"), F.sum("n").alias("n"))


def best_by(df: DataFrame, key: str, order: list[str], largest: bool = True) -> DataFrame:
    pick = (F.max if largest else F.min)(F.struct(*order))
    return df.groupBy(key).agg(pick.alias("b")).select(key, "b.*")


def top_k_per_group(df: DataFrame, by: list[str], order: list[Column | str], k: int) -> DataFrame:
    return df.withColumn("_r", F.row_number().over(W.partitionBy(*by).orderBy(*order))).where(F.col("_r") <= k).withColumnRenamed("_r", "rank")


def sessionize(df: DataFrame, by: list[str], ts: str, tie: str, gap_seconds: int) -> DataFrame:
    """A session number a row: a new one after a gap of more than ``gap_seconds``."""
    w = W.partitionBy(*by).orderBy(ts, tie)
    at = F.unix_micros(F.col(ts).cast("timestamp"))
    new = F.when(at - F.lag(at).over(w) <= gap_seconds * 1_000_000, 0).otherwise(1)
    return df.withColumn("_new", new).withColumn("session", F.sum("_new").over(w.rowsBetween(W.unboundedPreceding, 0))).drop("_new")
