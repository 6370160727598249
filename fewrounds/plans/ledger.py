"""Costs in the message model: rounds, messages and loads of each step, counted from the data."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graphs import EdgeSet, symmetrize
from ..operators.sparsify import Split


def sparsify_ledger(g: EdgeSet, split: Split) -> DataFrame:
    """step, rounds, messages (seven communication steps whatever the size; 6 edges + 4 n at most), broadcasts (distinct
    payloads: what a vertex tells all others counts once) and lean (only what can't be known: a label that isn't the
    vertex's own, a component that is awake)."""
    m, n = g.edges.count(), g.n
    h1, h2 = split.hooks1.count(), split.hooks2.count()
    out = symmetrize(g.edges)
    told = out.join(split.labels1.where("comp <> vid").select(F.col("vid").alias("u")), "u").count()
    up = out.join(split.labels.where("awake").select(F.col("vid").alias("u")), "u").count()
    rows = [
        ("announce_degree", 1, 2 * m, n, 2 * m), ("stage1_choice", 1, h1, h1, h1), ("stage1_labels", 1, n, n, n), ("announce_labels", 1, 2 * m, n, told),
        ("stage2_choice", 1, h2, h2, h2), ("stage2_labels", 1, n, n, n), ("announce_awake", 1, 2 * m, n, up),
    ]
    return g.edges.sparkSession.createDataFrame(rows, "step string, rounds long, messages long, broadcasts long, lean long")


def contract_ledger(samples: DataFrame, leaders: DataFrame, messages: DataFrame, m: int) -> DataFrame:
    """step, rounds, messages, max_sent and max_received (of a node; a boss has the rows of its sample) of the four steps
    of the sample contraction."""
    per = lambda df, key: df.groupBy(key).agg(F.count(F.lit(1)).alias("k")).agg(F.coalesce(F.sum("k"), F.lit(0)).alias("messages"), F.coalesce(F.max("k"), F.lit(0)).alias("most"))

    def step(name: str, sent: DataFrame, received: DataFrame) -> DataFrame:
        return sent.select("messages", F.col("most").alias("max_sent")).join(received.select(F.col("most").alias("max_received"))).select(F.lit(name).alias("step"), F.lit(1).alias("rounds"), "messages", "max_sent", "max_received")

    flags = leaders.agg((F.count(F.lit(1)) * m).alias("messages"), F.count(F.lit(1)).alias("max_received")).select(F.lit("leader_flags").alias("step"), F.lit(1).alias("rounds"), "messages", F.lit(m).cast("long").alias("max_sent"), "max_received")
    pointing = messages.where("hop IS NOT NULL").agg(F.count_distinct("v").alias("messages")).select(F.lit("pointers").alias("step"), F.lit(1).alias("rounds"), "messages", F.lit(1).cast("long").alias("max_sent"), F.col("messages").alias("max_received"))
    return step("edges_to_bosses", per(samples, "src"), per(samples, "sample")).unionByName(flags).unionByName(step("replies", per(messages, "sample"), per(messages, "v"))).unionByName(pointing)


def measured(spark: SparkSession, work: Callable[[], object]) -> dict[str, int]:
    """What the engine did for some work: jobs, stages, stages that wrote a shuffle, shuffled bytes and tasks, as the
    session's own status store has them."""
    context = spark.sparkContext
    group = f"measured-{uuid.uuid4().hex}"
    context.setJobGroup(group, group)
    try:
        work()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    jobs = list(tracker.getJobIdsForGroup(group))
    stages = sorted({k for j in jobs if (info := tracker.getJobInfo(j)) for k in info.stageIds})
    ran = []
    for k in stages:
        try:
            ran.append(store.lastStageAttempt(k))
        except Exception:  # noqa: BLE001  a stage that was skipped has no attempt
            continue
    written = [s.shuffleWriteBytes() for s in ran]
    return {"jobs": len(jobs), "stages": sum(s.numCompleteTasks() > 0 for s in ran), "shuffles": sum(w > 0 for w in written), "shuffle_bytes": sum(written), "tasks": sum(s.numCompleteTasks() for s in ran)}


def nested_message_total(edges: DataFrame, count: int) -> DataFrame:
    """Messages that all instances' announcements take: twice the sum of their edges."""
    return edges.agg(F.sum((F.lit(count) - F.col("first_instance") + 1) * 2).cast("long").alias("messages"))
