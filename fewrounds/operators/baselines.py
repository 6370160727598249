"""Methods to compare with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spool import cut, mark, sweep
from .components import ComponentResult, as_links, canonical_labels, complete_partition
from .graphs import EdgeSet, symmetrize
from .msf import squared_growth_msf
from .sketches import finish_by_sketches


def star_contraction_cc(g: EdgeSet) -> ComponentResult:
    labels, forest = complete_partition(as_links(g.edges), "distributed")
    return ComponentResult(canonical_labels(g.vertices, labels), forest)


def hook_and_contract_cc(g: EdgeSet) -> ComponentResult:
    """Each component takes its least outgoing edge; all weights alike."""
    labels, forest = complete_partition(as_links(g.edges.select("src", "dst", F.lit(0.0).alias("weight"))), "distributed", weighted=True)
    return ComponentResult(canonical_labels(g.vertices, labels), forest)


def exact_local_cc(g: EdgeSet) -> ComponentResult:
    labels, forest = complete_partition(as_links(g.edges), "task")
    return ComponentResult(canonical_labels(g.vertices, labels), forest)


def sketch_only_cc(g: EdgeSet, log: list | None = None) -> ComponentResult:
    g = g.settle()
    since = mark()
    done = finish_by_sketches(g, g.vertices.select("vid", F.col("vid").alias("comp")), g.edges.select("src", "dst").where("false"), log=log, exact_below=0)
    sweep(g.vertices.sparkSession, since, done.labels, done.forest)
    return ComponentResult(canonical_labels(g.vertices, done.labels), done.forest)


def growth_then_sketch_cc(g: EdgeSet, phases: int = 2) -> ComponentResult:
    """A few phases of squared growth, the rest by sketches."""
    g = g.settle()
    flat = EdgeSet(g.vertices, g.edges.select("src", "dst", F.lit(0.0).alias("weight")), settled=True)
    forest, labels = squared_growth_msf(flat, phases)
    done = finish_by_sketches(g, labels, forest.select("src", "dst"), exact_below=0)
    return ComponentResult(canonical_labels(g.vertices, done.labels), done.forest)


def min_label_propagation(g: EdgeSet, most: int = 100_000) -> tuple[DataFrame, int]:
    """Labels, and the steps it took: the least id flows along edges until nothing changes."""
    edges = cut(symmetrize(g.edges).select("u", "v"))
    labels, step = cut(g.vertices.select("vid", F.col("vid").alias("comp"))), 0
    while step < most:
        step += 1
        offered = edges.join(labels, F.col("v") == F.col("vid")).groupBy("u").agg(F.min("comp").alias("m"))
        new = cut(labels.join(offered, F.col("vid") == F.col("u"), "left").select("vid", F.least("comp", F.coalesce("m", "comp")).alias("comp"), (F.coalesce("m", "comp") < F.col("comp")).alias("moved")))
        labels = new.drop("moved")
        if new.where("moved").isEmpty():
            break
    return labels, step


def naive_nested_load(deg: DataFrame, n: int) -> DataFrame:
    """max_load of a vertex that serves its own edges in all instances, against n."""
    return deg.agg(F.max(F.col("d") * F.ceil(F.sqrt(F.lit(n)))).cast("long").alias("max_load")).withColumn("overloaded", F.col("max_load") > n)
