"""Answers that reduce to components: bipartite, cut, s-t connected, cycles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import ComponentResult
from .connectivity import connected_components
from .graphs import TAG, EdgeSet

OTHER = TAG * 64


def bipartite_components(g: EdgeSet, solve=connected_components) -> DataFrame:
    """comp, size, bipartite: a component is bipartite if its double cover falls into two."""
    plain = solve(g).labels
    lift = lambda a, b: g.edges.select((F.col("src") + a).alias("src"), (F.col("dst") + b).alias("dst"))
    cover = EdgeSet(g.vertices.union(g.vertices.select(F.col("vid") + OTHER)), lift(0, OTHER).union(lift(OTHER, 0)).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))
    twice = solve(cover).labels.select((F.col("vid") % OTHER).alias("vid"), F.col("comp").alias("lifted"))
    both = plain.join(twice, "vid").groupBy("comp").agg(F.count_distinct("vid").alias("size"), F.count_distinct("lifted").alias("lifts"))
    return both.select("comp", "size", (F.col("lifts") == 2).alias("bipartite"))


def is_bipartite(g: EdgeSet) -> bool:
    return bipartite_components(g).where("NOT bipartite").isEmpty()


def is_cut(g: EdgeSet, cut_edges: DataFrame, solve=connected_components) -> DataFrame:
    """before, after, is_cut: components without some edges."""
    rest = EdgeSet(g.vertices, g.edges.join(cut_edges, ["src", "dst"], "left_anti"))
    before = solve(g).labels.agg(F.count_distinct("comp").alias("before"))
    after = solve(rest).labels.agg(F.count_distinct("comp").alias("after"))
    return before.join(after).withColumn("is_cut", F.col("after") > F.col("before"))


def st_connected(result: ComponentResult, pairs: DataFrame) -> DataFrame:
    """s, t, connected for many pairs."""
    a = result.labels.select(F.col("vid").alias("s"), F.col("comp").alias("cs"))
    b = result.labels.select(F.col("vid").alias("t"), F.col("comp").alias("ct"))
    return pairs.join(a, "s", "left").join(b, "t", "left").select("s", "t", F.coalesce(F.col("cs") == F.col("ct"), F.col("s") == F.col("t")).alias("connected"))


def has_cycle(g: EdgeSet, solve=connected_components) -> DataFrame:
    """comp, has_cycle: more edges than vertices less one."""
    labels = solve(g).labels
    size = labels.groupBy("comp").agg(F.count(F.lit(1)).alias("size"))
    m = g.edges.join(labels, F.col("src") == F.col("vid")).groupBy("comp").agg(F.count(F.lit(1)).alias("m"))
    return size.join(m, "comp", "left").select("comp", (F.coalesce("m", F.lit(0)) > F.col("size") - 1).alias("has_cycle"))


def edge_on_cycle(g: EdgeSet, src: int, dst: int, solve=connected_components) -> bool:
    rest = EdgeSet(g.vertices, g.edges.where(~((F.col("src") == src) & (F.col("dst") == dst))))
    return st_connected(solve(rest), g.edges.sparkSession.createDataFrame([(src, dst)], "s long, t long")).first()["connected"]
