"""Degree sparsification: two stages of hooking toward high degree split the edges into a part with few components and
a part of low degree."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spool import cut, cut_and_count
from .components import complete_partition, pointer_double
from .graphs import EdgeSet, degrees, labelled, symmetrize


@dataclass
class Split:
    edges_a: DataFrame  # both ends awake
    edges_b: DataFrame
    labels: DataFrame  # vid, comp, cdeg, awake
    forest: DataFrame
    hooks1: DataFrame
    hooks2: DataFrame
    labels1: DataFrame
    sides: DataFrame  # the edges with in_a and crosses (the ends are in different components)


def hook_to_top_neighbour(g: EdgeSet, deg: DataFrame) -> DataFrame:
    """v, u, d: each vertex's neighbour of the largest (degree, id), and that degree."""
    far = deg.select(F.col("vid").alias("v"), "d")
    return symmetrize(g.edges).select("u", "v").join(far, "v").groupBy("u").agg(F.max(F.struct("d", "v")).alias("m")).select(F.col("u").alias("v"), F.col("m.v").alias("u"), F.col("m.d").alias("d"))


def hook_to_top_component(g: EdgeSet, labels: DataFrame) -> DataFrame:
    """v, u: each vertex's neighbour in the other component of the largest (degree, label, neighbour).  labels: vid, comp, cdeg."""
    near = labels.select(F.col("vid").alias("u"), F.col("comp").alias("cu"))
    far = labels.select(F.col("vid").alias("v"), F.col("comp").alias("cv"), "cdeg")
    crossing = symmetrize(g.edges).select("u", "v").join(near, "u").join(far, "v").where("cu <> cv")
    return crossing.groupBy("u").agg(F.max(F.struct("cdeg", "cv", "v")).alias("m")).select(F.col("u").alias("v"), F.col("m.v").alias("u"))


def stage_one(g: EdgeSet, deg: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Hooks, labels (vid, comp, cdeg) and forest edges.  The hooks can only meet in pairs, so they form a forest."""
    hooks = cut(hook_to_top_neighbour(g, deg))
    back = hooks.select(F.col("v").alias("u"), F.col("u").alias("w"), F.col("d").alias("dw"))
    root = (F.col("w") == F.col("v")) & (F.struct(F.col("dw"), F.col("w")) > F.struct(F.col("d"), F.col("u")))  # of a mutual pair, the higher one
    parents, n = cut_and_count(hooks.join(back, "u").select(F.col("v").alias("vid"), F.when(root, F.col("v")).otherwise(F.col("u")).alias("parent")))
    alone = g.vertices.join(hooks.select(F.col("v").alias("vid")), "vid", "left_anti").select("vid", F.col("vid").alias("root"))
    rooted = pointer_double(parents, count=n).unionByName(alone)
    whole = rooted.join(deg, "vid").groupBy("root").agg(F.min("vid").alias("comp"), F.max("d").alias("cdeg"))
    labels = cut(rooted.join(whole, "root").select("vid", "comp", "cdeg"))
    forest = parents.where("vid <> parent").select(F.least("vid", "parent").alias("src"), F.greatest("vid", "parent").alias("dst"))
    return hooks, labels, forest


def sparsify_by_degree(g: EdgeSet, s: int, second_stage: bool = True, mode: str = "auto") -> Split:
    """Awake components have a vertex of degree s or more; an edge with both ends awake goes to part A."""
    g = g.settle()
    deg = cut(degrees(g))
    hooks1, labels1, forest = stage_one(g, deg)
    labels2, hooks2, n = labels1, hooks1.where("false"), 0
    if second_stage:
        hooks2, n = cut_and_count(hook_to_top_component(g, labels1))
    if n:
        ends = hooks2.select(F.least("v", "u").alias("src"), F.greatest("v", "u").alias("dst")).distinct()
        links = labelled(ends, labels1).select(F.col("comp_src").alias("u"), F.col("comp_dst").alias("v"), F.col("src").alias("e_src"), F.col("dst").alias("e_dst"))
        merged, more = complete_partition(links, mode)
        to = labels1.groupBy("comp").agg(F.max("cdeg").alias("cdeg")).join(merged.select(F.col("vid").alias("comp"), F.col("comp").alias("to")), "comp", "left").withColumn("to", F.coalesce("to", "comp"))
        top = to.groupBy("to").agg(F.max("cdeg").alias("cdeg"))
        labels2 = labels1.select("vid", "comp").join(to.select("comp", "to"), "comp").join(top, "to").select("vid", F.col("to").alias("comp"), "cdeg")
        forest = forest.unionByName(more)
    labels = cut(labels2.withColumn("awake", F.col("cdeg") >= s))
    near = labels.select(F.col("vid").alias("src"), F.col("awake").alias("x"), F.col("comp").alias("cx"))
    far = labels.select(F.col("vid").alias("dst"), F.col("awake").alias("y"), F.col("comp").alias("cy"))
    sides = cut(g.edges.join(near, "src").join(far, "dst").select(*g.edges.columns, (F.col("x") & F.col("y")).alias("in_a"), (F.col("cx") != F.col("cy")).alias("crosses")))
    return Split(sides.where("in_a").select(*g.edges.columns), sides.where("NOT in_a").select(*g.edges.columns), labels, forest, hooks1, hooks2, labels1, sides)
