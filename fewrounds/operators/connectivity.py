"""Connected components with spanning forests: sparsify, finish, contract, finish, unite."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import Params, params_for
from ..plans.spool import mark, sweep
from .components import ComponentResult, as_links, canonical_labels, complete_partition
from .graphs import EdgeSet
from .sampling import contract_by_samples
from .sketches import finish_by_sketches
from .sparsify import sparsify_by_degree


def merge_results(vertices: DataFrame, one: DataFrame, two: DataFrame, mode: str = "auto") -> ComponentResult:
    """The answer for the union of two edge sets from their forests alone."""
    labels, forest = complete_partition(as_links(one.unionByName(two).distinct()), mode)
    return ComponentResult(canonical_labels(vertices, labels), forest)


def connected_components(g: EdgeSet, params: Params | None = None, mode: str = "auto", reuse_asleep_edges: bool = False, exact_below: int = 0, log: dict | None = None) -> ComponentResult:
    """labels (vid, comp: the least id) and forest.  The coins change cost only: every hook goes along an edge.

    ``params`` default to the method's own, sqrt(n) samples among them; what sampling leaves is finished by sketches.
    ``exact_below`` is an option for small graphs: contracted graphs of so many edges are completed from their edges."""
    since = mark()
    done = _solved(g, params, mode, reuse_asleep_edges, exact_below, log)
    sweep(g.vertices.sparkSession, since, done.labels, done.forest)
    return done


def _solved(g: EdgeSet, params: Params | None, mode: str, reuse_asleep_edges: bool, exact_below: int, log: dict | None) -> ComponentResult:
    g = EdgeSet(g.vertices, g.edges.select("src", "dst"), g.listed, g.settled).settle()
    p = params or params_for(g.n)
    phases_a, phases_b = [], []
    if log is not None:
        log |= {"n": g.n, "samples": p.num_samples, "phases_a": phases_a, "phases_b": phases_b, "contracted": False}
    split = sparsify_by_degree(g, p.s, mode=mode)
    part_a = EdgeSet(g.vertices, split.edges_a, settled=True)
    crossing, asleep = split.sides.agg(F.count_if(F.col("in_a") & F.col("crosses")), F.count_if(~F.col("in_a"))).first()
    forest_a, labels_a = split.forest, split.labels
    if crossing:
        done = finish_by_sketches(part_a, labels_a, forest_a, seed=p.seed, mode=mode, log=phases_a, exact_below=exact_below)
        labels_a, forest_a = done.labels, done.forest
    if not asleep:
        return ComponentResult(canonical_labels(g.vertices, labels_a), forest_a)
    part_b = EdgeSet(g.vertices, split.edges_b, settled=True)
    if reuse_asleep_edges:  # what stage 1 and 2 found among the asleep is part of the forest already
        part_b = EdgeSet(g.vertices, split.sides.where("NOT in_a AND crosses").select("src", "dst"), settled=True)
        done = finish_by_sketches(part_b, labels_a, forest_a, seed=p.seed + 1, mode=mode, log=phases_b, exact_below=exact_below)
        return ComponentResult(canonical_labels(g.vertices, done.labels), done.forest)
    if log is not None:
        log["contracted"] = True
    labels_b, forest_b, _ = contract_by_samples(part_b, p, keep_messages=False)
    done = finish_by_sketches(part_b, labels_b, forest_b, seed=p.seed + 1, mode=mode, log=phases_b, exact_below=exact_below)
    return merge_results(g.vertices, forest_a, done.forest, mode)


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("comp").agg(F.count(F.lit(1)).alias("size"))
