"""Complete partitions and spanning forests of edge lists, in one task or distributed, and rooted forests."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.coins import priority
from ..plans.spool import cut, cut_and_count
from .graphs import EdgeSet, symmetrize

TASK_LIMIT = 2_000_000


@dataclass
class ComponentResult:
    labels: DataFrame  # vid, comp (least vid)
    forest: DataFrame  # src, dst


class UnionFind:
    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        root = x
        while (p := self.up.get(root, root)) != root:
            root = p
        while (p := self.up.get(x, x)) != root:
            self.up[x], x = root, p
        return root

    def join(self, x: int, y: int) -> bool:
        """The lesser root stays."""
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def _solve(u: np.ndarray, v: np.ndarray) -> tuple[UnionFind, np.ndarray]:
    sets = UnionFind()
    used = np.fromiter((sets.join(a, b) for a, b in zip(u.tolist(), v.tolist(), strict=True)), bool, len(u))
    return sets, used


def union_find_task(links: DataFrame, weighted: bool = False) -> tuple[DataFrame, DataFrame]:
    """labels and forest of links (u, v, e_src, e_dst[, weight]) solved by one task; for a bounded number of links."""
    columns = ["u", "v", "e_src", "e_dst"] + (["weight"] if weighted else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[c.to_numpy(zero_copy_only=False) for c in b.columns] for b in batches if b.num_rows]
        if not parts:
            return
        cols = [np.concatenate(x) for x in zip(*parts, strict=True)]
        order = np.lexsort((cols[3], cols[2], cols[4])) if weighted else np.lexsort((cols[3], cols[2]))
        u, v, s, d = (c[order] for c in cols[:4])
        sets, used = _solve(u, v)
        ends = np.unique(np.concatenate([u, v]))
        comp = np.array([sets.find(x) for x in ends.tolist()], np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(ends), bool)), pa.array(ends), pa.array(comp)], ["is_edge", "a", "b"])
        yield pa.RecordBatch.from_arrays([pa.array(np.ones(int(used.sum()), bool)), pa.array(s[used]), pa.array(d[used])], ["is_edge", "a", "b"])

    solved = cut(links.select(*columns).coalesce(1).mapInArrow(run, "is_edge boolean, a long, b long"))
    return solved.where("NOT is_edge").select(F.col("a").alias("vid"), F.col("b").alias("comp")), solved.where("is_edge").select(F.col("a").alias("src"), F.col("b").alias("dst"))


def pointer_double(parents: DataFrame, limit: int = TASK_LIMIT, count: int | None = None) -> DataFrame:
    """vid, root from acyclic pointers (vid, parent); a root points to itself, and so does a parent without a row.

    ``parents`` is read twice, so it should be a written table; ``count`` spares counting it.  Up to ``limit`` pointers one task doubles them in
    memory; beyond it they double by self-joins."""
    up = parents.select("vid", F.col("parent").alias("root"))
    if (up.count() if count is None else count) <= limit:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
            if not parts:
                return
            vid, to = (np.concatenate(x) for x in zip(*parts, strict=True))
            ids = np.unique(np.concatenate([vid, to]))
            root = np.arange(len(ids))
            root[np.searchsorted(ids, vid)] = np.searchsorted(ids, to)
            while (root[root] != root).any():
                root = root[root]
            yield pa.RecordBatch.from_arrays([pa.array(vid), pa.array(ids[root[np.searchsorted(ids, vid)]])], ["vid", "root"])

        return cut(up.coalesce(1).mapInArrow(run, "vid long, root long"))
    while True:
        over = up.select(F.col("vid").alias("root"), F.col("root").alias("next"))
        moved = cut(up.join(over, "root", "left").select("vid", F.coalesce("next", "root").alias("root"), (F.coalesce("next", "root") != F.col("root")).alias("moved")))
        up = moved.drop("moved")
        if moved.where("moved").isEmpty():
            return up


def star_contraction(links: DataFrame, seed: int = 0, weighted: bool = False, levels: list | None = None) -> tuple[DataFrame, DataFrame]:
    """labels and forest of links (u, v, e_src, e_dst[, weight]) by hooking toward the least hashed priority among the
    neighbours (weighted: along the lightest edge) and pointer doubling, until no link is left.  With weights, ``levels``
    receives a table a step: u, up (the component u went into), weight, e_src, e_dst (the edge u chose)."""
    links = cut(links.where("u <> v"))
    labels = cut(links.select(F.explode(F.array("u", "v")).alias("vid")).distinct().withColumn("comp", F.col("vid")))
    forest, step = None, 0
    edge = ["weight", "e_src", "e_dst"] if weighted else ["e_src", "e_dst"]
    while not links.isEmpty():
        rest = [c for c in links.columns if c not in ("u", "v")]
        both = links.select("u", "v", *rest).unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v"), *rest))
        if weighted:
            best = cut(both.groupBy("u").agg(F.min(F.struct(*edge, "v")).alias("b")).select("u", "b.*"))
            back = best.select(F.col("u").alias("v"), F.col("v").alias("back"))
            hooks = best.join(back, "v").where("NOT (back = u AND u < v)")  # one end of each mutual choice is a root
        else:
            best = both.groupBy("u").agg(F.min(F.struct(priority(F.col("v"), seed, step).alias("p"), F.col("v"), *edge)).alias("b")).select("u", "b.*")
            own = priority(F.col("u"), seed, step)
            hooks = best.where((F.col("p") < own) | ((F.col("p") == own) & (F.col("v") < F.col("u"))))
        hooks = cut(hooks)
        new = hooks.select(F.col("e_src").alias("src"), F.col("e_dst").alias("dst"))
        forest = new if forest is None else forest.unionByName(new)
        ends = links.select(F.explode(F.array("u", "v")).alias("vid")).distinct()
        up = pointer_double(cut(ends.join(hooks.select(F.col("u").alias("vid"), F.col("v").alias("parent")), "vid", "left").select("vid", F.coalesce("parent", "vid").alias("parent"))))
        if weighted and levels is not None:
            levels.append(cut(best.join(up.select(F.col("vid").alias("u"), F.col("root").alias("up")), "u").select("u", "up", *edge)))
        labels = cut(labels.join(up.select(F.col("vid").alias("comp"), "root"), "comp", "left").select("vid", F.coalesce("root", "comp").alias("comp")))
        a, b = up.select(F.col("vid").alias("u"), F.col("root").alias("ru")), up.select(F.col("vid").alias("v"), F.col("root").alias("rv"))
        kept = links.join(a, "u").join(b, "v").where("ru <> rv")
        links = cut(kept.groupBy(F.least("ru", "rv").alias("u"), F.greatest("ru", "rv").alias("v")).agg(F.min(F.struct(*edge)).alias("e")).select("u", "v", "e.*"))
        step += 1
    if forest is None:
        forest = labels.sparkSession.createDataFrame([], "src long, dst long")
    return labels, forest.distinct()


def complete_partition(links: DataFrame, mode: str = "auto", limit: int = TASK_LIMIT, weighted: bool = False, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """labels (vid, comp) and forest (src, dst) of links (u, v, e_src, e_dst[, weight]).

    ``task``: one task solves all links; ``distributed``: star contraction; ``auto``: by a count against ``limit``."""
    if mode == "auto":
        links, n = cut_and_count(links)
        mode = "task" if n <= limit else "distributed"
    return union_find_task(links, weighted) if mode == "task" else star_contraction(links, seed, weighted)


def as_links(edges: DataFrame) -> DataFrame:
    extra = ["weight"] if "weight" in edges.columns else []
    return edges.select(F.col("src").alias("u"), F.col("dst").alias("v"), F.col("src").alias("e_src"), F.col("dst").alias("e_dst"), *extra)


def canonical_labels(vertices: DataFrame, labels: DataFrame) -> DataFrame:
    """Every vertex with the least id of its component."""
    full = vertices.join(labels, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("c"))
    least = full.groupBy("c").agg(F.min("vid").alias("comp"))
    return full.join(least, "c").select("vid", "comp")


def publish_forest(vertices: DataFrame, result: ComponentResult, limit: int = TASK_LIMIT) -> DataFrame:
    """vid, parent, root, depth: every tree rooted at its least vertex.  Trees are handed to tasks whole, which must fit;
    ``limit`` bounds a tree's edges, and larger ones are rooted by tours."""
    comp = result.labels
    tree = result.forest.join(comp, F.col("src") == F.col("vid")).select("comp", "src", "dst")
    large = cut(tree.groupBy("comp").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > limit).select("comp"))

    def run(table: pa.Table) -> pa.Table:
        c = table["comp"][0].as_py()
        near: dict[int, list[int]] = {}
        for a, b in zip(table["src"].to_pylist(), table["dst"].to_pylist(), strict=True):
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        rows, level, seen = [(c, c, c, 0)], [c], {c}
        depth = 0
        while level:
            depth += 1
            nxt = []
            for a in level:
                for b in sorted(near.get(a, ())):
                    if b not in seen:
                        seen.add(b)
                        rows.append((b, a, c, depth))
                        nxt.append(b)
            level = nxt
        return pa.table([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], ["vid", "parent", "root", "depth"])

    small = tree.join(large, "comp", "left_anti").groupBy("comp").applyInArrow(run, "vid long, parent long, root long, depth long")
    alone = comp.join(result.forest.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), "vid", "left_anti").select("vid", F.col("vid").alias("parent"), F.col("vid").alias("root"), F.lit(0).cast("long").alias("depth"))
    out = small.unionByName(alone)
    if large.isEmpty():
        return out
    return out.unionByName(root_by_tours(tree.join(large, "comp")))


def root_by_tours(tree: DataFrame) -> DataFrame:
    """vid, parent, root, depth of trees (comp, src, dst) of any size, rooted at comp: an Euler tour of each tree is a
    linked list of its edges in both directions; pointer doubling along it gives every direction its place and the
    steps down less the steps up behind it, in as many joins as the tour's length has binary digits."""
    both = cut(tree.select("comp", F.col("src").alias("u"), F.col("dst").alias("v")).unionByName(tree.select("comp", F.col("dst").alias("u"), F.col("src").alias("v"))))
    around = W.partitionBy("u").orderBy("v")
    after = both.select("u", "v", F.coalesce(F.lead("v").over(around), F.lit(None)).alias("next"), F.min("v").over(W.partitionBy("u")).alias("first"))
    # behind (w, u) comes (u, the neighbour of u after w); at the root the tour ends behind its last neighbour
    turns = after.select(F.col("v").alias("u"), F.col("u").alias("v"), F.col("next"), F.col("first"))
    ring = both.join(turns, ["u", "v"]).select("comp", "u", "v", F.col("v").alias("nu"), F.when(F.col("next").isNotNull(), F.col("next")).when(F.col("v") != F.col("comp"), F.col("first")).alias("nv"))
    state = cut(ring.select("comp", "u", "v", F.when(F.col("nv").isNotNull(), F.col("nu")).alias("nu"), "nv", F.lit(1).cast("long").alias("left")))
    while not state.where("nv IS NOT NULL").isEmpty():
        over = state.select(F.col("u").alias("nu"), F.col("v").alias("nv"), F.col("nu").alias("pu"), F.col("nv").alias("pv"), F.col("left").alias("more"))
        state = cut(state.join(over, ["nu", "nv"], "left").select("comp", "u", "v", F.col("pu").alias("nu"), F.col("pv").alias("nv"), (F.col("left") + F.coalesce("more", F.lit(0))).alias("left")))
    back = state.select(F.col("v").alias("u"), F.col("u").alias("v"), F.col("left").alias("back"))
    down = cut(state.join(back, ["u", "v"]).where("left > back").select("comp", F.col("v").alias("vid"), F.col("u").alias("parent")))  # the way down comes first
    roots = down.select("comp").distinct()
    # depths: the same doubling over parents
    depth = cut(down.select("vid", F.col("parent").alias("up"), F.lit(1).cast("long").alias("depth")).unionByName(roots.select(F.col("comp").alias("vid"), F.lit(None).cast("long").alias("up"), F.lit(0).cast("long").alias("depth"))))
    while not depth.where("up IS NOT NULL").isEmpty():
        over = depth.select(F.col("vid").alias("up"), F.col("up").alias("next"), F.col("depth").alias("more"))
        depth = cut(depth.join(over, "up", "left").select("vid", F.col("next").alias("up"), (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth")))
    full = down.unionByName(roots.select("comp", F.col("comp").alias("vid"), F.col("comp").alias("parent")))
    return full.join(depth.select("vid", "depth"), "vid").select("vid", "parent", F.col("comp").alias("root"), "depth")


def empty_forest(g: EdgeSet) -> DataFrame:
    return g.edges.select("src", "dst").where("false")
