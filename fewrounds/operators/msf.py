"""Minimum spanning forests: random thinning, light edges, and nested runs of the sorted edges.

Edges are totally ordered by (weight, src, dst), so the forest is unique."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import coin
from ..plans.spool import cut, mark, sweep
from .components import TASK_LIMIT, UnionFind, as_links, complete_partition, star_contraction
from .graphs import EdgeSet, relabel
from .relational import global_rank

FOREST_LIMIT = 500_000  # vertices whose forest is broadcast for the light-edge test; its table takes 360 bytes a vertex at most


FILTER_ABOVE = 4  # edges a vertex


def thin_by_sampling(g: EdgeSet, p: float, seed: int = 0, portable: bool = False) -> DataFrame:
    return g.edges.where(coin(seed, "thin", "src", "dst", portable=portable) < p)


def with_weights(forest: DataFrame, edges: DataFrame) -> DataFrame:
    return edges.join(forest.select("src", "dst"), ["src", "dst"], "left_semi")


def _lifting(src: np.ndarray, dst: np.ndarray, rank: np.ndarray, ids: np.ndarray):
    """Ancestors and largest edge rank by powers of two, depths and roots of a forest."""
    n = len(ids)
    a, b = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    order = np.argsort(np.concatenate([a, b]), kind="stable")
    other, weight = np.concatenate([b, a])[order], np.concatenate([rank, rank])[order]
    at = np.searchsorted(np.concatenate([a, b])[order], np.arange(n + 1))
    parent, depth, root, up_rank = np.arange(n), np.full(n, -1), np.full(n, -1), np.zeros(n, np.int64)
    for start in range(n):
        if depth[start] >= 0:
            continue
        depth[start], root[start] = 0, start
        stack = [start]
        while stack:
            x = stack.pop()
            for k in range(at[x], at[x + 1]):
                y = other[k]
                if depth[y] < 0:
                    depth[y], root[y], parent[y], up_rank[y] = depth[x] + 1, start, x, weight[k]
                    stack.append(int(y))
    ups, tops = [parent], [up_rank]
    while (1 << len(ups)) <= max(1, depth.max(initial=0)):
        p, t = ups[-1], tops[-1]
        ups.append(p[p])
        tops.append(np.maximum(t, t[p]))
    return np.stack(ups), np.stack(tops), depth, root


def _path_max(table, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Largest edge rank on each path, of vertices in one tree."""
    ups, tops, depth, _ = table
    x, y = np.where(depth[x] >= depth[y], x, y), np.where(depth[x] >= depth[y], y, x)
    best = np.zeros(len(x), np.int64)
    gap = depth[x] - depth[y]
    for k in range(len(ups)):
        go = (gap >> k) & 1 == 1
        best[go] = np.maximum(best[go], tops[k][x[go]])
        x = np.where(go, ups[k][x], x)
    for k in range(len(ups) - 1, -1, -1):
        go = ups[k][x] != ups[k][y]
        best[go] = np.maximum(best[go], np.maximum(tops[k][x[go]], tops[k][y[go]]))
        x, y = np.where(go, ups[k][x], x), np.where(go, ups[k][y], y)
    last = x != y
    best[last] = np.maximum(best[last], np.maximum(tops[0][x[last]], tops[0][y[last]]))
    return best


def light_edges(g: EdgeSet, forest: DataFrame, limit: int = FOREST_LIMIT) -> DataFrame:
    """The edges no heavier than the heaviest edge between their ends in the forest (src, dst, weight), and those
    whose ends it doesn't join.  Beyond ``limit`` vertices the test is one of joins."""
    if g.n > limit:
        return light_edges_by_levels(g, forest)
    rows = forest.select("src", "dst", "weight").toArrow()  # n rows at most, n checked
    f = [rows[c].to_numpy() for c in ("src", "dst", "weight")]
    order = np.lexsort((f[1], f[0], f[2]))
    src, dst, weight = (x[order] for x in f)
    ids = np.unique(np.concatenate([src, dst]))
    if not len(ids):
        return g.edges
    table = _lifting(src, dst, np.arange(1, len(src) + 1), ids)
    held = g.edges.sparkSession.sparkContext.broadcast((ids, src, dst, weight, table))
    names = g.edges.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, fs, fd, fw, table = held.value
        for batch in batches:
            s, d, w = (batch.column(names.index(c)).to_numpy(zero_copy_only=False) for c in ("src", "dst", "weight"))
            a, b = np.minimum(np.searchsorted(ids, s), len(ids) - 1), np.minimum(np.searchsorted(ids, d), len(ids) - 1)
            same = (ids[a] == s) & (ids[b] == d)
            same[same] = table[3][a[same]] == table[3][b[same]]
            keep = ~same
            top = _path_max(table, a[same], b[same]) - 1  # place of the heaviest forest edge
            x, y, z = w[same], s[same], d[same]
            tw, ts, td = fw[top], fs[top], fd[top]
            keep[same] = (x < tw) | ((x == tw) & ((y < ts) | ((y == ts) & (z <= td))))
            yield batch.filter(pa.array(keep))

    return g.edges.mapInArrow(run, g.edges.schema)


def light_edges_by_levels(g: EdgeSet, forest: DataFrame) -> DataFrame:
    """The light edges by joins alone.  In the tree of merged components, where each has the edge it chose, the heaviest
    edge between two vertices equals the heaviest in the forest; so both ends climb together, at most lg n steps, until
    an edge at least as heavy is met (light), they meet (heavy), or a tree ends (not joined).  The tables of the steps
    halve at least."""
    levels: list[DataFrame] = []
    star_contraction(as_links(forest), weighted=True, levels=levels)
    names = g.edges.columns
    rest = g.edges.select(*names, F.col("src").alias("cu"), F.col("dst").alias("cv"))
    own = F.struct("weight", "src", "dst")
    kept = None
    for level in levels:
        chosen = F.struct("weight", F.col("e_src").alias("src"), F.col("e_dst").alias("dst"))
        a = level.select(F.col("u").alias("cu"), F.col("up").alias("pu"), chosen.alias("ku"))
        b = level.select(F.col("u").alias("cv"), F.col("up").alias("pv"), chosen.alias("kv"))
        light = F.isnull("pu") | F.isnull("pv") | (F.col("ku") >= own) | (F.col("kv") >= own)
        step = cut(rest.join(a, "cu", "left").join(b, "cv", "left").withColumn("light", light).where("light OR pu <> pv").select(*names, F.col("pu").alias("cu"), F.col("pv").alias("cv"), "light"))
        done, rest = step.where("light").select(*names), step.where("NOT light").drop("light")
        kept = done if kept is None else kept.unionByName(done)
        if rest.isEmpty():
            return kept
    rest = rest.select(*names)
    return rest if kept is None else kept.unionByName(rest)


def nested_instances(edges: DataFrame, n: int, growth: str = "uniform") -> DataFrame:
    """The edges with first_instance: runs of n edges in order, or runs that double."""
    ranked = global_rank(edges, ["weight", "src", "dst"], "rank")
    run = F.floor((F.col("rank") - 1) / n) + 1 if growth == "uniform" else F.floor(F.log2((F.col("rank") - 1) / n + 1) + 1e-9) + 1
    return ranked.withColumn("first_instance", run.cast("int"))


def bucketed_forest(g: EdgeSet, growth: str = "geometric", run: int | None = None, mode: str = "auto", log: list | None = None) -> DataFrame:
    """src, dst of the minimum spanning forest: run after run, contracted by what is joined already."""
    n = run or max(g.n, 1)
    edges = cut(nested_instances(g.edges, n, growth))
    last = edges.agg(F.max("first_instance")).first()[0] or 0
    labels = cut(g.vertices.select("vid", F.col("vid").alias("comp")))
    forest = None
    for i in range(1, last + 1):
        own = relabel(edges.where(F.col("first_instance") == i).select("src", "dst", "weight"), labels)
        links = cut(own.select(F.col("cu").alias("u"), F.col("cv").alias("v"), F.col("e.src").alias("e_src"), F.col("e.dst").alias("e_dst"), F.col("e.weight").alias("weight")))
        if links.isEmpty():
            continue
        to, more = complete_partition(links, mode, weighted=True)
        forest = more if forest is None else forest.unionByName(more)
        labels = cut(labels.join(to.select(F.col("vid").alias("comp"), F.col("comp").alias("to")), "comp", "left").select("vid", F.coalesce("to", "comp").alias("comp")))
        if log is not None:
            log.append({"instance": i, "edges": more.count()})
        if labels.select("comp").distinct().limit(2).count() < 2:
            break
    return forest if forest is not None else g.edges.select("src", "dst").where("false")


def simultaneous_forest(g: EdgeSet, run: int | None = None, log: list | None = None) -> DataFrame:
    """src, dst of the minimum spanning forest: runs of n edges in order make nested instances, whose components are
    found all at once; then every run is solved on its own, contracted by the instance before it."""
    from .nested import bucket_kruskal, components_of_nested

    n = run or max(1, min(g.n, TASK_LIMIT))
    edges = cut(nested_instances(g.edges, n, "uniform"))
    last = edges.agg(F.max("first_instance")).first()[0] or 0
    if log is not None:
        log.append({"instances": last})
    nothing = g.vertices.select(F.lit(0).alias("instance"), "vid", F.col("vid").alias("comp")).where("false")
    labels = components_of_nested(edges.where(F.col("first_instance") < last), g.vertices, last - 1) if last > 1 else nothing
    return bucket_kruskal(edges, cut(labels))


def minimum_spanning_forest(g: EdgeSet, seed: int = 0, faithful: bool = False, method: str = "simultaneous", growth: str = "geometric", force_filter: bool = False, log: dict | None = None) -> DataFrame:
    """src, dst, weight.  Graphs of more than ``FILTER_ABOVE`` edges a vertex are first thinned (p = 1/sqrt n with
    ``faithful``, else sqrt(n / edges), which leaves as many thin edges as light ones); the forest of the thin part shows
    which edges are light, and only those go on.  ``method``: nested instances all at once, or ``sequential`` runs."""
    g = g.settle()
    since = mark()
    n, m = max(g.n, 1), g.edges.count()
    runs: list = []
    forest_of = (lambda x: simultaneous_forest(x, log=runs)) if method == "simultaneous" else (lambda x: bucketed_forest(x, growth))
    edges = g.edges
    if m > FILTER_ABOVE * n or force_filter:
        p = 1 / n**0.5 if faithful else min(1.0, (n / max(m, 1)) ** 0.5)
        thin = EdgeSet(g.vertices, cut(thin_by_sampling(g, p, seed)), settled=True)
        forest = with_weights(forest_of(thin), thin.edges)
        edges = cut(light_edges(g, forest))
        if log is not None:
            log |= {"n": n, "edges": m, "p": p, "thin": thin.edges.count(), "light": edges.count()}
    light = EdgeSet(g.vertices, edges, settled=True)
    out = with_weights(forest_of(light), edges)
    if log is not None:
        log["instances"] = [r["instances"] for r in runs]
    sweep(g.edges.sparkSession, since, out)
    return out


def hook_and_contract_msf(g: EdgeSet) -> DataFrame:
    """Every component takes its lightest outgoing edge, again and again.  The edges are made once and written."""
    since = mark()
    edges = g.edges if g.settled else cut(g.edges)
    _, forest = complete_partition(as_links(edges), "distributed", weighted=True)
    out = cut(with_weights(forest, edges))
    sweep(g.edges.sparkSession, since, out)
    return out


def exact_local_msf(g: EdgeSet) -> DataFrame:
    """Kruskal's method in one task, for bounded graphs."""
    _, forest = complete_partition(as_links(g.edges), "task", weighted=True)
    return with_weights(forest, g.edges)


def squared_growth_msf(g: EdgeSet, phases: int | None = None, limit: int = TASK_LIMIT) -> tuple[DataFrame, DataFrame]:
    """A cluster of k vertices lists its k lightest edges to different clusters, n rows at most; a task merges along
    listed edges in order as long as a side still vouches for its lightest edge, that is until a member's list ends.
    With more than ``limit`` vertices clusters list one edge, and the merges are those of hooking and contracting.
    Returns the forest and labels; with ``phases`` it stops early."""
    from pyspark.sql import Window as W

    g = g.settle()
    labels = g.vertices.select("vid", F.col("vid").alias("comp"))
    forest, done = None, 0
    while phases is None or done < phases:
        pairs = relabel(g.edges, labels)
        both = cut(pairs.select(F.col("cu").alias("c"), F.col("cv").alias("o"), "e.*").unionByName(pairs.select(F.col("cv").alias("c"), F.col("cu").alias("o"), "e.*")))
        if both.isEmpty():
            break
        if g.n > limit:
            best = both.groupBy("c").agg(F.min(F.struct("weight", "src", "dst", "o")).alias("b")).select(F.col("c").alias("u"), F.col("b.o").alias("v"), F.col("b.src").alias("e_src"), F.col("b.dst").alias("e_dst"), F.col("b.weight").alias("weight"))
            to, new = complete_partition(best, "distributed", weighted=True)
            to = to.select(F.col("vid").alias("comp"), F.col("comp").alias("to"))
        else:
            sizes = labels.groupBy(F.col("comp").alias("c")).agg(F.count(F.lit(1)).alias("k"))
            w = W.partitionBy("c").orderBy("weight", "src", "dst")
            listed = both.withColumn("r", F.row_number().over(w)).join(sizes, "c").where(F.col("r") <= F.col("k"))
            ends = both.groupBy("c").agg(F.count(F.lit(1)).alias("all"))
            rows = listed.join(ends, "c").select("c", "o", "weight", "src", "dst", ((F.col("r") == F.col("k")) & (F.col("all") > F.col("k"))).alias("ends"))
            solved = cut(rows.coalesce(1).mapInArrow(_merge_listed, "is_edge boolean, a long, b long"))
            new = solved.where("is_edge").select(F.col("a").alias("src"), F.col("b").alias("dst"))
            to = solved.where("NOT is_edge").select(F.col("a").alias("comp"), F.col("b").alias("to"))
        forest = new if forest is None else forest.unionByName(new)
        labels = cut(labels.join(to, "comp", "left").select("vid", F.coalesce("to", "comp").alias("comp")))
        done += 1
    if forest is None:
        forest = g.edges.select("src", "dst").where("false")
    return with_weights(forest, g.edges) if "weight" in g.edges.columns else forest, labels


def _merge_listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Merges of listed edges (c, o, weight, src, dst, ends)."""
    data = sorted((r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)), key=lambda r: (r[2], r[3], r[4]))
    sets, closed, used = UnionFind(), set(), []
    i = 0
    while i < len(data):
        j = i
        while j < len(data) and data[j][2:5] == data[i][2:5]:
            j += 1
        x, y = sets.find(data[i][0]), sets.find(data[i][1])
        if x != y and not (x in closed and y in closed):
            shut = x in closed or y in closed
            sets.join(x, y)
            used.append((data[i][3], data[i][4]))
            if shut:
                closed.add(sets.find(x))
        closed |= {sets.find(r[0]) for r in data[i:j] if r[5]}
        i = j
    ids = sorted({r[0] for r in data} | {r[1] for r in data})
    rows = [(False, v, sets.find(v)) for v in ids] + [(True, a, b) for a, b in used]
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.bool_(), pa.int64(), pa.int64()), strict=True)], ["is_edge", "a", "b"])
