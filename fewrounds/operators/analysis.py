"""Vertex classes, pieces of trees, and the measures that the bounds speak of."""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import coin
from ..functions.params import Params
from .components import ComponentResult
from .graphs import EdgeSet, growable
from .sparsify import Split

ROWS = 100_000  # rows of pieces that a task hands on at a time


def classify_vertices(g: EdgeSet, messages: DataFrame, labels: DataFrame, p: Params, portable: bool = False) -> DataFrame:
    """vid, class (alpha: a sample component of it holds a leader; beta: not so, but its final component is small and
    ungrowable; gamma: the rest) and bad (final component growable and without leader)."""
    led = messages.where("comp_has_leader").select(F.col("v").alias("vid")).distinct().withColumn("led", F.lit(True))
    sizes = labels.groupBy("comp").agg(F.count(F.lit(1)).alias("size"), F.max(coin(p.seed, "leader", "vid", portable=portable) < p.p_leader).alias("has_leader"))
    grow = growable(labels, g.edges).withColumn("grow", F.lit(True))
    own_leader = coin(p.seed, "leader", "vid", portable=portable) < p.p_leader
    full = labels.join(led, "vid", "left").join(sizes, "comp").join(grow, "comp", "left")
    alpha = F.coalesce("led", F.lit(False)) | own_leader
    kind = F.when(alpha, "alpha").when(F.col("grow").isNull() & (F.col("size") <= p.small), "beta").otherwise("gamma")
    return full.select("vid", kind.alias("class"), (F.col("grow").isNotNull() & ~F.col("has_leader")).alias("bad"), "has_leader")


def _tiles(src: np.ndarray, dst: np.ndarray, s: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """ids in order, and piece, place and is_unique of every member of a piece, for a forest.

    Leaves are taken off again and again.  A vertex gathers what its children leave over, less than s vertices each; as
    soon as that and the vertex have s, they are a piece at it, and the vertex goes no further.  Else it goes on to its
    parent with what it has.  What a vertex with pieces has left joins the last of them, and what the last vertex of a
    tree has goes to a vertex with pieces next to it."""
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n, m, need = len(ids), len(src), max(s, 2) - 1
    ends = ends.astype(np.int32)
    deg = array("i", np.bincount(ends, minlength=n).astype(np.int32).tobytes())
    x = np.zeros(n, np.int32)
    np.bitwise_xor.at(x, ends[:m], ends[m:])
    np.bitwise_xor.at(x, ends[m:], ends[:m])
    up = array("i", x.tobytes())  # of a vertex with one neighbour left it is this one
    del x, ends
    count, now, group, last = (array("i", bytes(4 * n)) for _ in range(4))
    holder = array("i", [0])
    for v in range(n):
        while deg[v] == 1:
            w = up[v]
            deg[v] = -1
            deg[w] -= 1
            up[w] ^= v
            if not last[v]:
                g = now[w]
                if not g:
                    g = now[w] = len(holder)
                    holder.append(w)
                group[v] = g
                k = count[w] + count[v] + 1
                if k >= need:
                    last[w] = g
                    now[w] = count[w] = 0
                else:
                    count[w] = k
            v = w
    deg, up, count, now, group, last, holder = (np.frombuffer(c, np.int32) for c in (deg, up, count, now, group, last, holder))
    groups, own = len(holder), np.arange(n, dtype=np.int32)
    left = np.zeros(groups, bool)
    left[now[now > 0]] = True
    left[0] = False
    root, anchor = deg == 0, last > 0
    to = np.where(left, last[holder], np.arange(groups, dtype=np.int32))  # the piece of a group; 0: it went on with its holder
    top = np.where(~root & ~anchor & (to[group] == 0), holder[group], own)
    while (top[top] != top).any():
        top = top[top]
    alone = np.flatnonzero(root & ~anchor)
    final = np.zeros(n, np.int32)
    final[alone] = groups + np.arange(len(alone))  # a piece of its own
    at = np.full(groups + len(alone), -1, np.int32)  # the vertex of a piece
    at[1:groups] = np.where(left[1:], -1, holder[1:])
    near = np.flatnonzero(anchor & ~root)
    near = near[root[top[up[near]]] & ~anchor[up[near]]]
    t, first = np.unique(top[up[near]], return_index=True)
    c = near[first]
    enough = count[c] + count[t] + 1 >= need
    final[t[~enough]] = last[c[~enough]]
    at[final[t[enough]]] = c[enough]
    rest = enough & (now[c] > 0)
    to[now[c[rest]]] = final[t[rest]]
    member = np.flatnonzero(~anchor)
    end = top[member]
    piece = np.where(root[end], final[end], to[group[end]])
    held = np.flatnonzero(at >= 0)
    several = np.bincount(at[held], minlength=n) > 1
    return ids, np.concatenate([piece, held]), np.concatenate([member, at[held]]), np.concatenate([np.ones(len(member), bool), ~several[at[held]]])


def almost_partition(forest: DataFrame, labels: DataFrame, s: int) -> DataFrame:
    """comp, piece, vid, is_unique: connected pieces of s to 3s vertices (one piece if the tree is smaller), which share
    at most one vertex each with others.  A tree is handled by one task, which takes time in proportion to it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[c.to_numpy() for c in b.columns] for b in batches if b.num_rows]
        if not parts:
            return
        comp, src, dst = (np.concatenate(c) for c in zip(*parts, strict=True))
        del parts
        ids, piece, at, unique = _tiles(src, dst, s)
        own = np.zeros(len(ids), np.int64)
        own[np.searchsorted(ids, src)] = comp
        own[np.searchsorted(ids, dst)] = comp
        for k in range(0, len(at), ROWS):
            p, v, u = (c[k : k + ROWS] for c in (piece, at, unique))
            yield pa.RecordBatch.from_arrays([pa.array(own[v]), pa.array(p.astype(np.int32)), pa.array(ids[v]), pa.array(u)], ["comp", "piece", "vid", "is_unique"])

    tree = forest.join(labels, F.col("src") == F.col("vid")).select("comp", "src", "dst")
    return tree.repartition("comp").mapInArrow(run, "comp long, piece int, vid long, is_unique boolean")


def forest_checks(g: EdgeSet, result: ComponentResult) -> DataFrame:
    """n, components, forest_edges, and verdicts: right size, within the edges, same partition as the labels."""
    from .components import as_links, canonical_labels, complete_partition

    f = result.forest.select("src", "dst").distinct()
    n, c, m = g.n, result.labels.select("comp").distinct().count(), f.count()
    inside = f.join(g.edges, ["src", "dst"], "left_anti").isEmpty()
    spanned, _ = complete_partition(as_links(f))
    same = canonical_labels(g.vertices, spanned).exceptAll(result.labels.select("vid", "comp")).isEmpty()
    return g.edges.sparkSession.createDataFrame([(n, c, m, m == n - c, inside, same)], "n long, components long, forest_edges long, size_ok boolean, inside_ok boolean, spans_ok boolean")


def split_measures(g: EdgeSet, split: Split, s: int) -> DataFrame:
    """awake components and their least size against n/s and s+1, and the sparse part's largest degree against s."""
    awake = split.labels.where("awake").groupBy("comp").agg(F.count(F.lit(1)).alias("size"))
    a = awake.agg(F.count(F.lit(1)).alias("awake_components"), F.min("size").alias("least_size"))
    d = split.edges_b.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").count().agg(F.coalesce(F.max("count"), F.lit(0)).alias("deg_b"))
    e = split.edges_a.agg(F.count(F.lit(1)).alias("edges_a")).join(split.edges_b.agg(F.count(F.lit(1)).alias("edges_b")))
    return a.join(d).join(e).select("awake_components", F.coalesce("least_size", F.lit(0)).alias("least_size"), "deg_b", "edges_a", "edges_b", (F.col("awake_components") * s <= g.n).alias("count_ok"), (F.coalesce("least_size", F.lit(s + 1)) >= s + 1).alias("size_ok"), (F.col("deg_b") < s).alias("degree_ok"))


def tree_hit_rate(samples: DataFrame, chains: DataFrame, k: int) -> DataFrame:
    """How many chains of k vertices lie whole in a sample.  chains: chain, src, dst (k - 1 edges each)."""
    hit = chains.join(samples, ["src", "dst"]).groupBy("chain", "sample").count().where(F.col("count") == k - 1).select("chain").distinct()
    total = chains.select("chain").distinct().agg(F.count(F.lit(1)).alias("chains"))
    return total.join(hit.agg(F.count(F.lit(1)).alias("hit"))).withColumn("rate", F.col("hit") / F.col("chains"))


def piece_bad_bound(pieces: DataFrame, samples: DataFrame, forest: DataFrame, classes: DataFrame) -> DataFrame:
    """Per piece: in_sample (some sample holds it whole), holds_leader, and what it adds to the bound on bad vertices."""
    edges = pieces.alias("a").join(pieces.alias("b"), ["comp", "piece"]).join(forest, (F.col("a.vid") == F.col("src")) & (F.col("b.vid") == F.col("dst"))).select("comp", "piece", "src", "dst")
    need = edges.groupBy("comp", "piece").agg(F.count(F.lit(1)).alias("need"))
    whole = edges.join(samples, ["src", "dst"]).groupBy("comp", "piece", "sample").agg(F.count(F.lit(1)).alias("have")).join(need, ["comp", "piece"]).where("have = need").select("comp", "piece").distinct().withColumn("in_sample", F.lit(True))
    size = pieces.join(classes, "vid").groupBy("comp", "piece").agg(F.count(F.lit(1)).alias("size"), F.max(F.col("class") == "alpha").alias("some_alpha"))
    return size.join(whole, ["comp", "piece"], "left").select("comp", "piece", "size", F.coalesce("in_sample", F.lit(False)).alias("in_sample"), "some_alpha", F.when(F.coalesce("in_sample", F.lit(False)) & F.col("some_alpha"), 0).otherwise(F.col("size")).alias("adds"))
