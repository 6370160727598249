"""Linear sketches of crossing edges, and the finisher that completes a partition with them.

The finisher works on the contracted graph: a vertex is a component of the partition so far, an edge a pair of them with
one real edge to stand for it.  Each component's edges are folded by XOR into levels, dealt by a hash, for a number of
independent repetitions; a level that holds one edge gives it away, and the folds of two components add up to the fold
of their union, where inner edges vanish.  So one coordinator that holds the folds, and no edge, merges phase after phase
with a fresh repetition each.  Folds too many for one task are merged phase by phase with joins, and then a repetition
is folded when its phase comes, from the pairs that still cross.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.coins import trailing_zeros
from ..plans.spool import cut, cut_and_count, mark, sweep
from .components import TASK_LIMIT, ComponentResult, UnionFind, complete_partition
from .graphs import EdgeSet, labelled, relabel

LEVELS = 40

#: The primes of the public XXH64 hash.
_PRIMES = tuple(np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _check(seed: int, rep: Column, src: Column, dst: Column) -> Column:
    return F.xxhash64(F.lit(seed).cast("long"), rep.cast("long"), src, dst)


def xxhash_of_longs(*keys: np.ndarray | int) -> np.ndarray:
    """What xxhash64 of the SQL functions gives for columns of longs."""
    one, two, three, four, five = _PRIMES
    left = lambda x, k: (x << np.uint64(k)) | (x >> np.uint64(64 - k))
    h = np.uint64(42)
    with np.errstate(over="ignore"):
        for key in keys:
            k = np.asarray(key, np.int64).view(np.uint64)
            h = (h + five + np.uint64(8)) ^ (left(k * two, 31) * one)
            h = left(h, 27) * one + four
            h = (h ^ (h >> np.uint64(33))) * two
            h = (h ^ (h >> np.uint64(29))) * three
            h = h ^ (h >> np.uint64(32))
    return h.view(np.int64)


def component_sketch(edges: DataFrame, labels: DataFrame, reps: int, seed: int = 0) -> DataFrame:
    """comp, rep, level, x_src, x_dst, x_chk: XOR folds of the edges at a component's vertices, dealt to levels by a
    hash; an edge inside a component meets itself and vanishes."""
    ends = labelled(edges.select("src", "dst"), labels).where("comp_src <> comp_dst")
    return _folded(ends.select("src", "dst", F.explode(F.array("comp_src", "comp_dst")).alias("comp")), reps, seed)


def _folded(ends: DataFrame, reps: int, seed: int, first: int = 0) -> DataFrame:
    rows = ends.withColumn("rep", F.explode(F.sequence(F.lit(first), F.lit(reps - 1))))
    level = trailing_zeros(F.xxhash64(F.lit(seed), F.lit("level"), "rep", "src", "dst"), LEVELS)
    check = _check(seed, F.col("rep"), F.col("src"), F.col("dst"))
    return rows.groupBy("comp", "rep", level.alias("level")).agg(F.bit_xor("src").alias("x_src"), F.bit_xor("dst").alias("x_dst"), F.bit_xor(check).alias("x_chk"))


def refold(sketch: DataFrame, moved: DataFrame) -> DataFrame:
    """The sketch of merged components: moved (comp, to)."""
    return sketch.join(moved, "comp", "left").withColumn("comp", F.coalesce("to", "comp")).groupBy("comp", "rep", "level").agg(F.bit_xor("x_src").alias("x_src"), F.bit_xor("x_dst").alias("x_dst"), F.bit_xor("x_chk").alias("x_chk"))


def recovered(sketch: DataFrame, rep: int, seed: int = 0) -> DataFrame:
    """comp, src, dst: one edge of each component that has a level with exactly one edge."""
    fits = F.col("x_chk") == _check(seed, F.col("rep"), F.col("x_src"), F.col("x_dst"))
    whole = sketch.where((F.col("rep") == rep) & fits & (F.col("x_src") < F.col("x_dst")))
    return whole.groupBy("comp").agg(F.min(F.struct("level", "x_src", "x_dst")).alias("e")).select("comp", F.col("e.x_src").alias("src"), F.col("e.x_dst").alias("dst"))


def merge_in_task(sketch: DataFrame, reps: int, seed: int) -> DataFrame:
    """kind, a, b, n: the coordinator's answer from a sketch of bounded size.  Kind 0: component a went into b; 1: the
    pair (a, b) joined two of them; 2: in phase a, of n growable components b gave an edge; 3: none was growable."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[c.to_numpy(zero_copy_only=False) for c in b.columns] for b in batches if b.num_rows]
        if not parts:
            return
        comp, rep, level, x_src, x_dst, x_chk = (np.concatenate(x).astype(np.int64) for x in zip(*parts, strict=True))
        ids = np.unique(comp)
        sets, rows = UnionFind(), []
        for r in range(reps):
            own = rep == r
            label = np.array([sets.find(x) for x in ids.tolist()], np.int64)[np.searchsorted(ids, comp[own])]
            order = np.lexsort((level[own], label))
            label, lev, folds = label[order], level[own][order], [x[own][order] for x in (x_src, x_dst, x_chk)]
            new = np.flatnonzero(np.concatenate([[True], (label[1:] != label[:-1]) | (lev[1:] != lev[:-1])]))
            label, lev = label[new], lev[new]
            src, dst, chk = (np.bitwise_xor.reduceat(x, new) for x in folds)
            open_ = (src != 0) | (dst != 0) | (chk != 0)  # a fold of crossing edges is empty with a chance of 2^-64
            good = open_ & (src < dst) & (chk == xxhash_of_longs(seed, r, src, dst))
            growable = len(np.unique(label[open_]))
            if not growable:
                rows.append((3, r, 0, 0))  # every fold is empty: the partition is complete
                break
            first = np.unique(label[good], return_index=True)[1]
            src, dst = src[good][first], dst[good][first]
            rows.append((2, r, len(first), growable))
            rows += [(1, x, y, 0) for x, y in zip(src.tolist(), dst.tolist(), strict=True) if sets.join(x, y)]
        rows += [(0, x, sets.find(x), 0) for x in ids.tolist()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], ["kind", "a", "b", "n"])

    return cut(sketch.select("comp", "rep", "level", "x_src", "x_dst", "x_chk").coalesce(1).mapInArrow(run, "kind int, a long, b long, n long"))


def _merge_by_joins(pairs: DataFrame, sketch: DataFrame, reps: int, seed: int, mode: str, log: list | None) -> tuple[DataFrame, DataFrame]:
    """to (comp, to) and the joining pairs (src, dst), phase by phase on tables.  sketch: the first repetition.  The fold of
    a merged component is the sum of its parts' folds, so a later repetition is the same whether it is folded before the
    merges or after them; it is folded after them, and only one repetition is written at a time."""
    since, spark = mark(), pairs.sparkSession
    moved = cut(pairs.select(F.explode(F.array("src", "dst")).alias("comp")).distinct().withColumn("to", F.col("comp")))
    crossing = pairs.select("src", "dst", F.col("src").alias("cu"), F.col("dst").alias("cv"))
    joined: list[DataFrame] = []
    for rep in range(reps):
        if rep:
            ends = crossing.select("src", "dst", F.explode(F.array("cu", "cv")).alias("comp"))
            sketch = cut(_folded(ends, rep + 1, seed, rep))
        picked = cut(crossing.join(recovered(sketch, rep, seed).select("src", "dst").distinct(), ["src", "dst"], "left_semi"))
        growing = sketch.where((F.col("rep") == rep) & ((F.col("x_src") != 0) | (F.col("x_dst") != 0))).select("comp").distinct().count()
        if log is not None:
            log.append({"phase": len(log), "growable": growing, "recovered": picked.count()})
        if not growing:
            break
        links = picked.select(F.col("cu").alias("u"), F.col("cv").alias("v"), F.col("src").alias("e_src"), F.col("dst").alias("e_dst"))
        to, more = complete_partition(links, mode)
        step = cut(to.select(F.col("vid").alias("to"), F.col("comp").alias("next")))
        joined.append(cut(more))
        moved = cut(moved.join(step, "to", "left").select("comp", F.coalesce("next", "to").alias("to")))
        for side in ("cu", "cv"):
            crossing = crossing.join(step.select(F.col("to").alias(side), "next"), side, "left").withColumn(side, F.coalesce("next", side)).drop("next")
        crossing = cut(crossing.where("cu <> cv"))
        sweep(spark, since, moved, crossing, *joined)
    out = pairs.select("src", "dst").where("false")
    for more in joined:
        out = out.unionByName(more)
    return moved, out


def finish_by_sketches(g: EdgeSet, labels: DataFrame, forest: DataFrame, reps: int | None = None, seed: int = 0, mode: str = "auto", log: list | None = None, exact_below: int = 0, task_limit: int = TASK_LIMIT) -> ComponentResult:
    """Completes a partition by sketches of its crossing edges.  ``reps`` phases a sketch (default: lg of the components
    and a few); what is still open then gets a fresh sketch of the merged components, until no edge crosses.

    Sketches of at most ``task_limit`` rows are merged by one coordinator.  With ``exact_below`` a contracted graph of at
    most so many edges is completed from its edges in one task instead; by default none is."""
    g, labels = g.settle(), labels.select("vid", "comp")
    whole = False
    while True:
        contracted, count = cut_and_count(relabel(g.edges.select("src", "dst"), labels).select(F.col("cu").alias("src"), F.col("cv").alias("dst"), F.col("e.src").alias("e_src"), F.col("e.dst").alias("e_dst")))
        if not count:
            return ComponentResult(labels, forest)
        if count <= exact_below:
            to, more = complete_partition(contracted.withColumnsRenamed({"src": "u", "dst": "v"}), "task")
            moved = to.select("vid", F.col("comp").alias("to"))
        else:
            phases = reps or math.ceil(math.log2(count + 1)) + 3
            own = contracted.select("src", "dst", F.explode(F.array("src", "dst")).alias("comp"))
            many = mode == "distributed" or 2 * count * phases > task_limit  # an edge gives two rows a repetition at most
            if many:
                sketch, rows = cut_and_count(_folded(own, 1, seed))
                many = mode == "distributed" or rows * phases > task_limit
            if not many:
                sketch, rows = cut_and_count(_folded(own, phases, seed))
                many = rows > task_limit
            if not many:
                solved = merge_in_task(sketch, phases, seed)
                moved, joined = solved.where("kind = 0").select(F.col("a").alias("vid"), F.col("b").alias("to")), solved.where("kind = 1").select(F.col("a").alias("src"), F.col("b").alias("dst"))
                if log is not None:
                    log += [{"phase": len(log) + k, "growable": r["n"], "recovered": r["b"]} for k, r in enumerate(solved.where("kind = 2").orderBy("a").collect())]
                more, real = cut_and_count(contracted.join(joined, ["src", "dst"], "left_semi").select(F.col("e_src").alias("src"), F.col("e_dst").alias("dst")))
                kinds = {r["kind"]: r["count"] for r in solved.groupBy("kind").count().collect()}
                whole = 3 in kinds
                if real != kinds.get(1, 0):  # a check sum that met by chance: draw anew
                    seed += 1
                    continue
            else:
                moved, joined = _merge_by_joins(contracted, sketch, phases, seed, mode, log)
                moved = moved.withColumnRenamed("comp", "vid")
                more = contracted.join(joined, ["src", "dst"], "left_semi").select(F.col("e_src").alias("src"), F.col("e_dst").alias("dst"))
        forest = forest.unionByName(more)
        labels = cut(labels.join(moved.select(F.col("vid").alias("comp"), "to"), "comp", "left").select("vid", F.coalesce("to", "comp").alias("comp")))
        if whole or count <= exact_below:
            return ComponentResult(labels, forest)
        seed += 1
