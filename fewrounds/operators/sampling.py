"""Contraction of low-degree graphs by independent edge samples and random leaders."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import coin, mixed
from ..functions.params import Params
from ..plans.spool import cut, cut_and_count, mark, sweep
from .blocks import best_hops
from .components import pointer_double
from .graphs import EdgeSet

HIT_ROWS = 50_000  # edges whose hits are sought at a time
MERGE_ROWS = 2_000_000  # messages that a task holds before it keeps the best of each vertex
MESSAGE = "v long, x long, size long, sample int, hop long, comp_has_leader boolean, comp_key long"


def sample_edges(edges: DataFrame, m: int, p: float, seed: int, portable: bool = False) -> DataFrame:
    """sample, src, dst: each edge joins each of m samples with probability p.

    Hits are found by geometric gaps, so a row costs its hits and not m coins; ``portable`` flips m coins instead.  The
    gaps come from a hash of seed, edge and step, so a task that is run again finds the same hits.  With ``portable``
    columns ls and ld of the edges go along."""
    if portable:  # what a row's coins share is made once, before it is repeated
        bound = math.ceil(p * (1 << 32))  # a coin of 32 bits is below p if its number is below this
        own = ["src", "dst", *(c for c in ("ls", "ld") if c in edges.columns)]
        keys = edges.select(*own, F.concat_ws("|", F.lit(""), F.col("src").cast("string"), F.col("dst").cast("string")).alias("keys"))
        all_ = keys.select(*own, "keys", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("sample"))
        number = F.substring(F.md5(F.concat(F.lit(f"{seed}|sample|"), F.col("sample").cast("string"), F.col("keys"))), 1, 8)
        return all_.where(number < f"{bound:08x}" if bound < 1 << 32 else F.lit(True)).select("sample", *own)
    if p >= 1:
        return edges.select(F.explode(F.sequence(F.lit(1), F.lit(m))).alias("sample"), "src", "dst")
    scale = 1 / math.log(1 - p)

    def skip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, HIT_ROWS):
                src, dst = (batch.column(k).slice(start, HIT_ROWS).to_numpy() for k in range(2))
                state = mixed(mixed(src.view(np.uint64) + np.uint64(seed)) ^ dst.view(np.uint64))
                row, at = np.arange(len(src)), np.zeros(len(src), np.int64)
                while len(row):
                    state = mixed(state)
                    gap = np.floor(np.log(((state >> np.uint64(11)).astype(float) + 0.5) * 2.0**-53) * scale)
                    at = at + np.minimum(gap, m).astype(np.int64) + 1
                    going = at <= m
                    row, at, state = row[going], at[going], state[going]
                    if len(row):
                        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(src[row]), pa.array(dst[row])], ["sample", "src", "dst"])

    return edges.select("src", "dst").mapInArrow(skip, "sample int, src long, dst long")


def hits_table_function():
    """A table function (a, b, m, p, seed) -> sample: the samples an edge joins, by geometric skips."""
    from pyspark.sql.functions import udtf

    class Hits:
        def eval(self, a: int, b: int, m: int, p: float, seed: int):
            import math
            import random

            draw, at = random.Random(f"{seed}|{a}|{b}"), 0
            while True:
                at += 1 if p >= 1 else int(math.log(1 - draw.random()) / math.log(1 - p)) + 1
                if at > m:
                    return
                yield (at,)

    return udtf(Hits, returnType="sample int")


def with_leaders(edges: DataFrame, p: Params, portable: bool = False) -> DataFrame:
    """The edges with ls and ld, whether their ends are leaders."""
    flag = lambda c: coin(p.seed, "leader", c, portable=portable) < p.p_leader
    return edges if "ls" in edges.columns else edges.withColumns({"ls": flag("src"), "ld": flag("dst")})


def choose_leaders(vertices: DataFrame, p: float, seed: int, portable: bool = False) -> DataFrame:
    return vertices.where(coin(seed, "leader", "vid", portable=portable) < p)


SAMPLE_LIMIT = 20_000_000  # edges of one sample that a task solves alone
DEALT_LIMIT = 50_000_000  # edges of all samples that are dealt to their tasks; more are drawn there


def _solved(sample: int, src: np.ndarray, dst: np.ndarray, lead_src: np.ndarray, lead_dst: np.ndarray, n: int) -> pa.Table:
    """The messages of one sample."""
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    k, m = len(ids), len(src)
    a, b = ends, np.concatenate([ends[m:], ends[:m]])  # every edge from both ends
    leader = np.zeros(k, bool)
    leader[ends[np.concatenate([lead_src, lead_dst])]] = True
    comp = np.arange(k)
    while True:  # the least place among the neighbours, then jumps
        new = comp.copy()
        np.minimum.at(new, comp[a], comp[b])
        new = np.minimum(new, new[comp])
        while (new[new] != new).any():
            new = new[new]
        if (new == comp).all():
            break
        comp = new
    led = np.zeros(k, bool)
    led[comp[leader]] = True
    target = leader | (~led[comp] & (comp == np.arange(k)))
    order = np.argsort(a, kind="stable")
    near, at = b[order], np.searchsorted(a[order], np.arange(k + 1))
    distance = np.where(target, 0, -1)
    front, d = np.flatnonzero(target), 0
    while len(front):
        d += 1
        count = at[front + 1] - at[front]
        reached = near[np.repeat(at[front] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())]
        front = np.unique(reached[distance[reached] < 0])
        distance[front] = d
    hop = np.full(k, np.iinfo(np.int64).max)
    nearer = distance[b] == distance[a] - 1
    np.minimum.at(hop, a[nearer], ids[b[nearer]])
    hops = pa.array(hop, mask=distance == 0)
    return pa.table([ids, np.where(led[comp], n - distance, 0), np.bincount(comp, minlength=k)[comp], np.full(k, sample, np.int32), hops, led[comp], ids[comp]], ["v", "x", "size", "sample", "hop", "comp_has_leader", "comp_key"])


def solve_sample(samples: DataFrame, p: Params, portable: bool = False) -> DataFrame:
    """For each vertex of each sample: how near its component's leader is (x = n - distance, 0 without leader), the
    component's size, and the neighbour one step nearer to the target (its nearest leader, else the least vertex).
    A sample is one task; see ``solve_samples_by_joins`` for samples beyond ``SAMPLE_LIMIT`` edges."""

    def boss(table: pa.Table) -> pa.Table:
        src, dst, ls, ld = (table[c].to_numpy() for c in ("src", "dst", "ls", "ld"))
        return _solved(table["sample"][0].as_py(), src, dst, ls, ld, p.n)

    return with_leaders(samples, p, portable).groupBy("sample").applyInArrow(boss, MESSAGE)


def best_of_samples(samples: DataFrame, p: Params, portable: bool = False) -> DataFrame:
    """v, x, size, sample, hop: of the messages of ``solve_sample`` the largest of each vertex in each task, so that m
    samples give a row a task and vertex instead of one a sample and vertex; and of how many messages (held).  A task
    solves its samples one by one."""
    names = ["v", "x", "size", "sample", "hop"]

    def largest(parts: list[list[np.ndarray]]) -> list[np.ndarray]:
        cols = [np.concatenate(c) for c in zip(*parts, strict=True)]
        order = np.lexsort((cols[2], cols[1], cols[0]))  # stable, and samples come in order: the last of equals has the largest
        cols = [c[order] for c in cols]
        last = np.concatenate([cols[0][1:] != cols[0][:-1], [True]])
        held = np.diff(np.concatenate([[0], np.cumsum(cols[5])[last]]))
        return [*(c[last] for c in cols[:5]), held]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        now, own = None, []

        def solve() -> None:
            src, dst, ls, ld = (np.concatenate(c) for c in zip(*own, strict=True))
            own.clear()
            t = _solved(now, src, dst, ls, ld, p.n)
            held.append([t[c].to_numpy() if c != "hop" else t[c].fill_null(-1).to_numpy() for c in names] + [np.ones(len(t), np.int64)])
            if sum(len(h[0]) for h in held) > MERGE_ROWS:
                held[:] = [largest(held)]

        for batch in batches:
            sample, *cols = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(5))
            bounds = [0, *(np.flatnonzero(sample[1:] != sample[:-1]) + 1).tolist(), len(sample)]
            for b, e in zip(bounds, bounds[1:], strict=False):
                if e > b:
                    if own and sample[b] != now:
                        solve()
                    now = int(sample[b])
                    own.append([c[b:e] for c in cols])
        if own:
            solve()
        if held:
            best = largest(held)
            yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int32) if n == "sample" else c.astype(np.int64)) for n, c in zip([*names, "held"], best, strict=True)], [*names, "held"])

    flagged = with_leaders(samples, p, portable).select("sample", "src", "dst", "ls", "ld")
    return flagged.repartition("sample").sortWithinPartitions("sample").mapInArrow(run, "v long, x long, size long, sample int, hop long, held long")


def _roots_by_joins(up: DataFrame) -> DataFrame:
    """sample, v, up, lead with every pointer at its root: pointers double by joins, and those at a root rest.  up: the
    same columns, acyclic; a root points to itself."""
    rest, known = up.where("up <> v").withColumn("open", F.lit(True)), up.where("up = v")
    ended = None
    while True:
        over = rest if ended is None else ended.unionByName(rest)
        over = over.select("sample", F.col("v").alias("up"), F.col("up").alias("next"), F.col("open").alias("more"))
        step = cut(rest.drop("open").join(over, ["sample", "up"], "left").select("sample", "v", F.coalesce("next", "up").alias("up"), "lead", F.coalesce("more", F.lit(False)).alias("open")))
        done, rest = step.where("NOT open"), step.where("open")
        ended = done if ended is None else ended.unionByName(done)
        if rest.isEmpty():
            return known.unionByName(ended.drop("open"))


def _components_by_joins(edges: DataFrame) -> DataFrame:
    """sample, v, comp (the least vertex), lead from edges (sample, v, u, lead of v) in both directions: every vertex points
    to its least lesser neighbour.  Only an edge to another lesser neighbour can join two trees; such edges, if their
    trees differ, are solved in the same way on the trees."""
    near = cut(edges.groupBy("sample", "v").agg(F.min("u").alias("u"), F.count_if(F.col("u") < F.col("v")).alias("lesser"), F.max("lead").alias("lead")))
    labels = _roots_by_joins(near.select("sample", "v", F.least("v", "u").alias("up"), "lead")).withColumnRenamed("up", "comp")
    several = near.where("lesser > 1").select("sample", "v", F.col("u").alias("least"))
    if several.isEmpty():
        return labels
    spare = edges.where("u < v").join(several, ["sample", "v"]).where("u <> least").select("sample", "v", "u")
    a, b = (labels.select("sample", F.col("v").alias(c), F.col("comp").alias(f"c{c}")) for c in ("v", "u"))
    over = cut(spare.join(a, ["sample", "v"]).join(b, ["sample", "u"]).where("cv <> cu").select("sample", F.least("cv", "cu").alias("a"), F.greatest("cv", "cu").alias("b")).distinct())
    if over.isEmpty():
        return labels
    ends = F.explode(F.array(F.struct(F.col("a").alias("v"), F.col("b").alias("u")), F.struct(F.col("b").alias("v"), F.col("a").alias("u"))))
    more = _components_by_joins(over.select("sample", ends.alias("e")).select("sample", "e.*", F.lit(False).alias("lead")))
    return labels.join(more.select("sample", F.col("v").alias("comp"), F.col("comp").alias("to")), ["sample", "comp"], "left").select("sample", "v", F.coalesce("to", "comp").alias("comp"), "lead")


def solve_samples_by_joins(samples: DataFrame, p: Params, portable: bool = False) -> DataFrame:
    """As ``solve_sample``, with no sample in one task: components of all samples at once by pointers, and distances along
    the edges, a join a step.  A step takes only what the steps before have left open."""
    since, spark = mark(), samples.sparkSession
    ends = F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u"), F.col("ls").alias("lead")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u"), F.col("ld").alias("lead"))))
    edges = cut(with_leaders(samples, p, portable).select("sample", ends.alias("e")).select("sample", "e.*"))
    labels = _components_by_joins(edges)
    whole = labels.groupBy("sample", "comp").agg(F.count(F.lit(1)).alias("size"), F.max("lead").alias("led"))
    state = cut(labels.join(whole, ["sample", "comp"]).withColumn("target", F.col("lead") | (~F.col("led") & (F.col("v") == F.col("comp")))))
    sweep(spark, since, edges, state)
    found = state.select("sample", "v", F.lit(0).alias("d"), F.lit(None).cast("long").alias("hop")).where("false")
    rest, front, d = edges.select("sample", "v", "u"), state.where("target").select("sample", "v"), 0
    while True:  # the least neighbour that the last step reached is a vertex's hop
        d += 1
        rest = cut(rest.join(front.select("sample", "v"), ["sample", "v"], "left_anti"))
        if rest.isEmpty():
            break
        front = cut(rest.join(front.select("sample", F.col("v").alias("u")), ["sample", "u"]).groupBy("sample", "v").agg(F.min("u").alias("hop")))
        found = found.unionByName(front.select("sample", "v", F.lit(d).alias("d"), "hop"))
        sweep(spark, since, state, found, rest, front)
    sweep(spark, since, state, found)
    x = F.when(F.col("led"), F.lit(p.n) - F.coalesce("d", F.lit(0))).otherwise(0).cast("long")
    return state.join(found, ["sample", "v"], "left").select("v", x.alias("x"), "size", "sample", "hop", F.col("led").alias("comp_has_leader"), F.col("comp").alias("comp_key"))


def best_message(messages: DataFrame) -> DataFrame:
    """v, hop of each vertex's largest (x, size, sample, hop)."""
    best = F.max(F.struct("x", "size", "sample", F.coalesce("hop", F.lit(-1)).alias("hop")))
    return messages.groupBy("v").agg(best.alias("m")).select("v", F.nullif(F.col("m.hop"), F.lit(-1)).alias("hop"))


def contract_by_samples(g: EdgeSet, p: Params, labels_only: bool = False, keep_messages: bool = True, portable: bool = False, sample_limit: int = SAMPLE_LIMIT, dealt_limit: int = DEALT_LIMIT, count_messages: bool = False) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """labels (vid, comp), forest and the messages.  ``portable``: coins that other SQL engines can repeat.  ``labels_only``: vertices take the least leader that any sample
    component of theirs holds; no forest comes of it.  Without ``keep_messages`` they aren't written, only folded,
    and more than ``dealt_limit`` edges of all samples are drawn in the tasks that solve them (the messages are then None); with
    ``count_messages`` the largest of each task and vertex are written, and of how many they are (held)."""
    g = g.settle()
    # coins that take an md5 are flipped once an end of an edge and not once a sample
    samples = sample_edges(with_leaders(g.edges, p, True) if portable else g.edges, p.num_samples, p.p_edge, p.seed, portable)
    count = g.edges.count()
    small, pointers = p.p_edge * count <= sample_limit, None
    if not (keep_messages or labels_only or portable or count_messages) and count <= sample_limit and p.num_samples * p.p_edge * count > dealt_limit:
        messages, pointers = None, best_hops(g.edges, p)
    elif not small:
        messages = solve_samples_by_joins(samples, p, portable)
    elif keep_messages or labels_only:
        messages = solve_sample(samples, p, portable)
    else:
        messages = best_of_samples(samples, p, portable)
    if keep_messages or labels_only or count_messages:
        messages = cut(messages if "held" in messages.columns else messages.withColumn("held", F.lit(1).cast("long")) if count_messages else messages)
    if labels_only:
        led = messages.where(coin(p.seed, "leader", "v", portable=portable) < p.p_leader).groupBy("sample", "comp_key").agg(F.min("v").alias("leader"))
        own = messages.join(led, ["sample", "comp_key"]).groupBy("v").agg(F.min("leader").alias("comp"))
        labels = g.vertices.join(own, F.col("vid") == F.col("v"), "left").select("vid", F.when(coin(p.seed, "leader", "vid", portable=portable) < p.p_leader, F.col("vid")).otherwise(F.coalesce("comp", "vid")).alias("comp"))
        return cut(labels), g.edges.select("src", "dst").where("false"), messages
    pointers = best_message(messages) if pointers is None else pointers
    parents, n = cut_and_count(g.vertices.join(pointers, F.col("vid") == F.col("v"), "left").select("vid", F.coalesce("hop", "vid").alias("parent")))
    labels = pointer_double(parents, count=n).withColumnRenamed("root", "comp")
    forest = parents.where("vid <> parent").select(F.least("vid", "parent").alias("src"), F.greatest("vid", "parent").alias("dst")).distinct()
    return labels, forest, messages
