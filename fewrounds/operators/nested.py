"""Nested connectivity instances: encodings, proxies for busy vertices, and all instances at once."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spool import cut, cut_and_count
from .blocks import restored, squeezed
from .components import TASK_LIMIT, ComponentResult, _solve, complete_partition
from .connectivity import connected_components
from .graphs import TAG, EdgeSet, disjoint_union, relabel, symmetrize
from .relational import global_rank, prefix_sum
from .sampling import contract_by_samples
from .sparsify import Split, sparsify_by_degree

SHIFT = TAG * 64


def encode_nested(edges: DataFrame) -> DataFrame:
    """u, v, first_instance: each vertex's neighbours with the first instance that has the edge."""
    return symmetrize(edges.select("src", "dst", "first_instance")).groupBy("u", "v").agg(F.min("first_instance").alias("first_instance"))


def decode(encoded: DataFrame, instance: int) -> DataFrame:
    """The edges of one instance from the encoding."""
    return encoded.where((F.col("first_instance") <= instance) & (F.col("u") < F.col("v"))).select(F.col("u").alias("src"), F.col("v").alias("dst"))


def decode_all(encoded: DataFrame, count: int) -> DataFrame:
    """instance, src, dst of every instance from the encoding."""
    return expanded(encoded.where("u < v").select(F.col("u").alias("src"), F.col("v").alias("dst"), "first_instance"), count)


def expanded(edges: DataFrame, count: int) -> DataFrame:
    """instance, src, dst of all instances; for sizes where count times the edges is small."""
    return edges.select(F.explode(F.sequence("first_instance", F.lit(count))).alias("instance"), "src", "dst")


def expand_at_proxies(encoded: DataFrame, proxies: DataFrame, count: int) -> DataFrame:
    """proxy, instance, u, v: the edges of all instances, unfolded where they are served.

    A vertex's encoding goes to those of its proxies that simulate it in an instance with the edge; each proxy unfolds
    its own few instances after the exchange, so neither the exchange nor any key carries all instances of a busy
    vertex."""
    rows = encoded.join(proxies, encoded["u"] == proxies["vid"])
    first = F.least(F.floor((F.col("first_instance") - 1) / F.col("per_proxy")), F.col("proxies") - 1)
    dealt = rows.where(F.col("first_instance") <= count).withColumn("k", F.explode(F.sequence(first, F.least(F.col("proxies") - 1, F.greatest(first, F.floor(F.lit(count - 1) / F.col("per_proxy")))))))
    low = F.greatest(F.col("first_instance"), F.col("k") * F.col("per_proxy") + 1).cast("int")
    high = F.when(F.col("k") == F.col("proxies") - 1, F.lit(count)).otherwise(F.least(F.lit(count), (F.col("k") + 1) * F.col("per_proxy"))).cast("int")
    sent = dealt.select((F.col("first_proxy") + F.col("k")).alias("proxy"), "u", "v", low.alias("low"), high.alias("high")).where("low <= high").repartition("proxy")
    return sent.select("proxy", "u", "v", F.explode(F.sequence("low", "high")).alias("instance"))


def union_of_nested(edges: DataFrame, vertices: DataFrame, count: int) -> EdgeSet:
    """All instances side by side as one graph, unfolded at proxies.  edges: src, dst, first_instance."""
    encoded = cut(encode_nested(edges))
    deg = encoded.groupBy(F.col("u").alias("vid")).agg(F.count(F.lit(1)).alias("d"))
    proxies = cut(assign_proxies(deg, max(vertices.count(), 1)))
    served = expand_at_proxies(encoded, proxies, count).where("u < v")
    return disjoint_union(served.select("instance", F.col("u").alias("src"), F.col("v").alias("dst")), vertices, count)


UNFOLD_LIMIT = 2_000_000  # edges over all instances that are unfolded without a look for such as join nothing
SIDE_LIMIT = 200_000  # vertices over all instances that are solved side by side in one graph
BATCH_ROWS = 1 << 16  # labels that a task hands on at a time


def joining_edges(edges: DataFrame, count: int, limit: int = TASK_LIMIT) -> DataFrame:
    """src, dst, first_instance without edges whose ends edges of the same or earlier instances join already, as far as a
    task with a block of at most about ``limit`` edges can tell.  Every instance keeps its components."""

    def run(table: pa.Table) -> pa.Table:
        first, src, dst = (table[c].to_numpy() for c in ("first_instance", "src", "dst"))
        order = np.lexsort((dst, src, first))
        _, used = _solve(src[order], dst[order])
        return pa.table([x[order][used] for x in (src, dst, first)], ["src", "dst", "first_instance"])

    rest, left = cut_and_count(edges.where(F.col("first_instance") <= count).select("src", "dst", F.col("first_instance").cast("int").alias("first_instance")))
    while True:
        blocks, before = -(-left // limit), left
        if not left:
            return rest
        rest, left = cut_and_count(rest.groupBy(F.pmod(F.xxhash64("src", "dst"), F.lit(blocks)).alias("block")).applyInArrow(run, "src long, dst long, first_instance int"))
        if blocks == 1 or 2 * left > before:
            return rest


def components_of_nested(edges: DataFrame, vertices: DataFrame, count: int, mode: str = "parallel", unfold_limit: int = UNFOLD_LIMIT, side_limit: int = SIDE_LIMIT) -> DataFrame:
    """instance, vid, comp.  ``parallel`` solves all instances at once, side by side, and if they have more than
    ``unfold_limit`` edges in all, unfolds only those that join something; more than ``side_limit`` vertices over all
    instances go in two levels.  ``incremental`` adds run after run to the partition so far, one step an instance."""
    if mode == "parallel":
        if (edges.agg(F.sum(F.greatest(F.lit(0), F.lit(count + 1) - F.col("first_instance")))).first()[0] or 0) > unfold_limit:
            edges = joining_edges(edges, count)
        if count > 3 and count * vertices.count() > side_limit:
            return _by_levels(edges, vertices, count, unfold_limit, side_limit)
        labels = connected_components(union_of_nested(edges, vertices, count)).labels
        return labels.select(F.floor(F.col("vid") / SHIFT).cast("int").alias("instance"), (F.col("vid") % SHIFT).alias("vid"), (F.col("comp") % SHIFT).alias("comp"))
    few = joining_edges(edges, count)
    if max(few.count(), vertices.count()) <= TASK_LIMIT:
        return _run_by_run(few, vertices, count)
    labels, out = cut(vertices.select("vid", F.col("vid").alias("comp"))), None
    for i in range(1, count + 1):
        own = relabel(few.where(F.col("first_instance") == i).select("src", "dst"), labels)
        links = own.select(F.col("cu").alias("u"), F.col("cv").alias("v"), F.col("e.src").alias("e_src"), F.col("e.dst").alias("e_dst"))
        to, _ = complete_partition(links)
        labels = cut(labels.join(to.select(F.col("vid").alias("comp"), F.col("comp").alias("to")), "comp", "left").select("vid", F.coalesce("to", "comp").alias("comp")))
        row = labels.select(F.lit(i).alias("instance"), "vid", "comp")
        out = row if out is None else out.unionByName(row)
    return out


def _by_levels(edges: DataFrame, vertices: DataFrame, count: int, unfold_limit: int, side_limit: int) -> DataFrame:
    """instance, vid, comp of all instances: first of every step-th instance, side by side; then of the instances behind
    each of these, side by side too, on its components and only the edges that come after it.  A component is named
    by its least vertex on both levels, so names are those of one level."""
    step = math.ceil(math.sqrt(count))
    last = (count - 1) // step
    behind = F.floor((F.col("first_instance") - 1) / step).cast("int")
    coarse = components_of_nested(edges.select("src", "dst", (behind + 1).alias("first_instance")).where(F.col("first_instance") <= last), vertices, last, "parallel", unfold_limit, side_limit)
    base = cut(coarse.select(F.col("instance").alias("k"), "vid", "comp").unionByName(vertices.select(F.lit(0).alias("k"), "vid", F.col("vid").alias("comp"))))
    rest = edges.where(F.col("first_instance") <= count).select("src", "dst", behind.alias("k"), (F.col("first_instance") - behind * step).cast("int").alias("j"))
    for end, comp in (("src", "cu"), ("dst", "cv")):
        rest = rest.join(base.select("k", F.col("vid").alias(end), F.col("comp").alias(comp)), ["k", end])
    rest = cut(rest.where("cu <> cv").groupBy("k", F.least("cu", "cv").alias("cu"), F.greatest("cu", "cv").alias("cv")).agg(F.min("j").alias("first_instance")))
    ends = rest.select("k", F.explode(F.array("cu", "cv")).alias("comp")).distinct()
    names = cut(global_rank(ends, ["k", "comp"], "id"))  # components of all levels as vertices of one graph, in their order
    if names.isEmpty():
        found = names.select("k", "comp", F.lit(None).cast("array<bigint>").alias("to"))
    else:
        own = rest
        for end, c in (("src", "cu"), ("dst", "cv")):
            own = own.join(names.select("k", F.col("comp").alias(c), F.col("id").alias(end)), ["k", c])
        fine = components_of_nested(own.select("src", "dst", "first_instance"), names.select(F.col("id").alias("vid")), step, "parallel", unfold_limit, side_limit)
        named = fine.join(names.select(F.col("id").alias("comp"), F.col("comp").alias("name")), "comp")
        lists = named.groupBy("vid").agg(F.array_sort(F.collect_list(F.struct("instance", "name"))).alias("to"))
        found = cut(names.join(lists.select(F.col("vid").alias("id"), F.col("to.name").alias("to")), "id").select("k", "comp", "to"))
    every = base.join(found, ["k", "comp"], "left").select("k", "vid", "comp", "to", F.explode(F.sequence(F.lit(1), F.least(F.lit(step), F.lit(count) - F.col("k") * step))).alias("j"))
    return every.select((F.col("k") * step + F.col("j")).cast("int").alias("instance"), "vid", F.coalesce(F.col("to")[F.col("j") - 1], "comp").alias("comp"))


def _run_by_run(edges: DataFrame, vertices: DataFrame, count: int, blocks: int | None = None) -> DataFrame:
    """instance, vid, comp, run after run: every run is contracted by the partition before it, and what it joins goes into
    the partition.  A task takes a block of instances in a row, the vertices and the edges, packed, and starts with the
    partition before its block.  edges: those that join something."""
    tasks = min(count, blocks or 2 * edges.sparkSession.sparkContext.defaultParallelism)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([squeezed(c.to_numpy())], pa.binary()) for c in batch.columns], ["src", "dst", "first_instance"])

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[list[np.ndarray]]] = {}
        for batch in batches:
            for block, *parts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.setdefault(block, []).append([restored(x) for x in parts])
        for block in sorted(held):
            src, dst, first = (np.concatenate(x) for x in zip(*held.pop(block), strict=True))
            ids = np.unique(src[first == 0])  # a vertex comes as a loop of run 0
            order = np.argsort(first, kind="stable")[len(ids) :]
            src, dst, first = np.searchsorted(ids, src[order]), np.searchsorted(ids, dst[order]), first[order]
            comp, rows, at = np.arange(len(ids)), [], 0
            for i in range(1 + block * count // tasks, 1 + (block + 1) * count // tasks):
                to = int(np.searchsorted(first, i, "right"))
                u, v = comp[src[at:to]], comp[dst[at:to]]
                at, open_ = to, u != v
                if open_.any():
                    sets, _ = _solve(u[open_], v[open_])
                    up = np.arange(len(ids))
                    moved = np.fromiter(sets.up, np.int64, len(sets.up))
                    up[moved] = [sets.find(x) for x in moved.tolist()]
                    comp = up[comp]
                rows.append((np.full(len(ids), i, np.int32), ids, ids[comp]))
                if len(rows) * len(ids) >= BATCH_ROWS:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*rows, strict=True)], ["instance", "vid", "comp"])
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*rows, strict=True)], ["instance", "vid", "comp"])

    own = edges.select("src", "dst", F.col("first_instance").cast("long")).unionByName(vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst"), F.lit(0).cast("long").alias("first_instance")))
    packed = own.mapInArrow(pack, "src binary, dst binary, first_instance binary")
    dealt = packed.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("block"), "src", "dst", "first_instance").repartitionById(tasks, F.col("block"))
    return dealt.mapInArrow(solve, "instance int, vid long, comp long")


def bucket_kruskal(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """src, dst of the forest: each run solved by a task of its own, contracted by the instance before it.
    labels: instance, vid, comp of all instances."""
    before = labels.select((F.col("instance") + 1).alias("first_instance"), "vid", "comp")
    a = before.select("first_instance", F.col("vid").alias("src"), F.col("comp").alias("cu"))
    b = before.select("first_instance", F.col("vid").alias("dst"), F.col("comp").alias("cv"))
    first = edges.where("first_instance = 1").select("first_instance", "src", "dst", "weight", F.col("src").alias("cu"), F.col("dst").alias("cv"))
    rest = edges.join(a, ["first_instance", "src"]).join(b, ["first_instance", "dst"]).select("first_instance", "src", "dst", "weight", "cu", "cv")
    run = first.unionByName(rest).where("cu <> cv")

    def solve(table: pa.Table) -> pa.Table:
        weight, src, dst, u, v = (table[c].to_numpy() for c in ("weight", "src", "dst", "cu", "cv"))
        order = np.lexsort((dst, src, weight))
        _, used = _solve(u[order], v[order])
        return pa.table([src[order][used], dst[order][used]], ["src", "dst"])

    return run.groupBy("first_instance").applyInArrow(solve, "src long, dst long")


def assign_proxies(deg: DataFrame, n: int, chunk: int | None = None) -> DataFrame:
    """vid, d, proxies, first_proxy, per_proxy: l = ceil(d / chunk) proxies in vertex order; each serves per_proxy
    instances."""
    size = chunk or math.ceil(math.sqrt(n))
    own = deg.where("d > 0").withColumn("proxies", F.ceil(F.col("d") / size).cast("long"))
    summed = prefix_sum(own, ["vid"], "proxies", "upto")
    return summed.select("vid", "d", "proxies", (F.col("upto") - F.col("proxies")).alias("first_proxy"), F.least(F.lit(math.ceil(math.sqrt(n))), F.ceil(F.lit(n) / F.col("d"))).cast("long").alias("per_proxy"))


def deliver_to_proxies(encoded: DataFrame, proxies: DataFrame) -> DataFrame:
    """proxy, u, received (neighbours dealt to the proxy), all (neighbours after the proxies of u have exchanged)."""
    spread = encoded.join(proxies, encoded["u"] == proxies["vid"]).withColumn("slot", F.pmod(F.xxhash64("u", "v"), F.col("proxies")))
    return spread.groupBy((F.col("first_proxy") + F.col("slot")).alias("proxy"), "u").agg(F.count(F.lit(1)).alias("received"), F.max("d").alias("all"))


def instance_proxy(instances: DataFrame, proxies: DataFrame) -> DataFrame:
    """vid, instance, proxy: who simulates a vertex in an instance."""
    return proxies.join(instances).select("vid", "instance", (F.col("first_proxy") + F.least(F.floor((F.col("instance") - 1) / F.col("per_proxy")), F.col("proxies") - 1)).alias("proxy"))


def nested_sparsify(edges: DataFrame, vertices: DataFrame, count: int, s: int) -> tuple[EdgeSet, Split]:
    """Sparsification of all instances side by side."""
    union = union_of_nested(edges, vertices, count).settle()
    return union, sparsify_by_degree(union, s)


def nested_contract(part: EdgeSet, params) -> tuple[DataFrame, DataFrame]:
    """Sample contraction of all instances side by side; bosses are keyed by the sample, instances never meet."""
    labels, forest, _ = contract_by_samples(part, params)
    return labels, forest


def nested_finish(union: EdgeSet, labels: DataFrame, forest: DataFrame) -> ComponentResult:
    from .sketches import finish_by_sketches

    return finish_by_sketches(union, labels, forest)


def routing_feasible(messages: DataFrame, n: int, c: float) -> DataFrame:
    """max_sent, max_received and whether both are within c * n.  messages: sender, receiver."""
    sent = messages.groupBy("sender").agg(F.count(F.lit(1)).alias("k")).agg(F.max("k").alias("max_sent"))
    got = messages.groupBy("receiver").agg(F.count(F.lit(1)).alias("k")).agg(F.max("k").alias("max_received"))
    return sent.join(got).withColumn("feasible", (F.col("max_sent") <= c * n) & (F.col("max_received") <= c * n))


def auxiliary_schedule(c: int) -> list[tuple[int, int]]:
    """The rounds, (a, b) each, by which c auxiliary nodes a node exchange: sender's a-th with receiver's b-th."""
    return [(a, b) for a in range(c) for b in range(c)]


def _top_neighbour(a: np.ndarray, b: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Each vertex's neighbour of the largest (rank, place), -1 for none; a, b: every edge from both ends."""
    k = len(rank)
    key = np.full(k, -1, np.int64)
    np.maximum.at(key, a, rank[b] * k + b)
    return np.where(key < 0, -1, key % k)


def _split(src: np.ndarray, dst: np.ndarray, k: int, s: int) -> tuple[int, int, int, int, int]:
    """awake components, the least size of one (0: none), the largest degree of part B, and the edges of both parts, by
    the two stages of ``sparsify_by_degree`` on one graph of k vertices."""
    a, b, own = np.concatenate([src, dst]), np.concatenate([dst, src]), np.arange(k)
    deg = np.bincount(a, minlength=k)
    hook = _top_neighbour(a, b, deg)
    up = np.where(hook < 0, own, hook)
    mutual = (hook >= 0) & (up[up] == own)
    up = np.where(mutual & (deg * k + own > deg[up] * k + up), own, up)  # of a mutual pair the higher one is the root
    while (up[up] != up).any():
        up = up[up]
    comp, cdeg = np.full(k, k), np.zeros(k, np.int64)
    np.minimum.at(comp, up, own)
    np.maximum.at(cdeg, up, deg)
    comp, cdeg = comp[up], cdeg[up]
    over = comp[a] != comp[b]
    hook = _top_neighbour(a[over], b[over], cdeg * k + comp)
    hooked = np.flatnonzero(hook >= 0)
    sets, _ = _solve(comp[hooked], comp[hook[hooked]])
    comp = np.array([sets.find(x) for x in comp.tolist()], np.int64)
    top = np.zeros(k, np.int64)
    np.maximum.at(top, comp, cdeg)
    awake = top[comp] >= s
    size = np.bincount(comp[awake], minlength=k)
    size = size[size > 0]
    in_a = awake[src] & awake[dst]
    deg_b = np.bincount(np.concatenate([src[~in_a], dst[~in_a]]), minlength=1)
    return len(size), int(size.min(initial=k + 1)) if len(size) else 0, int(deg_b.max()), int(in_a.sum()), int((~in_a).sum())


def split_measures_in_tasks(edges: DataFrame, vertices: DataFrame, count: int, s: int, blocks: int | None = None) -> DataFrame:
    """instance, awake_components, least_size, deg_b, edges_a, edges_b of every instance's sparsification.  A task takes a
    block of instances and the edges once, packed, with the first instance of each, and unfolds one instance at a time."""
    tasks = min(count, blocks or 2 * edges.sparkSession.sparkContext.defaultParallelism)
    n = vertices.count()
    own = edges.where(F.col("first_instance") <= count).select("src", "dst", F.col("first_instance").cast("long"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([squeezed(c.to_numpy())], pa.binary()) for c in batch.columns], ["src", "dst", "first_instance"])

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[list[np.ndarray]]] = {}
        for batch in batches:
            for block, *parts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.setdefault(block, []).append([restored(x) for x in parts])
        for block in sorted(held):
            src, dst, first = (np.concatenate(x) for x in zip(*held.pop(block), strict=True))
            order = np.argsort(first, kind="stable")
            ids, ends = np.unique(np.concatenate([src[order], dst[order]]), return_inverse=True)
            src, dst, first = ends[: len(src)], ends[len(src) :], first[order]
            rows = []
            for i in range(1 + block, count + 1, tasks):
                m = int(np.searchsorted(first, i, "right"))
                rows.append((i, *_split(src[:m], dst[:m], len(ids), s)))
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], ["instance", "awake_components", "least_size", "deg_b", "edges_a", "edges_b"])

    packed = own.mapInArrow(pack, "src binary, dst binary, first_instance binary")
    dealt = packed.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("block"), "src", "dst", "first_instance").repartitionById(tasks, F.col("block"))
    out = cut(dealt.mapInArrow(solve, "instance long, awake_components long, least_size long, deg_b long, edges_a long, edges_b long"))
    return out.withColumn("n", F.lit(n).cast("long"))


def nested_split_measures(edges: DataFrame, vertices: DataFrame, count: int, s: int, blocks: int | None = None) -> DataFrame:
    """What ``analysis.split_measures`` tells of all instances side by side, from the measures of each."""
    m = split_measures_in_tasks(edges, vertices, count, s, blocks)
    total = m.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("awake_components", "edges_a", "edges_b")), F.min(F.when(F.col("awake_components") > 0, F.col("least_size"))).alias("least"), F.coalesce(F.max("deg_b"), F.lit(0)).alias("deg_b"), F.coalesce(F.max("n"), F.lit(0)).alias("n"))
    return total.select("awake_components", F.coalesce("least", F.lit(0)).alias("least_size"), "deg_b", "edges_a", "edges_b", (F.col("awake_components") * s <= F.col("n") * count).alias("count_ok"), (F.coalesce("least", F.lit(s + 1)) >= s + 1).alias("size_ok"), (F.col("deg_b") < s).alias("degree_ok"))
