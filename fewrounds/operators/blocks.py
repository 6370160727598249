"""Samples drawn where they are solved: a task takes all edges and a block of samples, so no sample travels or is written."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import coin, mixed
from ..functions.params import Params

CHUNK = 1 << 16  # vertices whose pointers are compared at a time
PART = 1 << 17  # vertices of a sample, about, that are solved at a time
_FAR = np.iinfo(np.int32).max


def squeezed(x: np.ndarray) -> bytes:
    """Longs by planes of bytes, so that what they don't need takes no room."""
    return zlib.compress(np.ascontiguousarray(x, np.int64).view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def restored(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(data), np.uint8).reshape(8, -1).T).view(np.int64).ravel()


def drawn(seed: int, sample: int, count: int, p: float) -> np.ndarray:
    """The places, in the order of the edges, of those that a sample takes: each with probability p, in 32 bits."""
    if p >= 1:
        return np.arange(count)
    bits = np.random.Generator(np.random.PCG64([seed % (1 << 32), sample])).integers(0, 1 << 32, count, np.uint32)
    return np.flatnonzero(bits < np.uint32(min(round(p * (1 << 32)), (1 << 32) - 1)))


def _pointers(u: np.ndarray, v: np.ndarray, leader: np.ndarray, n: int, best: np.ndarray, torn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each vertex of one sample that is no leader: its place, (x, size) of its message in one number, and its hop
    (-1: none), if that number isn't below ``best``.  Vertices are places in order; the messages are those of
    ``solve_sample``.  Components with a vertex in ``torn`` are left out; also, which edges are theirs."""
    k = len(leader)
    up = np.arange(k, dtype=np.int32)
    x, y = u, v
    while len(x):  # roots hook to lesser roots
        np.minimum.at(up, np.maximum(x, y), np.minimum(x, y))
        x, y = (_top(up, z) for z in (x, y))
        open_ = x != y
        x, y = x[open_], y[open_]
    aside = np.zeros(len(u), bool)
    if len(torn):
        bad = np.zeros(k, bool)
        bad[_top(up, torn)] = True
        aside = bad[_top(up, u)]
        u, v = u[~aside], v[~aside]
    seen = np.zeros(k, bool)
    seen[u] = seen[v] = True
    t = np.flatnonzero(seen)
    root, lead = _top(up, t), leader[t]
    led = np.zeros(k, bool)
    led[root[lead]] = True
    led, size = led[root], np.bincount(root, minlength=k)[root]
    far = np.full(k, _FAR, np.int32)
    far[t[lead | (~led & (root == t))]] = 0
    x, y, d = u, v, 0
    while len(x):
        a, b = far[x], far[y]
        far[y[(a == d) & (b > d)]] = d + 1
        far[x[(b == d) & (a > d)]] = d + 1
        open_ = (far[x] == _FAR) | (far[y] == _FAR)
        x, y, d = x[open_], y[open_], d + 1
    key = (np.where(led, n - far[t].astype(np.int64), 0) << 32) | size
    new = np.flatnonzero((key >= best[t]) & ~lead)
    t, key = t[new], key[new]
    hop = np.full(k, _FAR, np.int32)
    seen[:] = False
    seen[t] = True
    some = np.flatnonzero(seen[u] | seen[v])
    u, v = u[some], v[some]
    a, b = far[u], far[v]
    np.minimum.at(hop, v[b == a + 1], u[b == a + 1])
    np.minimum.at(hop, u[a == b + 1], v[a == b + 1])
    return t, key, np.where(hop[t] == _FAR, -1, hop[t]), aside


def _top(up: np.ndarray, x: np.ndarray) -> np.ndarray:
    x = up[x]
    left = np.flatnonzero(up[x] != x)
    while len(left):
        to = up[x[left]]
        x[left] = to
        left = left[up[to] != to]
    return x


def _parts(a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
    """The part of each of k vertices: clusters grow along edges, to about a quarter of ``PART`` vertices, and are put
    together in parts of about ``PART``, so that few edges go from part to part."""
    if k <= PART:
        return np.zeros(k, np.int32)
    label, step = np.arange(k, dtype=np.int32), 0
    x, y = a, b
    while len(x):
        step += 1
        rank = (mixed(np.arange(k, dtype=np.uint64) + (np.uint64(step) << np.uint64(40))) >> np.uint64(33)).astype(np.int64) << 32 | np.arange(k)
        best = rank.copy()
        np.minimum.at(best, x, rank[y])
        np.minimum.at(best, y, rank[x])
        up = (best & 0xFFFFFFFF).astype(np.int32)  # the neighbour of the least rank, if that is less than its own
        label, x, y = _top(up, label), _top(up, x), _top(up, y)
        whole = np.bincount(label, minlength=k) >= max(PART // 4, 2)
        open_ = (x != y) & ~whole[x] & ~whole[y]
        x, y = x[open_], y[open_]
    size = np.bincount(label, minlength=k)
    return ((np.cumsum(size) - size) // PART).astype(np.int32)[label]


def _laid(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """ids; the vertices (places in ids) part by part, in order in each; the ends of the edges as places among these, by
    part and those between parts last, in one order however they came; and where each part's vertices and edges begin."""
    ids = np.unique(np.concatenate([src, dst]))
    k = len(ids)
    a, b = (z.astype(np.int32) for z in np.divmod(np.sort(np.searchsorted(ids, src) * k + np.searchsorted(ids, dst)), k))
    part = np.unique(_parts(a, b, k), return_inverse=True)[1].astype(np.int32)
    count = int(part.max(initial=-1)) + 1
    vertices = np.argsort(part, kind="stable").astype(np.int32)
    place = np.empty(k, np.int32)
    place[vertices] = np.arange(k, dtype=np.int32)
    of = np.where(part[a] == part[b], part[a], count)
    order = np.argsort(of, kind="stable")
    starts = np.searchsorted(part[vertices], np.arange(count + 1))
    return ids, vertices, place[a[order]], place[b[order]], starts, np.searchsorted(of[order], np.arange(count + 2))


def _best(samples: range, src: np.ndarray, dst: np.ndarray, leads: np.ndarray, p: Params) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, and of each the largest (x, size) over some samples (0: none) and the hop of the last sample that has it.  A
    sample is solved part by part, in memory that is near; what edges between parts tie together is solved last."""
    ids, vertices, a, b, starts, begins = _laid(src, dst)
    k, parts = len(ids), len(starts) - 1
    place = np.empty(k, np.int32)
    place[vertices] = np.arange(k, dtype=np.int32)
    leader = np.zeros(k, bool)
    leader[place[np.searchsorted(ids, np.concatenate([src[leads & 1 > 0], dst[leads & 2 > 0]]))]] = True
    best, hops = np.zeros(k, np.int64), np.full(k, -1, np.int32)
    none = np.zeros(0, np.int32)

    for sample in samples:
        own = drawn(p.seed, sample, len(a), p.p_edge)
        at = np.searchsorted(own, begins)
        u, v = a[own], b[own]
        tied = [(u[at[parts] :], v[at[parts] :])]
        torn = np.sort(np.concatenate(tied[0]))
        of = np.searchsorted(torn, starts)
        for q in range(parts):
            s, x, y = np.int32(starts[q]), u[at[q] : at[q + 1]], v[at[q] : at[q + 1]]
            if len(x):
                t, key, hop, aside = _pointers(x - s, y - s, leader[s : starts[q + 1]], p.n, best[s : starts[q + 1]], torn[of[q] : of[q + 1]] - s)
                best[t + s], hops[t + s] = key, np.where(hop < 0, -1, hop + s)
                tied.append((x[aside], y[aside]))
        x, y = (vertices[np.concatenate(z)] for z in zip(*tied, strict=True))
        if len(x):
            some = np.unique(np.concatenate([x, y]))
            near = place[some]
            t, key, hop, _ = _pointers(*(np.searchsorted(some, z).astype(np.int32) for z in (x, y)), leader[near], p.n, best[near], none)
            best[near[t]], hops[near[t]] = key, np.where(hop < 0, -1, near[hop])
    return ids, best[place], np.where(hops < 0, -1, vertices[hops])[place]


def best_hops(edges: DataFrame, p: Params, blocks: int | None = None) -> DataFrame:
    """v, hop: of all samples the hop of each vertex's largest message, as ``best_message`` has it; leaders, which stay
    where they are, have no row.  Every block of samples gets the edges once, packed, and gives one number and one hop a
    vertex, packed too.  All edges must fit in a task."""
    spark = edges.sparkSession
    count = min(p.num_samples, blocks or spark.sparkContext.defaultParallelism)  # each lays out all edges, so no more than run at a time
    flag = lambda c: (coin(p.seed, "leader", c) < p.p_leader).cast("int")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                src, dst, leads = (batch.column(k).to_numpy() for k in range(3))
                order = np.argsort(src)
                src, dst, leads = src[order], dst[order], leads[order]
                yield pa.RecordBatch.from_arrays([pa.array([squeezed(x)], pa.binary()) for x in (np.diff(src, prepend=0), dst - src, leads)], ["src", "dst", "leads"])

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[int, list[tuple]] = {}
        for batch in batches:
            for block, *parts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                own.setdefault(block, []).append(tuple(parts))
        for block in sorted(own):
            parts = [tuple(restored(x) for x in row) for row in own.pop(block)]
            src = np.concatenate([np.cumsum(x[0]) for x in parts])
            dst, leads = src + np.concatenate([x[1] for x in parts]), np.concatenate([x[2] for x in parts])
            parts = []
            samples = range(1 + block * p.num_samples // count, 1 + (block + 1) * p.num_samples // count)
            ids, best, hops = _best(samples, src, dst, leads, p)
            for at in range(0, len(ids), CHUNK):
                v, h = ids[at : at + CHUNK], hops[at : at + CHUNK]
                columns = (np.diff(v, prepend=0), best[at : at + CHUNK], np.where(h < 0, 0, ids[h] - v))  # 0: none, as no vertex is its own neighbour
                yield pa.RecordBatch.from_arrays([pa.array([at // CHUNK], pa.int32()), pa.array([block], pa.int32()), *(pa.array([squeezed(x)], pa.binary()) for x in columns)], ["chunk", "block", "v", "best", "hop"])

    def largest(table: pa.Table) -> pa.Table:
        best = None
        for row in table.sort_by("block").to_pylist():
            key, hop = restored(row["best"]), restored(row["hop"])
            best = (key, hop) if best is None else tuple(np.where(key >= best[0], new, old) for new, old in zip((key, hop), best, strict=True))
        v = np.cumsum(restored(row["v"]))
        some = best[0] > 0
        return pa.table([v[some], pa.array((v + best[1])[some], mask=(best[1] == 0)[some])], ["v", "hop"])

    packed = edges.select("src", "dst", (flag("src") + 2 * flag("dst")).alias("leads")).mapInArrow(pack, "src binary, dst binary, leads binary")
    dealt = packed.select(F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("block"), "src", "dst", "leads").repartitionById(count, F.col("block"))
    return dealt.mapInArrow(solve, "chunk int, block int, v binary, best binary, hop binary").groupBy("chunk").applyInArrow(largest, "v long, hop long")
