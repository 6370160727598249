"""Near-duplicate documents by BagMinHash signatures, bands, and exact verification of multiset overlap.

Documents are multisets of word shingles.  A shingle's weight, its count, is cut at 1, 2, 4, 8 and so on; each piece of
weight carries a Poisson process in time whose points have a slot of the signature and a place inside the piece.  A
document keeps, for every slot, its earliest point whose place lies below its own weight.  Two documents keep the same
point with the probability of their weighted Jaccard similarity.  Points are drawn in rising time, piece by piece, and
a piece stops as soon as its next point comes later than the latest slot, so long texts need about one draw a shingle.

Equal texts are one node from the start.  Slots are joined to bands; nodes that share a band are candidates.  In each
bucket one node at a time is compared with all nodes of other classes, by the exact weighted overlap of their
multisets; the classes are updated, and a bucket ends when it holds a single class.  Members that have too many
shingles of their own, which no other document of these buckets has, to be similar to anyone leave it.  After
``rounds`` such rounds the members that are left are dealt by bucket, in blocks of bounded size that meet two by two, and their
pairs of different classes are settled in place: by size and own shingles, by the share of equal slots (which loses a
pair of similarity 0.8 with a chance of one in a million; ``slots_least=None`` leaves this test out), or by exact overlap.  So every candidate
pair ends up settled or in one class already, no pair leaves its task unless it is a link, and a bucket of near copies
costs about a comparison for each member.

Defined results: a text without words is a class of its own; a text of fewer words than a shingle is one shingle, the
whole text; texts with the same words are in one class; the class id is the least doc_id of the class (null only if
all its ids are null); rows may share ids.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from . import textnum as tn
from .spool import dropped, kept

WORDS, BANDS, ROWS = 5, 20, 5
SIMILARITY = 0.8
BLOCK_BYTES = 32 << 20
SLOTS_LEAST = 0.2  # below the wanted similarity; of 100 slots a similarity of 0.8 keeps 60 but for one pair in a million
U = np.uint64


def multisets(data: np.ndarray, offsets: np.ndarray, words: int = WORDS) -> tuple[tn.Words, np.ndarray, np.ndarray, np.ndarray]:
    """Words; then document, shingle hash and weight of all distinct shingles, in order of document and hash."""
    w = tn.words_of(data, offsets, hashes=2)
    at, h = tn.windows(w, words)
    doc = w.doc[at]
    short = np.flatnonzero((w.counts > 0) & (w.counts < words))
    if len(short):
        ends = np.cumsum(w.counts)
        whole = np.array([tn.joined([w.hash[e - n : e][k : k + 1] for k in range(n)], 9)[0] for e, n in zip(ends[short].tolist(), w.counts[short].tolist(), strict=True)], U)
        doc, h = np.concatenate([doc, short]), np.concatenate([h, whole])
    # one number a shingle: document in front, 44 bits of the hash behind
    key = np.sort((doc.astype(U) << U(44)) | (h >> U(20)))
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    return w, (key[first] >> U(44)).astype(np.int64), key[first] & U((1 << 44) - 1), np.diff(np.append(first, len(key)))


def signatures(doc: np.ndarray, element: np.ndarray, weight: np.ndarray, n: int, slots: int, seed: int = 1) -> np.ndarray:
    """BagMinHash signatures, n rows of ``slots`` 32-bit values."""
    best = np.full(n * slots, np.inf)
    with np.errstate(over="ignore"):
        stream = tn.mix(element + U(seed) * U(0xA0761D6478BD642F))
        # pieces of weight: [0, 1), then [1, 2), [2, 4), [4, 8) and so on
        pieces = [(doc, stream, weight, 0, 1)]
        low = 1
        while (more := weight > low).any():
            pieces.append((doc[more], tn.mix(stream[more] + U(low)), weight[more], low, low))
            low *= 2
        d, s, w = (np.concatenate([p[k] for p in pieces]) for k in range(3))
        base = np.concatenate([np.full(len(p[0]), p[3]) for p in pieces])
        size = np.concatenate([np.full(len(p[0]), p[4]) for p in pieces])
        t = np.zeros(len(d))
        while len(d):
            s = tn.mix(s + U(0x9E3779B97F4A7C15))
            t = t - np.log(((s >> U(11)).astype(float) + 0.5) * 2.0**-53) / size
            latest = best.reshape(n, slots).max(1)
            going = t < latest[d]
            d, s, w, base, size, t = d[going], s[going], w[going], base[going], size[going], t[going]
            draw = tn.mix(s ^ U(0x8EBC6AF09C88C6E3))
            slot = ((draw >> U(32)) * U(slots) >> U(32)).astype(np.int64)
            place = base + ((draw & U(0xFFFFFFFF)) * size.astype(U) >> U(32)).astype(np.int64)
            inside = place < w
            np.minimum.at(best, d[inside] * slots + slot[inside], t[inside])
    return (tn.mix(best.view(U)) >> U(32)).astype(np.uint32).reshape(n, slots)


def _print(w: tn.Words) -> list[bytes | None]:
    """16 bytes that stand for each document's words in order; None without words."""
    ends = np.cumsum(w.counts)
    place = (np.arange(len(w.doc)) - (ends - w.counts)[w.doc]).astype(U)
    out = []
    for h in w.hashes:
        with np.errstate(over="ignore"):
            total = np.concatenate([np.zeros(1, U), np.cumsum(tn.mix(h + tn.mix(place)))])
        out.append(tn.mix(total[ends] - total[ends - w.counts] + w.counts.astype(U)))
    raw = np.stack(out, 1).tobytes()
    return [raw[16 * k : 16 * k + 16] if n else None for k, n in enumerate(w.counts.tolist())]


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, words: int = WORDS) -> DataFrame:
    """doc_id, node (16 bytes for the text's words, null without words) and signature of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            for i, j in tn.slices(offsets, rows=4096):
                w, doc, element, weight = multisets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], words)
                sig = signatures(doc, element, weight, j - i, bands * rows)
                yield pa.RecordBatch.from_arrays([part.column(0).slice(i, j - i).cast(pa.int64()), pa.array(_print(w), pa.binary()), pa.array([r.tobytes() for r in sig], pa.binary())], ["doc_id", "node", "signature"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, node binary, signature binary")


def similarity_of(a: bytes, b: bytes) -> float:
    """Weighted Jaccard similarity of two packed multisets."""
    x, y = np.frombuffer(a, U), np.frombuffer(b, U)
    both = np.concatenate([x, y])
    both.sort()
    common = int((both[1:] == both[:-1]).sum())
    return common / max(1, len(x) + len(y) - common)


def packed(data: np.ndarray, offsets: np.ndarray, words: int = WORDS) -> tuple[tn.Words, list[bytes]]:
    """Each document's multiset as distinct numbers: the k-th copy of a shingle has a number of its own."""
    w, doc, element, weight = multisets(data, offsets, words)
    first = np.cumsum(weight) - weight
    copy = (np.arange(int(weight.sum())) - np.repeat(first, weight)).astype(U)
    with np.errstate(over="ignore"):
        number = tn.mix(np.repeat(element, weight) + copy * U(0xE7037ED1A0B428DB))
    bound = np.searchsorted(np.repeat(doc, weight), np.arange(len(offsets)))
    return w, [number[b:e].tobytes() for b, e in zip(bound[:-1].tolist(), bound[1:].tolist(), strict=True)]


def _bags(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """node and multiset of the wanted (doc_id, node)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            w, bags = packed(data, offsets, words)
            nodes, want = _print(w), part.column(2).to_pylist()
            take = [k for k, n in enumerate(nodes) if n is not None and n == want[k]]
            yield pa.RecordBatch.from_arrays([pa.array([nodes[k] for k in take], pa.binary()), pa.array([bags[k] for k in take], pa.binary())], ["node", "bag"])

    return docs.select("doc_id", "text").join(wanted, "doc_id").select("doc_id", "text", "node").mapInArrow(run, "node binary, bag binary")


def _verified(pairs: DataFrame, bags: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) of nodes whose multisets overlap enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [similarity_of(x.as_py(), y.as_py()) >= similarity for x, y in zip(batch.column(2), batch.column(3), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good, pa.bool_()))

    one = bags.select(F.col("node").alias("a"), F.col("bag").alias("x"))
    two = bags.select(F.col("node").alias("b"), F.col("bag").alias("y"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "x", "y").mapInArrow(run, "a binary, b binary")


def _mixed(here: DataFrame) -> DataFrame:
    """The rows of buckets that hold several classes."""
    several = kept(here.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high").select("bucket"))
    return kept(here.join(several, "bucket"))


def _facts(bags: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, size (shingles) and own (shingles that no other of these nodes has)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, bag in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                h = np.frombuffer(bag, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(np.full(len(h), key))], ["h", "key"])

    own = bags.join(nodes, "node").withColumn("key", F.xxhash64("node"))
    counted = own.select("key", "bag").mapInArrow(run, "h long, key long").groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("key"))
    single = counted.where("n = 1").groupBy("key").agg(F.count(F.lit(1)).alias("own"))
    return own.select("node", "key", (F.length("bag") / 8).cast("long").alias("size")).distinct().join(single, "key", "left").select("node", "size", F.coalesce("own", F.lit(0)).cast("long").alias("own"))


def _most(size, own, other_size, other_own):
    """The largest similarity two multisets can have, given their sizes and what no other multiset has."""
    common = F.least(size - own, other_size - other_own)
    return common / (size + other_size - common)


def _linkable(here: DataFrame, similarity: float) -> DataFrame:
    """The rows of buckets that hold several classes, without the members that no partner in their bucket can be similar
    enough to: even the best partner's size, between what a member shares at most and the bucket's least size, gives too
    little."""
    facts = kept(here.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.min("size").alias("least")).where("low <> high").select("bucket", "least"))
    shared = F.col("size") - F.col("own")
    best = F.greatest(F.col("least"), shared)
    return kept(here.join(facts, "bucket").where(shared / (best + F.col("own")) >= similarity).drop("least"))


def _settled(members: list[tuple], similarity: float, rows: int, slots_least: float | None = SLOTS_LEAST) -> list[tuple[bytes, bytes]]:
    """Links between members (node, label, size, own, block, signature, bag) of one bucket that join its classes."""
    n = len(members)
    sig = np.frombuffer(b"".join(m[5] for m in members), np.uint32).reshape(n, -1)
    bands = sig.reshape(n, -1, rows)
    alike = (bands == bands[:1]).all((0, 2))  # bands in which all members agree
    names: dict[bytes, int] = {}
    label = np.array([names.setdefault(m[1], len(names)) for m in members])
    size, own, block = (np.array([m[k] for m in members], float) for k in (2, 3, 4))
    apart = len(set(block)) > 1  # two blocks meet: pairs within one are settled elsewhere
    links = []
    for i in range(n - 1):
        j = np.flatnonzero(label[i + 1 :] != label[i]) + i + 1
        if apart:
            j = j[block[j] != block[i]]
        common = np.minimum(size[i] - own[i], size[j] - own[j])
        j = j[common >= similarity * (size[i] + size[j] - common)]
        same = sig[j] == sig[i]
        j, same = j[(close := same.mean(1) >= (-1.0 if slots_least is None else similarity - slots_least))], same[close]
        first = same.reshape(len(j), sig.shape[1] // rows, rows).all(2).argmax(1)  # a pair is settled where it meets first
        for k in j[alike[first]].tolist():
            if label[k] != label[i] and similarity_of(members[i][6], members[k][6]) >= similarity:
                links.append((members[i][0], members[k][0]))
                label[label == label[k]] = label[i]
    return links


def _finished(here: DataFrame, signed: DataFrame, bags: DataFrame, similarity: float, rows: int, slots_least: float | None) -> DataFrame:
    """Links (a, b) between the classes of the buckets' members."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, members = None, []

        def done() -> pa.RecordBatch:
            links = _settled(members, similarity, rows, slots_least) if len(members) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([x for x, _ in links], pa.binary()), pa.array([y for _, y in links], pa.binary())], ["a", "b"])

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if row[:3] != key:
                    if members:
                        yield done()
                    key, members = row[:3], []
                members.append(row[3:])
        if members:
            yield done()

    parts = kept(here.groupBy("bucket").agg(F.ceil(F.sum(F.col("size") * 8 + 1000) / BLOCK_BYTES).cast("int").alias("n")))
    dealt = here.join(parts, "bucket").withColumn("block", F.pmod(F.xxhash64("node"), F.col("n")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    whole = kept(signed.join(here.select("node").distinct(), "node", "left_semi").join(bags, "node"))
    full = dealt.join(whole, "node").select("bucket", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "node", "label", "size", "own", "block", "signature", "bag")
    return full.repartition("bucket", "low", "high").sortWithinPartitions("bucket", "low", "high", "node").mapInArrow(run, "a binary, b binary").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def classes(links: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """node and label (its class's least node) of all nodes of some links (a, b), by hooking and pointer jumping; with
    ``labels`` of earlier links these too, joined further by the new links alone.

    Written tables on both sides of each join let the engine split a hot label."""
    if labels is not None:
        a = labels.select(F.col("node").alias("a"), F.col("label").alias("la"))
        b = labels.select(F.col("node").alias("b"), F.col("label").alias("lb"))
        over = kept(links.join(a, "a", "left").join(b, "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b")).where("a <> b").distinct())
        step = classes(over).select(F.col("node").alias("label"), F.col("label").alias("next"))
        # a node without label is its own in ``over``
        return kept(labels.join(step, "label", "full_outer").select(F.coalesce("node", "label").alias("node"), F.coalesce("next", "label").alias("label")))
    while True:
        both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = kept(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")))
        while True:
            over = up.select(F.col("node").alias("label"), F.col("label").alias("next"))
            seen = Observation()
            moved = kept(up.join(over, "label").select("node", F.col("next").alias("label"), (F.col("next") < F.col("label")).alias("moved")).observe(seen, F.count_if("moved").alias("n")))
            dropped(up)
            up = moved.drop("moved")
            if not seen.get["n"]:
                break
        if labels is None:
            labels = up
        else:
            step = up.select(F.col("node").alias("label"), F.col("label").alias("next"))
            labels = kept(labels.join(step, "label", "left").select("node", F.coalesce("next", "label").alias("label")))
        a = up.select(F.col("node").alias("a"), F.col("label").alias("la"))
        b = up.select(F.col("node").alias("b"), F.col("label").alias("lb"))
        seen = Observation()
        links = kept(links.join(a, "a").join(b, "b").where("la <> lb").select(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b")).distinct().observe(seen, F.count(F.lit(1)).alias("n")))
        if not seen.get["n"]:
            return labels


def near_classes(docs: DataFrame, similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS, words: int = WORDS, rounds: int = 3, slots_least: float | None = SLOTS_LEAST) -> DataFrame:
    """doc_id, class_id, n_links (verified links of the row's text, exact copies aside) and copies (rows with the same
    words) for every row."""
    spark: SparkSession = docs.sparkSession
    sketched = kept(sketch(docs, bands, rows, words))
    # the signature of a node's words is the same in all its rows
    nodes = kept(sketched.where("node IS NOT NULL").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies"), F.first("signature").alias("signature")))
    signed = nodes.where("doc_id IS NOT NULL").select("node", "signature")
    nodes = nodes.drop("signature")
    in_bucket = signed.select("node", F.explode(F.array(*(F.xxhash64(F.substring("signature", 1 + 4 * rows * k, 4 * rows), F.lit(k)) for k in range(bands)))).alias("bucket"))
    full = kept(in_bucket.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("bucket"))
    left = kept(in_bucket.join(full, "bucket"))
    bags = kept(_bags(docs, left.select("node").distinct().join(nodes, "node").where("doc_id IS NOT NULL").select("doc_id", "node"), words))
    links, labels, facts = None, None, None
    done = False
    for k in range(rounds + 1):
        if left.isEmpty():
            break
        if labels is None:
            here = left.withColumn("label", F.col("node"))
        else:  # buckets that hold several classes go on, with those members that can have a link at all
            here = kept(left.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")))
            if facts is None:  # from here on the rows carry them
                here = _mixed(here)
                facts = kept(_facts(bags, here.select("node").distinct()))
                here = kept(here.join(facts, "node"))
            here = _linkable(here, similarity)
        if k < rounds:
            rank = F.struct("node", "label") if facts is None else F.struct((F.col("own") / F.col("size")).alias("share"), "node", "label", "size", "own")
            chosen = kept(here.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.min(rank).alias("c")).where("low <> high").select("bucket", "c"))
            left = kept(here.join(chosen, "bucket").where("node <> c.node"))
            pairs = left.where("label <> c.label").withColumns({"a": F.col("node"), "b": F.col("c.node")})
            if facts is not None:
                pairs = pairs.where(_most(F.col("size"), F.col("own"), F.col("c.size"), F.col("c.own")) >= similarity)
            left = left.select("bucket", "node", *([] if facts is None else ["size", "own"]))
            new = kept(_verified(pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), bags, similarity))
        else:  # what is left, whole
            new, done = kept(_finished(_mixed(here), signed, bags, similarity, rows, slots_least)), True
        links = new if links is None else links.unionByName(new)
        if not new.isEmpty():
            labels = classes(new, labels)
        elif labels is None:
            labels = spark.createDataFrame([], "node binary, label binary")
        if done:
            break
    if links is None:
        links, labels = spark.createDataFrame([], "a binary, b binary"), spark.createDataFrame([], "node binary, label binary")
    degree = links.select(F.col("a").alias("node")).unionByName(links.select(F.col("b").alias("node"))).groupBy("node").agg(F.count(F.lit(1)).alias("n_links"))
    known = nodes.join(labels, "node", "left").join(degree, "node", "left").select("node", "doc_id", "copies", F.coalesce("label", "node").alias("label"), F.coalesce("n_links", F.lit(0)).alias("n_links"))
    known = kept(known)
    least = kept(known.groupBy("label").agg(F.min("doc_id").alias("class_id")))
    named = kept(known.join(least, "label").select("node", "class_id", "n_links", "copies"))
    rows_ = sketched.select("doc_id", "node").join(named, "node", "left")
    return rows_.select("doc_id", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("copies", F.lit(1)).cast("long").alias("copies"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The documents with the least doc_id of every class, with all columns.  Rows without id stay; rows that share the
    least id of a class stay together."""
    found = near_classes(docs, **options)
    gone = kept(found.where("class_id IS NOT NULL AND (doc_id IS NULL OR doc_id <> class_id)").select(F.col("doc_id").alias("_gone")).where("_gone IS NOT NULL").distinct())
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
