"""Sampled segmentation into sentence pieces, and lossless decoding.

A text becomes characters with the space mark in place of spaces and one mark in front, as the model's own encoder has
it.  All pieces that match anywhere form a lattice.  Forward filtering sums the weights of all paths to each place;
backward sampling then draws, from the end, each last piece in proportion to its share.  The draws come from a hash of
the seed, the row's key and the place in the text, so they are the same on any cluster and after any retry.

No piece of these models crosses a space mark that follows another character, and characters outside all pieces stand
alone, so the lattice falls into units between such places; the filter runs once for each different unit, and the
draws of all units of many texts run side by side.

Weights: a model whose scores are log probabilities gives them itself; a model whose scores are merge ranks gives
``-log(rank + 3)``; ``alpha`` scales both.  Characters without a piece, and space marks that stand in the text itself,
become UTF-8 byte pieces, so decoding always gives back the text.

Defined results: null and empty texts have no pieces and decode to the empty text; rows are encoded alone, a null key
counts as a key of its own.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textnum as tn

MARK = 0x2581
LITERAL = 0x110000  # a space mark that the text itself holds
LEXICON_CHARS = 500_000  # known units are forgotten beyond this
LEARN_CHARS = 60_000  # characters of new units that are filtered at a time; a longer unit alone
BYTES = -1


class _Table:
    """Numbers by 64-bit key: an open-addressing table that looks up whole arrays."""

    def __init__(self, items: dict[int, int]):
        self.bits = max(4, (4 * len(items)).bit_length())
        self.keys, self.values = np.zeros(1 << self.bits, np.uint64), np.full(1 << self.bits, -1, np.int64)
        keys = np.array(list(items), np.uint64)
        for slot, k in zip(self._slot(keys).tolist(), items, strict=True):
            while self.values[slot] >= 0:
                slot = (slot + 1) & ((1 << self.bits) - 1)
            self.keys[slot], self.values[slot] = k, items[k]

    def _slot(self, h: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, h: np.ndarray) -> np.ndarray:
        """The number of each key, -1 for those not here."""
        slot = self._slot(h)
        out = self.values[slot]
        other = np.flatnonzero((out >= 0) & (self.keys[slot] != h))
        while len(other):
            slot[other] = (slot[other] + 1) & ((1 << self.bits) - 1)
            out[other] = self.values[slot[other]]
            other = other[(out[other] >= 0) & (self.keys[slot[other]] != h[other])]
        return out


def _cp_hash_parts(cps: np.ndarray) -> np.ndarray:
    return tn.mix(cps.astype(np.uint64) + np.uint64(77)) | np.uint64(1)


class Lattice:
    """Pieces of one model with their weights, and the units seen so far."""

    def __init__(self, path: str, alpha: float):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        scores = np.array([sp.get_score(i) for i in range(n)])
        self.byte_ids = np.full(256, -1, np.int64)
        names, usable = [], []
        for i in range(n):
            p = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte_ids[int(p[3:5], 16)] = i
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)) and p:
                usable.append(i)
            names.append(p)
        if (self.byte_ids < 0).any():
            raise ValueError("the model needs byte pieces, else decoding can't be lossless")
        own = scores[usable]
        if len(own) and (own == np.round(own)).all():  # merge ranks
            weights = -np.log(-own - (-own).min() + 3.0)
        else:
            weights = own.astype(float)
        weights = alpha * weights
        self.byte_weight = float(weights.min()) - 1.0 if len(own) else -1.0
        # by length: hashes of the beginnings of pieces, with the piece that ends there or BYTES
        self.longest = max((len(names[i]) for i in usable), default=1)
        power, _ = tn._tables(self.longest + 1, 0)
        begins: list[dict[int, tuple[int, float]]] = [{} for _ in range(self.longest + 1)]
        alphabet: set[int] = set()
        self.mark_inside = False
        for i, w in zip(usable, weights, strict=True):
            cps = np.array([ord(c) for c in names[i]])
            alphabet.update(cps.tolist())
            self.mark_inside |= chr(MARK) in names[i].lstrip(chr(MARK))
            with np.errstate(over="ignore"):
                h = np.cumsum(_cp_hash_parts(cps) * power[: len(cps)]).tolist()
            for k in range(1, len(cps)):
                begins[k].setdefault(h[k - 1], (BYTES, 0.0))
            begins[len(cps)][h[-1]] = (i, float(w))
        self.begins = []
        for found in begins:
            self.begins.append((_Table({h: k for k, h in enumerate(found)}), np.array([p for p, _ in found.values()], np.int64), np.array([w for _, w in found.values()])))
        self.alphabet = np.zeros(LITERAL + 1, bool)
        self.alphabet[sorted(alphabet)] = True
        # decoding: bytes of each piece, end to end
        texts = [bytes([int(p[3:5], 16)]) if sp.is_byte(i) else b"" if sp.is_control(i) else p.replace(chr(MARK), " ").encode() for i, p in enumerate(names)]
        self.piece_size = np.array([len(x) for x in texts], np.int64)
        self.piece_at = np.concatenate([[0], np.cumsum(self.piece_size)[:-1]])
        self.piece_bytes = np.frombuffer(b"".join(texts), np.uint8)
        self.forget()

    def forget(self) -> None:
        self.known = np.zeros(0, np.uint64)  # sorted unit hashes
        self.known_first = np.zeros(0, np.int64)  # first node of each
        self.n_nodes = 0
        self.node_edge = np.zeros(0, np.int64)  # first edge of each node
        self.edge_share = np.zeros(0)  # cumulative within a node
        self.edge_piece = np.zeros(0, np.int32)
        self.edge_size = np.zeros(0, np.int32)

    def learn(self, cps: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Edges into every node of some units by forward filtering: cumulative shares, pieces, sizes; first edge of
        each node; first node of each unit.

        A unit of L characters has nodes 1 to L, its characters' ends."""
        total = int(sizes.sum())
        first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        unit = np.repeat(np.arange(len(sizes)), sizes)
        local = np.arange(total) - first[unit]
        own = cps[starts[unit] + local]
        left = sizes[unit] - local  # characters from here to the unit's end
        power, inverse = tn._tables(total + 1, 0)
        with np.errstate(over="ignore"):
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_cp_hash_parts(own) * power[:total])])
        at, node, piece, size, weight = np.arange(total), [], [], [], []
        single = np.zeros(total, bool)
        for k in range(1, self.longest + 1):
            at = at[left[at] >= k]
            if not len(at):
                break
            table, pieces, weights = self.begins[k]
            with np.errstate(over="ignore"):
                h = (sums[at + k] - sums[at]) * inverse[at]
            j = table.get(h)
            same = j >= 0
            at, j = at[same], j[same]
            full = pieces[j] >= 0
            if k == 1:
                single[at[full]] = True
            node.append(at[full] + k - 1)
            piece.append(pieces[j][full])
            size.append(np.full(int(full.sum()), k))
            weight.append(weights[j][full])
        bare = np.flatnonzero(~single)
        n_bytes = 1 + (own[bare] > 0x7F) + (own[bare] > 0x7FF) + ((own[bare] > 0xFFFF) & (own[bare] != LITERAL))
        node, piece, size = np.concatenate([*node, bare]), np.concatenate([*piece, np.full(len(bare), BYTES)]), np.concatenate([*size, np.ones(len(bare), np.int64)])
        weight = np.concatenate([*weight, self.byte_weight * n_bytes])
        # filter: places in order, all units at once
        order = np.argsort((local[node] * total + node) * 64 + np.minimum(size, 63))
        node, piece, size, weight = node[order], piece[order], size[order], weight[order]
        alpha = np.zeros(total)  # log of the weights of all paths to the node
        place = local[node]
        cut = np.flatnonzero(np.diff(place, prepend=-1, append=-2))
        share = np.empty(len(node))
        for b, e in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            n, s = node[b:e], size[b:e]
            before = np.where(s <= place[b], alpha[n - s], 0.0)
            x = before + weight[b:e]
            heads = np.flatnonzero(np.diff(n, prepend=-1))
            top = np.maximum.reduceat(x, heads)
            group = np.cumsum(np.diff(n, prepend=n[0]) != 0)
            y = np.exp(x - top[group])
            whole = np.add.reduceat(y, heads)
            alpha[n[heads]] = top + np.log(whole)
            share[b:e] = y / whole[group]
        order = np.argsort(node - 0.5 * share, kind="stable")  # the likeliest edge of a node comes first
        node, piece, size, share = node[order], piece[order], size[order], share[order]
        heads = np.flatnonzero(np.diff(node, prepend=-1))
        tails = np.append(heads[1:], len(node)) - 1
        rising, at, last = share.copy(), heads, tails
        while len(at):  # within each node alone, so that a unit's numbers never depend on its neighbours
            at, last = at[at < last] + 1, last[at < last]
            rising[at] += rising[at - 1]
        rising[tails] = 2.0  # the last edge of a node takes what rounding leaves
        return rising, piece.astype(np.int32), size.astype(np.int32), heads, first

    def units(self, cps: np.ndarray, text_starts: np.ndarray) -> np.ndarray:
        """Starts of the lattice's units."""
        if self.mark_inside:
            return np.unique(text_starts)
        mark, bare = cps == MARK, ~self.alphabet[cps]
        begin = np.zeros(len(cps), bool)
        begin[text_starts] = True
        begin[1:] |= (mark[1:] & ~mark[:-1]) | bare[1:] | bare[:-1]
        return np.flatnonzero(begin)

    def add(self, cps: np.ndarray, hashes: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> None:
        """Makes some units known, a bounded part of them at a time."""
        ends = np.concatenate([[0], np.cumsum(sizes)])
        edges, shares, pieces, lengths, firsts = [self.node_edge], [self.edge_share], [self.edge_piece], [self.edge_size], [self.known_first]
        n_edges = len(self.edge_share)
        for i, j in tn.slices(ends, LEARN_CHARS):
            share, piece, size, heads, first = self.learn(cps, starts[i:j], sizes[i:j])
            firsts.append(first + (self.n_nodes + ends[i]))
            edges.append(heads + n_edges)
            shares.append(share)
            pieces.append(piece)
            lengths.append(size)
            n_edges += len(share)
        self.node_edge, self.edge_share = np.concatenate(edges), np.concatenate(shares)
        self.edge_piece, self.edge_size = np.concatenate(pieces), np.concatenate(lengths)
        known, first = np.concatenate([self.known, hashes]), np.concatenate(firsts)
        order = np.argsort(known)
        self.known, self.known_first = known[order], first[order]
        self.n_nodes += int(ends[-1])

    def encode(self, data: np.ndarray, offsets: np.ndarray, row_keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids, end to end, and how many each text has."""
        n = len(offsets) - 1
        if not len(data):
            return np.zeros(0, np.int64), np.zeros(n, np.int64)
        cps = np.frombuffer(data.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32).astype(np.int64)
        chars = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])[offsets]
        cps[cps == MARK] = LITERAL
        cps[cps == 0x20] = MARK
        some = np.flatnonzero(np.diff(chars) > 0)
        cps = np.insert(cps, chars[:-1][some], MARK)
        sizes = np.diff(chars) + (np.diff(chars) > 0)
        ends = np.cumsum(sizes)
        text_starts = (ends - sizes)[some]
        starts = self.units(cps, text_starts)
        length = np.diff(np.append(starts, len(cps)))
        values = _cp_hash_parts(cps)
        power, inverse = tn._tables(len(cps) + 1, 0)
        with np.errstate(over="ignore"):
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values * power[: len(cps)])])
            h = tn.mix((sums[starts + length] - sums[starts]) * inverse[starts] + length.astype(np.uint64))
        distinct, where, back = np.unique(h, return_index=True, return_inverse=True)
        place = np.minimum(np.searchsorted(self.known, distinct), max(len(self.known) - 1, 0))
        new = self.known[place] != distinct if len(self.known) else np.ones(len(distinct), bool)
        if new.any():
            if self.n_nodes + int(length[where[new]].sum()) > LEXICON_CHARS and self.n_nodes:
                self.forget()
                new[:] = True
            self.add(cps, distinct[new], starts[where[new]], length[where[new]])
        first = self.known_first[np.searchsorted(self.known, distinct)][back]
        # backward sampling, all units at once
        text = np.searchsorted(ends, starts, "right")
        ids = np.full(len(cps), -2, np.int64)
        left, at_unit = length.copy(), np.arange(len(starts))
        seeds = row_keys[text]
        with np.errstate(over="ignore"):
            origin = (ends - sizes)[text]
            while len(at_unit):
                s = starts[at_unit]
                where_in_text = (s - origin[at_unit] + left).astype(np.uint64)
                u = (tn.mix(seeds[at_unit] + where_in_text * np.uint64(0xD1B54A32D192ED03)) >> np.uint64(11)).astype(float) * 2.0**-53
                edge = self.node_edge[first[at_unit] + left - 1]
                beyond = np.flatnonzero(u >= self.edge_share[edge])
                while len(beyond):
                    edge[beyond] += 1
                    beyond = beyond[u[beyond] >= self.edge_share[edge[beyond]]]
                step = self.edge_size[edge]
                left = left - step
                ids[s + left] = self.edge_piece[edge]
                going = left > 0
                if not going.all():
                    at_unit, left = at_unit[going], left[going]
        out_at = np.flatnonzero(ids > -2)
        ids = ids[out_at]
        counts = np.searchsorted(out_at, ends) - np.searchsorted(out_at, ends - sizes)
        bare = np.flatnonzero(ids == BYTES)
        if len(bare):  # characters that become bytes
            code = cps[out_at[bare]]
            raw = [chr(MARK if c == LITERAL else c).encode() for c in code.tolist()]
            grow = np.ones(len(ids), np.int64)
            grow[bare] = [len(r) for r in raw]
            owner = np.repeat(np.arange(n), counts)
            counts = np.bincount(owner, weights=grow, minlength=n).astype(np.int64)
            ids = np.repeat(ids, grow)
            ids[ids == BYTES] = self.byte_ids[np.frombuffer(b"".join(raw), np.uint8)]
        return ids, counts

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes and offsets of the texts; the mark in front of each text goes again."""
        size = self.piece_size[ids]
        ends = np.cumsum(size)
        total = int(ends[-1]) if len(ends) else 0
        where = np.repeat(self.piece_at[ids] - (ends - size), size) + np.arange(total)
        data = self.piece_bytes[where]
        upto = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(counts)])]
        some = np.flatnonzero(np.diff(upto) > 0)
        data = np.delete(data, upto[:-1][some])
        gone = np.zeros(len(upto), np.int64)
        gone[some + 1] = 1
        return data, upto - np.cumsum(gone)


@lru_cache(maxsize=4)
def lattice(path: str, alpha: float) -> Lattice:
    return Lattice(path, alpha)


def encoded(batches: Iterator[pa.RecordBatch], path: str, alpha: float, seed: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray, np.ndarray]]:
    """Parts of the batches with their ids, their numbers of pieces, and whether decoding gives back the text."""
    model = lattice(path, alpha)
    for part, data, offsets in tn.batched(batches, "text"):
        keys = part.column(part.schema.get_field_index("doc_id")).cast(pa.int64())
        numbers = np.array([-(1 << 62) if k is None else k for k in keys.to_pylist()], np.int64)
        with np.errstate(over="ignore"):
            row_keys = tn.mix(numbers.view(np.uint64) + tn.mix(np.array([seed], np.uint64)))
        ids, counts = model.encode(data, offsets, row_keys)
        back, upto = model.decode(ids, counts)
        if len(back) == len(data) and (back == data).all() and (upto == offsets).all():
            same = np.ones(len(counts), bool)
        else:
            same = np.array([back[upto[i] : upto[i + 1]].tobytes() == data[offsets[i] : offsets[i + 1]].tobytes() for i in range(len(counts))])
        yield part, ids, counts, same


def encode(docs: DataFrame, path: str, alpha: float = 1.0, seed: int = 0) -> DataFrame:
    """doc_id, pieces (array of ids), n_pieces, lossless for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, ids, counts, same in encoded(batches, path, alpha, seed):
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]), pa.int32()), pa.array(ids, pa.int32()))
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), lists, pa.array(counts), pa.array(same)], ["doc_id", "pieces", "n_pieces", "lossless"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, pieces array<int>, n_pieces long, lossless boolean")


def digest(docs: DataFrame, path: str, alpha: float = 1.0, seed: int = 0) -> DataFrame:
    """doc_id, n_pieces, ids_sha256 (of the ids as 4-byte little-endian numbers), lossless for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, ids, counts, same in encoded(batches, path, alpha, seed):
            raw, ends = ids.astype("<i4"), np.cumsum(counts)
            shas = [hashlib.sha256(raw[e - c : e].tobytes()).hexdigest() for e, c in zip(ends.tolist(), counts.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(counts), pa.array(shas, pa.string()), pa.array(same)], ["doc_id", "n_pieces", "ids_sha256", "lossless"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_pieces long, ids_sha256 string, lossless boolean")


def decode(rows: DataFrame, path: str) -> DataFrame:
    """doc_id and text from doc_id and pieces; null pieces give a null text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = lattice(path, 1.0)
        for batch in batches:
            lists = batch.column(1)
            counts = np.array([0 if v is None else v for v in pa.compute.list_value_length(lists).to_pylist()], np.int64)
            data, upto = model.decode(np.asarray(lists.flatten(), np.int64), counts)
            texts = [None if null else data[upto[i] : upto[i + 1]].tobytes().decode("utf-8") for i, null in enumerate(lists.is_null().to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(texts, pa.string())], ["doc_id", "text"])

    import pyarrow.compute  # noqa: F401  pa.compute

    return rows.select("doc_id", "pieces").mapInArrow(run, "doc_id long, text string")
