"""Sampled segmentations over a SentencePiece vocabulary: forward filtering, backward sampling.

A text is cut into units, each a run of spaces and the word behind it; pieces
never cross units, so the lattice of a text is that of its units in a row.  The
distinct units of a chunk are filtered together: all their edges come from a
hash table of pieces and of prefixes of pieces, and the forward sums go over
all units byte offset by byte offset.  Every occurrence of a unit is then
sampled backward with random words of its own, made from (seed, row key, place,
step): the same row gives the same pieces whatever its partition.

Edge probabilities are rounded to 32-bit integers, so sampling is exact
arithmetic.  Characters without a piece are spelled in byte pieces; a literal
U+2581 is spelled so too, which keeps decoding lossless.
"""

from __future__ import annotations

import hashlib
import itertools
import math
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import _BYTE, _BYTES_POW, mix, slice_batches, tidy_map

_U = np.uint64
_ONE = np.uint64(1) << np.uint64(32)


class _Table:
    """Open addressing by 64-bit hashes, read for many keys at once."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        size = 1 << max(8, int(len(keys) * 8).bit_length())
        self.mask = _U(size - 1)
        self.keys, self.values = np.zeros(size, np.uint64), np.full(size, -1, np.int64)
        self.probes = 1
        for k, v in zip(keys.tolist(), values.tolist(), strict=True):
            at, n = k & (size - 1), 1
            while self.values[at] >= 0:
                at, n = (at + 1) & (size - 1), n + 1
            self.keys[at], self.values[at] = k, v
            self.probes = max(self.probes, n)

    def get(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), -1, np.int64)
        for i in range(self.probes):
            at = (keys + _U(i)) & self.mask
            hit = self.keys[at] == keys
            out[hit] = self.values[at[hit]]
        return out


def _hash(data: bytes) -> int:
    up, _ = _BYTES_POW.get(len(data))
    return int(mix(np.array([(_BYTE[np.frombuffer(data, np.uint8)] * up).sum(dtype=np.uint64)], np.uint64))[0])


class Pieces:
    """A vocabulary as bytes, with log weights.

    `scores` are log probabilities of a unigram model: weights are flatness * score, and a byte has the least score less 10.
    Without them - merge models number their pieces in place of scores - weights go by rank: -flatness * log(2 + rank), a byte's
    being 1.5 times the last one's.
    """

    def __init__(self, pieces: list[bytes | None], byte_ids: list[int], dummy_prefix: bool = True, flatness: float = 1.0, scores: list[float] | None = None):
        self.bytes, self.byte_ids, self.dummy_prefix, self.flatness, self.scores = pieces, byte_ids, dummy_prefix, flatness, scores
        for p in pieces:
            if p and b" " in p.lstrip(b" "):
                raise ValueError("a piece crosses words")

    @classmethod
    def load(cls, path: str, flatness: float = 1.0) -> Pieces:
        """Of a SentencePiece model with byte pieces. Read on the driver alone; tasks get the vocabulary by broadcast."""
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces, byte_ids = [], [-1] * 256
        for i in range(sp.vocab_size()):
            name = sp.id_to_piece(i)
            if sp.is_byte(i):
                byte_ids[int(name[3:5], 16)] = i
            pieces.append(None if sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i) else name.replace("▁", " ").encode())
        if min(byte_ids) < 0:
            raise ValueError("the vocabulary has no byte pieces")
        scores = [sp.get_score(i) for i in range(sp.vocab_size())]
        told = [x for x, p in zip(scores, pieces, strict=True) if p]
        unigram = any(x != round(x) for x in told)  # merge models have whole numbers
        return cls(pieces, byte_ids, scores=scores if unigram else None, dummy_prefix=sp.encode("a") != sp.encode("▁a") or sp.id_to_piece(sp.encode("a")[0]).startswith("▁"), flatness=flatness)

    def prepare(self) -> Pieces:
        """Tables for tasks, made once a process."""
        if not hasattr(self, "table"):
            real = [(p, i) for i, p in enumerate(self.bytes) if p]
            prefixes = {p[:n]: -1 for p, _ in real for n in range(1, len(p) + 1)} | {p: i for p, i in reversed(real)}
            # value: 2 * (piece + 1) + whether a longer piece starts so
            longer = {p[:n] for p, _ in real for n in range(1, len(p))}
            self.table = _Table(np.array([_hash(p) for p in prefixes], np.uint64), np.array([2 * (i + 1) + (p in longer) for p, i in prefixes.items()], np.int64))
            n = len(self.bytes)
            if self.scores is None:
                self.weight = -self.flatness * np.log(2.0 + np.arange(n))
                self.byte_weight = -self.flatness * np.log(2.0 + n) * 1.5
            else:
                self.weight = self.flatness * np.array(self.scores, float)
                self.byte_weight = self.flatness * (min(x for x, p in zip(self.scores, self.bytes, strict=True) if p) - 10)
            self.spelled = [self.bytes[i] if self.bytes[i] else b"" for i in range(n)]
            for b, i in enumerate(self.byte_ids):
                self.spelled[i] = bytes([b])
            self.size = np.array([len(s) for s in self.spelled])
            self.flat = np.frombuffer(b"".join(self.spelled), np.uint8)
            self.offset = np.cumsum(self.size) - self.size
            self.byte_id = np.array(self.byte_ids)
        return self


def _edges(v: Pieces, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(from, to, piece) of all pieces within units; piece -1: the bytes of one character that no piece spells alone."""
    n = len(data)
    up, down = _BYTES_POW.get(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(_BYTE[data] * up[:n], out=total[1:])
    head = (data & 0xC0) != 0x80
    limit = np.repeat(end, end - start)  # units lie side by side
    at = np.flatnonzero(head)
    first, last, piece = [], [], []
    active = at
    size = 1
    char_end = np.append(at[1:], n)
    single = np.zeros(n, bool)
    width = np.zeros(n, np.int64)
    width[at] = char_end - at
    while len(active):
        active = active[active + size <= limit[active]]
        got = v.table.get(mix((total[active + size] - total[active]) * down[active]))
        hit = got >= 2
        piece_here = (got >> 1) - 1
        whole = hit & (piece_here >= 0)
        f = active[whole]
        first.append(f)
        last.append(f + size)
        piece.append(piece_here[whole])
        single[f[width[f] == size]] = True
        active = active[(got >= 0) & ((got & 1) == 1)]
        size += 1
    bare = at[~single[at]]
    first.append(bare)
    last.append(bare + width[bare])
    piece.append(np.full(len(bare), -1))
    return np.concatenate(first), np.concatenate(last), np.concatenate(piece)


#: Units of more bytes are summed one by one; shorter ones side by side, offset by offset.
_LONG = 2048


class Lattice:
    """Forward sums of distinct units, as integer thresholds of each node's edges. The work is linear in the bytes, whatever the units' lengths."""

    def __init__(self, v: Pieces, data: np.ndarray, size: np.ndarray):
        """data: the units' bytes side by side; size: bytes of each."""
        end = np.cumsum(size)
        start = end - size
        a, b, piece = _edges(v, data, start, end)
        begin = np.repeat(start, size)  # of the unit of each byte
        # nodes: a unit's byte offsets 1.. are known by their last byte's place; offset 0 sums to 1
        node = b - 1
        long = np.repeat(size > _LONG, size)[a]
        depth = np.where(long, _LONG + 1, b - begin[a])
        order = np.argsort((depth << 40) | (node << 8) | np.minimum(b - a, 255), kind="stable")  # edges come shortest first
        a, b, piece, node, depth = (x[order] for x in (a, b, piece, node, depth))
        weight = np.where(piece >= 0, v.weight[piece], v.byte_weight * (b - a))
        alpha = np.zeros(len(data))
        chance = np.zeros(len(a))
        is_first = a == begin[a]
        bounds = np.searchsorted(depth, np.arange(1, (depth.max() if len(depth) else 0) + 2))
        group = np.flatnonzero(np.concatenate((np.ones(min(1, len(node)), bool), node[1:] != node[:-1])))
        group_at = np.searchsorted(group, bounds)
        if long.any():
            self._one_by_one(bounds[_LONG], group, a, node, weight, is_first, alpha, chance)
        for d in range(min(len(bounds) - 1, _LONG)):
            lo, hi = bounds[d], bounds[d + 1]
            if lo == hi:
                continue
            g = group[group_at[d] : group_at[d + 1]]
            value = weight[lo:hi] + np.where(is_first[lo:hi], 0.0, alpha[np.maximum(a[lo:hi] - 1, 0)])
            count = np.diff(np.append(g, hi))
            top = np.maximum.reduceat(value, g - lo)
            part = np.exp(value - np.repeat(top, count))
            total = np.add.reduceat(part, g - lo)
            alpha[node[g]] = top + np.log(total)
            chance[lo:hi] = part / np.repeat(total, count)
        # thresholds by node: the last edge of each takes what rounding leaves
        share = np.floor(chance * float(_ONE)).astype(np.uint64)
        count = np.diff(np.append(group, len(node)))
        run = np.cumsum(share)
        within = run - np.repeat(run[group] - share[group], count)
        within[np.append(group[1:], len(node))[: len(group)] - 1] = _ONE
        self.a, self.piece, self.limit = a, piece, within
        self.edge = np.zeros(len(data), np.int64)
        self.edge[node[group]] = group
        self.start, self.end, self.data, self.log_total = start, end, data, alpha[end - 1]

    @staticmethod
    def _one_by_one(first: int, group: np.ndarray, a: np.ndarray, node: np.ndarray, weight: np.ndarray, is_first: np.ndarray, alpha: np.ndarray, chance: np.ndarray) -> None:
        """Forward sums of long units' nodes, edge by edge from the given one on."""
        start = [*group[np.searchsorted(group, first) :].tolist(), len(node)]
        before, w, fresh = (a[first:] - 1).tolist(), weight[first:].tolist(), is_first[first:].tolist()
        at = node[first:].tolist()
        sums: dict[int, float] = {}
        shares = []
        for lo, hi in itertools.pairwise(start):
            value = [w[e] + (0.0 if fresh[e] else sums[before[e]]) for e in range(lo - first, hi - first)]
            top = max(value)
            part = [math.exp(x - top) for x in value]
            total = sum(part)
            sums[at[lo - first]] = top + math.log(total)
            shares += [x / total for x in part]
        chance[first:] = shares
        alpha[np.fromiter(sums, np.int64, len(sums))] = np.fromiter(sums.values(), float, len(sums))

    def sample(self, unit: np.ndarray, noise: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(edge, edges of each occurrence) of occurrences of units, in reading order."""
        live, at, taken = np.arange(len(unit)), self.end[unit], []
        step = 0
        count = np.zeros(len(unit), np.int64)
        while len(live):
            u = mix(noise[live] + _U(step * 0x9E3779B97F4A7C15 & (2**64 - 1))) >> _U(32)
            edge = self.edge[at - 1]
            on = np.flatnonzero(u >= self.limit[edge])
            while len(on):
                edge[on] += 1
                on = on[u[on] >= self.limit[edge[on]]]
            taken.append((live, edge))
            count[live] += 1
            at = self.a[edge]
            more = at > self.start[unit[live]]
            live, at = live[more], at[more]
            step += 1
        out = np.zeros(count.sum(), np.int64)
        last = np.cumsum(count) - 1
        for step, (who, edge) in enumerate(taken):
            out[last[who] - step] = edge
        return out, count


def encode_texts(v: Pieces, texts: list[bytes], keys: np.ndarray, seed: int) -> list[np.ndarray]:
    """Piece ids of each text."""
    v.prepare()
    prefix = b" " if v.dummy_prefix else b""
    data = np.frombuffer(b"".join([prefix + t if t else t for t in texts]), np.uint8)
    if not len(data):
        return [np.zeros(0, np.int32)] * len(texts)
    text_end = np.cumsum([len(t) + len(prefix) if t else 0 for t in texts])
    # a unit starts with a text, and with the first of its spaces
    space = data == 32
    begins = space.copy()
    begins[1:] &= ~space[:-1]
    begins[0] = True
    begins[text_end[text_end < len(data)]] = True
    start = np.flatnonzero(begins)
    size = np.diff(np.append(start, len(data)))
    n = np.diff(np.concatenate(([0], np.searchsorted(start, text_end))))
    up, down = _BYTES_POW.get(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * up[: len(data)], out=total[1:])
    _, first, unit = np.unique(mix((total[start + size] - total[start]) * down[start] + size.astype(np.uint64)), return_index=True, return_inverse=True)
    wide = size[first]
    lattice = Lattice(v, data[np.arange(wide.sum()) - np.repeat(np.cumsum(wide) - wide - start[first], wide)], wide)
    place = np.arange(len(unit)) - np.repeat(np.cumsum(n) - n, n)
    base = mix(keys.astype(np.int64).view(np.uint64) + _U(seed & (2**64 - 1)))
    noise = mix(np.repeat(base, n) + place.astype(np.uint64) * _U(0xD1342543DE82EF95))
    edge, count = lattice.sample(unit, noise)
    piece = lattice.piece[edge]
    bare = np.flatnonzero(piece < 0)
    of = np.repeat(np.repeat(np.arange(len(texts)), n), count)
    if len(bare):
        # the bytes of a character take the place of its edge
        a = lattice.a[edge[bare]]
        head = (lattice.data & 0xC0) != 0x80
        ends = np.append(np.flatnonzero(head), len(lattice.data))
        wide = ends[np.searchsorted(ends, a, side="right")] - a
        times = np.ones(len(piece), np.int64)
        times[bare] = wide
        piece, of = np.repeat(piece, times), np.repeat(of, times)
        first = np.cumsum(times)[bare] - wide
        k = np.arange(wide.sum()) - np.repeat(np.cumsum(wide) - wide, wide)
        piece[np.repeat(first, wide) + k] = v.byte_id[lattice.data[np.repeat(a, wide) + k]]
    cut = np.searchsorted(of, np.arange(len(texts) + 1))
    piece = piece.astype(np.int32)
    return [piece[a:b] for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]


def decode_ids(v: Pieces, ids: list[np.ndarray]) -> list[bytes]:
    """Texts of piece ids; control pieces say nothing."""
    v.prepare()
    flat = np.concatenate(ids).astype(np.int64) if ids else np.zeros(0, np.int64)
    size = v.size[flat]
    total = np.concatenate(([0], np.cumsum(size)))
    joined = v.flat[np.arange(total[-1]) - np.repeat(total[:-1] - v.offset[flat], size)].tobytes()
    cut = total[np.cumsum([0, *map(len, ids)])].tolist()
    return [joined[a + (v.dummy_prefix and joined[a : a + 1] == b" ") : b] for a, b in zip(cut[:-1], cut[1:], strict=True)]


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def encode(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", seed: int = 17, flatness: float = 1.0, keep_text: bool = False) -> DataFrame:
    """(id, n_bytes, text_sha256, ids[, text]) of every row: a segmentation drawn by its pieces' weights.

    The draw depends on (seed, id, text) alone, so repeated rows repeat it; a null id is a key
    like any other.  Null and empty texts have no pieces.  Other columns are not read.
    """
    sent = docs.sparkSession.sparkContext.broadcast(Pieces.load(model, flatness))
    id_type = docs.schema[id_col].dataType.simpleString()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = sent.value
        for part, texts in slice_batches(batches, "text", 1 << 19):
            ids = encode_texts(v, texts, part.column("key").to_numpy(zero_copy_only=False), seed)
            offsets = np.concatenate(([0], np.cumsum([len(x) for x in ids]))).astype(np.int32)
            out = {"id": part.column("id"), "n_bytes": pa.array([len(t) for t in texts], pa.int64()), "text_sha256": pa.array([hashlib.sha256(t).hexdigest() for t in texts]), "ids": pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids)))}
            if keep_text:
                out["text"] = part.column("text")
            yield pa.record_batch(out)

    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).withColumn("key", F.xxhash64(F.col("id").cast("string")))
    return rows.mapInArrow(tidy_map(each), f"id {id_type}, n_bytes long, text_sha256 string, ids array<int>" + (", text string" if keep_text else ""))


def decode(encoded: DataFrame, model: str) -> DataFrame:
    """The columns of `encoded`, with text: what ids spell. Null ids spell nothing."""
    sent = encoded.sparkSession.sparkContext.broadcast(Pieces.load(model))
    kept = [f for f in encoded.schema.fields if f.name not in ("text", "ids")]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = sent.value
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                column = part.column("ids")
                flat = np.asarray(column.flatten())
                cut = np.concatenate(([0], np.cumsum([0 if x is None else x for x in column.value_lengths().to_pylist()]))).tolist()
                ids = [flat[a:z] for a, z in zip(cut[:-1], cut[1:], strict=True)]
                said = decode_ids(v, ids)
                out = {f.name: part.column(f.name) for f in kept}
                yield pa.record_batch(out | {"n_pieces": pa.array([len(x) for x in ids], pa.int64()), "ids_sha256": pa.array([hashlib.sha256(np.ascontiguousarray(x, "<i4").tobytes()).hexdigest() for x in ids]), "text": pa.array([s.decode() for s in said], pa.string())})

    return encoded.select(*(f.name for f in kept), "ids").mapInArrow(tidy_map(each), f"{schema}, n_pieces long, ids_sha256 string, text string")


def round_trip(docs: DataFrame, model: str, **options) -> DataFrame:
    """(id, n_bytes, n_pieces, ids_sha256, lossless): every row encoded, decoded and compared."""
    back = decode(encode(docs, model, **options), model)
    return back.select("id", "n_bytes", "n_pieces", "ids_sha256", (F.sha2("text", 256) == F.col("text_sha256")).alias("lossless"))


__all__ = ["Lattice", "Pieces", "decode", "decode_ids", "default_model", "encode", "encode_texts", "round_trip"]
