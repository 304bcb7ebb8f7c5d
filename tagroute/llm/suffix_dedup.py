"""Removal of repeated passages by prefix-partitioned suffix trees.

A suffix starts at a word of a document and ends with the document.  Two places
repeat a passage of `length` words if their suffixes meet in a node of the
corpus' suffix tree at a depth of `length` words or more.  The tree is never
held as a whole: prefixes of two kinds split its suffixes into groups that fit a
task, and only subtrees that can have deep nodes are built.

1. Census of short prefixes.  In every window of `length` words the runs of
   `gram` words compete by hash, and the least one (the leftmost of equals) is
   the window's anchor; equal windows have equal anchors at equal places.
   Anchors are counted over all documents, by ranges of their hashes.  A suffix
   whose anchor occurs once is a leaf above the depth asked for, and is done.
2. Groups.  Suffixes are grouped by their anchors' hash ranges, so many that a range of
   the bytes at hand stays well below `most` anchors.  Where the census counts more
   than that - a passage that very many documents hold - the prefix is lengthened to
   the whole `length` words: such a prefix is a node of the depth asked for by itself,
   so its suffixes are settled by count, and spread over all ranges by its own hash.
   The suffixes of a short prefix go out as one segment of words for each anchor.
3. Subtrees.  A group sorts the suffixes of its segments by prefix doubling and
   has the words that neighbours have in common: the suffix tree's inner nodes
   are the intervals of that list (`nodes`).  Suffixes below a node of
   `length` words or more are repeats.  Repeats at successive places of a
   document join to maximal ones (`maximal_repeats`).

Segments that are equal within a map task, and prefixes of full length that occur twice
there, are settled on the spot; one of them goes on to its group.

Words are compared by 48 bits of their hashes, long prefixes and rows by 64 bits.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import WORD_BY_SPACE, Words, delta, materialize, mix, pack, shuffle_parts, slice_batches, undelta, unpack, tidy_group, tidy_map

_U = np.uint64
#: Kinds of block rows: segments under short prefixes, suffixes under long ones, places already known as repeats.
_SEGMENTS, _LONG, _DONE = range(3)
_BLOCK = "part int, kind int, block binary, words binary, ids binary"
#: Low bits of a competing run are its place, so that the least is found with its place.
_PLACE = _U((1 << 31) - 1)
#: Bytes of text to an anchor, on the low side: sizes groups before any anchor is counted.
_ANCHOR_BYTES = 64
#: Suffixes, or words of segments, that a map task holds before it sends them off.
_HOLD = 1_000_000


def _sliding(f, a: np.ndarray, width: int) -> np.ndarray:
    """f (np.minimum or np.maximum) over each `width` neighbours, by doubling."""
    have = 1
    while have < width:
        step = min(have, width - have)
        a = f(a[:-step], a[step:])
        have += step
    return a


def _anchors(w: Words, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash (56 bits) of the run of `gram` words at each word, the place of each window's anchor, and which windows lie in one text."""
    runs = w.runs(gram)
    if len(w) < length:
        return runs, np.zeros(0, np.int64), np.zeros(0, bool)
    least = _sliding(np.minimum, (runs & ~_PLACE) | np.arange(len(runs), dtype=np.uint64), length - gram + 1)
    return runs >> _U(8), (least & _PLACE).astype(np.int64), w.valid(length)


def _slice(keys: np.ndarray, bits: int, parts: int) -> np.ndarray:
    """Which of `parts` equal ranges each key of so many bits lies in."""
    return ((keys >> _U(bits - 32)) * _U(parts) >> _U(32)).astype(np.int64)


def _cuts(sorted_values: np.ndarray) -> Iterator[tuple[int, slice]]:
    """Each value of a sorted array, and its range."""
    start = [*np.flatnonzero(_new(sorted_values)).tolist(), len(sorted_values)]
    for a, b in itertools.pairwise(start):
        yield int(sorted_values[a]), slice(a, b)


def _new(*keys: np.ndarray) -> np.ndarray:
    """Where one of the sorted keys differs from the one before."""
    fresh = np.zeros(len(keys[0]), bool)
    fresh[:1] = True
    for k in keys:
        fresh[1:] |= k[1:] != k[:-1]
    return fresh


def _repeated(keys: np.ndarray) -> np.ndarray:
    if not len(keys):
        return np.zeros(0, bool)
    same = keys[1:] == keys[:-1]
    return np.concatenate((same, [False])) | np.concatenate(([False], same))


def _within(count: np.ndarray) -> np.ndarray:
    """0, 1, ... within each of the runs of these lengths."""
    return np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)


def _short_ids(row: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, bytes]:
    used, of = np.unique(row, return_inverse=True)
    return of, pack(ids[used].view(np.uint64))


class _Out:
    """Block rows on their way out of a map task."""

    def __init__(self, parts: int, ids: list[np.ndarray]):
        self.parts, self.rows = parts, []
        self.ids = np.concatenate(ids)

    def add(self, part: int, kind: int, block: bytes, words: bytes | None, ids: bytes) -> None:
        self.rows.append((part, kind, block, words, ids))

    def done(self, row: np.ndarray, place: np.ndarray) -> None:
        """Known repeats: spread by row, whatever their prefix."""
        to = (mix(self.ids.view(np.uint64)) % _U(self.parts)).astype(np.int64)[row]
        order = np.argsort(to, kind="stable")
        for p, s in _cuts(to[order]):
            of, ids = _short_ids(row[order[s]], self.ids)
            self.add(p, _DONE, pack(of, place[order[s]]), None, ids)

    def suffixes(self, keys: np.ndarray, bits: int, row: np.ndarray, place: np.ndarray) -> None:
        """Suffixes by the range of their prefix; of a prefix that is here twice, one goes on with the count of all."""
        order = np.argsort(keys)
        keys, row, place = keys[order], row[order], place[order]
        many = _repeated(keys)
        self.done(row[many], place[many])
        first = np.flatnonzero(_new(keys))
        times = np.diff(np.append(first, len(keys)))
        keys, row, place = keys[first], row[first], place[first]
        for p, s in _cuts(_slice(keys, bits, self.parts)):
            of, ids = _short_ids(row[s], self.ids)
            self.add(p, _LONG, pack(delta(keys[s]), of, place[s], times[s]), None, ids)

    def batch(self) -> pa.RecordBatch:
        part, kind, block, words, ids = zip(*self.rows, strict=True) if self.rows else ((),) * 5
        return pa.record_batch({"part": pa.array(part, pa.int32()), "kind": pa.array(kind, pa.int32()), "block": pa.array(block, pa.binary()), "words": pa.array(words, pa.binary()), "ids": pa.array(ids, pa.binary())})


def _rows_of(table: pa.Table, kind: int, *columns: str) -> Iterator[tuple]:
    """The block rows of a kind, read one by one out of the table's buffers."""
    mine = np.flatnonzero(table.column("kind").to_numpy() == kind)
    for i in mine.tolist():
        yield tuple(table.column(c)[i].as_py() for c in columns)


def _joined(parts: list[np.ndarray], kind: type) -> np.ndarray:
    return np.concatenate(parts) if parts else np.zeros(0, kind)


def _entries(table: pa.Table, kind: int) -> list[np.ndarray]:
    """keys, rid, place, times of suffixes, or of places that are done (keys and times 0)."""
    out: list[list[np.ndarray]] = [[], [], [], []]
    for block, ids in _rows_of(table, kind, "block", "ids"):
        columns = unpack(block)
        none = np.zeros(len(columns[0]), np.uint64)
        keys, of, at, times = (undelta(columns[0]), *columns[1:]) if kind == _LONG else (none, *columns, none)
        for held, x in zip(out, (keys, unpack(ids)[0].view(np.int64)[of.astype(np.int64)], at.astype(np.uint32), times), strict=True):
            held.append(x)
    return [_joined(x, t) for x, t in zip(out, (np.uint64, np.int64, np.uint32, np.uint64), strict=True)]


class Subtrees:
    """Suffixes of segments of words, sorted, with the words that neighbours have in common: a suffix tree as an array.

    Suffixes start at the first `starts[i]` words of segment i, and end with it.  Ranks of the first
    1, 2, 4, ... words are made by doubling; they sort the suffixes and tell what two have in common.
    """

    def __init__(self, words: np.ndarray, size: np.ndarray, starts: np.ndarray):
        n, end = len(words), np.repeat(np.cumsum(size), size)
        at = np.arange(n)
        self.left = (end - at).astype(np.int32)
        self.segment = np.repeat(np.arange(len(size)), starts)
        self.at = np.repeat(np.cumsum(size) - size, starts) + _within(starts)
        rank = np.unique(words, return_inverse=True)[1] + 1
        self.ranks, k = [rank.astype(np.int32)], 1
        longest = int(size.max()) if len(size) else 0
        while k * 2 < longest:
            rank = self._paired(at, rank, k, n)
            self.ranks.append(rank.astype(np.int32))
            k *= 2
        key = rank[self.at] * (n + 2) + self._beyond(self.at, rank, k) if n else rank
        order = np.argsort(key, kind="stable")
        self.at, self.segment = self.at[order], self.segment[order]
        self.place = self.at - (np.cumsum(size) - size)[self.segment]
        self.common = self._common(self.at[:-1], self.at[1:])

    def _beyond(self, at: np.ndarray, rank: np.ndarray, k: int) -> np.ndarray:
        return np.where(self.left[at] > k, rank[np.minimum(at + k, len(rank) - 1)], 0)

    def _paired(self, at: np.ndarray, rank: np.ndarray, k: int, n: int) -> np.ndarray:
        return np.unique(rank * (n + 2) + self._beyond(at, rank, k), return_inverse=True)[1] + 1

    def _common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Words that two suffixes have in common, from the longest ranks down."""
        out = np.zeros(len(a), np.int32)
        for i in range(len(self.ranks) - 1, -1, -1):
            for _ in range(2 if i == len(self.ranks) - 1 else 1):
                x, y = np.minimum(a + out, len(self.left) - 1), np.minimum(b + out, len(self.left) - 1)
                open_ = (out < self.left[a]) & (out < self.left[b])
                same = open_ & (self.ranks[i][x] == self.ranks[i][y])
                out += np.where(same, np.minimum(np.int32(1 << i), self.left[x]), 0).astype(np.int32)
        return out

    def deep(self, depth: int) -> np.ndarray:
        """Suffixes below an inner node of so many words or more."""
        if not len(self.at):
            return np.zeros(0, bool)
        near = self.common >= depth
        return np.concatenate((near, [False])) | np.concatenate(([False], near))

    def nodes(self, depth: int) -> list[tuple[int, int, int]]:
        """(depth, first, last) of the inner nodes of so many words or more: intervals of sorted suffixes."""
        out, stack = [], []
        for i, c in enumerate([*self.common.tolist(), -1]):
            first = i
            while stack and stack[-1][0] > c:
                d, first = stack.pop()
                if d >= depth:
                    out.append((d, first, i))
            if not stack or stack[-1][0] < c:
                stack.append((c, first))
        return out


def _by_row(who: np.ndarray, place: np.ndarray, parts: int) -> list[tuple[int, bytes, bytes]]:
    """(part, ids, block) of places, for a gathering by row."""
    rid, of = np.unique(who, return_inverse=True)
    order = np.lexsort((place, of))
    of, place = of[order], place[order]
    to = (mix(rid.view(np.uint64)) % _U(parts)).astype(np.int64)[of]
    order = np.argsort(to, kind="stable")
    rows = []
    for p, s in _cuts(to[order]):
        used, short = np.unique(of[order[s]], return_inverse=True)
        rows.append((p, pack(rid[used].view(np.uint64)), pack(delta(short.astype(np.uint64)), place[order[s]])))
    return rows


_TOLD = "part int, ids binary, block binary"


def _told(rows: list[tuple[int, bytes | None, bytes]]) -> pa.Table:
    part, ids, block = zip(*rows, strict=True) if rows else ((),) * 3
    return pa.table({"part": pa.array(part, pa.int32()), "ids": pa.array(ids, pa.binary()), "block": pa.array(block, pa.binary())})


def _gathered(told: DataFrame) -> DataFrame:
    """(rid, places): the places told of each row."""

    def gather(table: pa.Table) -> pa.Table:
        who, place = [], []
        for i in range(table.num_rows):
            short, at = unpack(table.column("block")[i].as_py())
            who.append(unpack(table.column("ids")[i].as_py())[0].view(np.int64)[undelta(short).astype(np.int64)])
            place.append(at.astype(np.uint32))
        who, place = np.concatenate(who), np.concatenate(place)
        order = np.lexsort((place, who))
        who, place = who[order], place[order]
        fresh = _new(who, place)
        who, place = who[fresh], place[fresh].astype(np.uint64)
        found = list(_cuts(who))
        return pa.table({"rid": pa.array([r for r, _ in found], pa.int64()), "places": pa.array([pack(delta(place[s])) for _, s in found], pa.binary())})

    return told.groupBy("part").applyInArrow(tidy_group(gather), "rid long, places binary")


def _places(blob: bytes | None) -> np.ndarray:
    return undelta(unpack(blob)[0]).astype(np.int64) if blob else np.zeros(0, np.int64)


def _flags(first: np.ndarray, n: int, blobs: list[bytes | None]) -> np.ndarray:
    """Marks of a chunk's words at the places told for each text."""
    on = np.zeros(n, bool)
    for i, blob in enumerate(blobs):
        if blob:
            on[first[i] + _places(blob)] = True
    return on


def _per_text(w: Words, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Text and word within the text of a chunk's words."""
    row = np.searchsorted(w.first, at, side="right") - 1
    return row, at - w.first[row]


def _census(rows: DataFrame, length: int, gram: int, parts: int, groups: int, most: int) -> DataFrame:
    """Anchors that occur more than once, told by row; and (part -1) the groups in which more than `most` of them lie."""

    def send(held: list) -> pa.RecordBatch:
        base = np.cumsum([0] + [len(h[3]) for h in held])
        out = _Out(parts, [h[3] for h in held])
        out.suffixes(_joined([h[0] for h in held], np.uint64), 56, _joined([h[1] + base[i] for i, h in enumerate(held)], np.int64), _joined([h[2] for h in held], np.int64))
        return out.batch()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total = [], 0
        for part, texts in slice_batches(batches, "text"):
            w = Words(texts, WORD_BY_SPACE, lower=False)
            runs, anchor, ok = _anchors(w, length, gram)
            at = np.unique(anchor[ok])
            row, place = _per_text(w, at)
            held.append((runs[at], row, place, part.column("rid").to_numpy(zero_copy_only=False)))
            total += len(at)
            if total > _HOLD:
                yield send(held)
                held, total = [], 0
        if held:
            yield send(held)

    def count(table: pa.Table) -> pa.Table:
        keys, who, place, times = _entries(table, _LONG)
        order = np.argsort(keys, kind="stable")
        keys, who, place, times = keys[order], who[order], place[order], times[order]
        several = _repeated(keys) | (times > 1)
        group, at = np.unique(_slice(keys[several], 56, groups), return_inverse=True)
        full = group[np.bincount(at, times[several], len(group)) > most]
        _, done_who, done_place, _ = _entries(table, _DONE)
        rows = _by_row(np.concatenate((who[several], done_who)), np.concatenate((place[several], done_place)), parts)
        return _told(rows + ([(-1, None, pack(full))] if len(full) else []))

    return rows.mapInArrow(tidy_map(each), _BLOCK).groupBy("part").applyInArrow(tidy_group(count), _TOLD)


def _suffix_blocks(asked: DataFrame, length: int, gram: int, groups: int, full) -> DataFrame:
    """Segments under short prefixes and suffixes under long ones, of rows with the places of repeated anchors. full: the groups with long prefixes, sorted."""

    def segments(out: _Out, key: np.ndarray, row: np.ndarray, place: np.ndarray, size: np.ndarray, words: np.ndarray, print_: np.ndarray) -> None:
        start = np.cumsum(size) - size
        order = np.lexsort((print_, key))
        settled = order[_repeated(print_[order])]
        starts = size[settled] - length + 1
        out.done(np.repeat(row[settled], starts), np.repeat(place[settled], starts) + _within(starts))
        order = order[_new(print_[order])]
        for p, s in _cuts(_slice(key[order], 56, groups)):
            mine = order[s]
            of, ids = _short_ids(row[mine], out.ids)
            flat = np.repeat(start[mine], size[mine]) + _within(size[mine])
            out.add(p, _SEGMENTS, pack(of, place[mine], size[mine]), pack(words[flat]), ids)

    def send(held: list) -> pa.RecordBatch:
        base = np.cumsum([0] + [len(h[-1]) for h in held])
        out = _Out(groups, [h[-1] for h in held])
        key, row, place, size, words, print_ = (_joined([h[0][i] + (base[j] if i == 1 else 0) for j, h in enumerate(held)], np.int64) for i in range(6))
        segments(out, key, row, place, size, words, print_)
        key, row, place = (_joined([h[1][i] + (base[j] if i == 1 else 0) for j, h in enumerate(held)], np.int64) for i in range(3))
        out.suffixes(key, 64, row, place)
        return out.batch()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total, overfull = [], 0, full.value
        for part, texts in slice_batches(batches, "text"):
            w = Words(texts, WORD_BY_SPACE, lower=False)
            runs, anchor, ok = _anchors(w, length, gram)
            on = _flags(w.first, len(w), part.column("places").to_pylist())
            live = np.flatnonzero(ok)
            live = live[on[anchor[live]]]
            a = anchor[live]
            group = _slice(runs[a], 56, groups)
            long = overfull[np.minimum(np.searchsorted(overfull, group), len(overfull) - 1)] == group if len(overfull) else np.zeros(len(a), bool)
            at = live[long]
            by_suffix = (w.spans(at, np.full(len(at), length)), *_per_text(w, at))
            # windows of one anchor stand side by side: one segment
            live, a = live[~long], a[~long]
            first = np.flatnonzero(_new(a))
            starts = np.diff(np.append(first, len(a)))
            at, size = live[first], starts + length - 1
            words = w.hash[np.repeat(at, size) + _within(size)] >> _U(16)
            by_segment = (runs[a[first]], *_per_text(w, at), size, words, w.spans(at, size))
            held.append((by_segment, by_suffix, part.column("rid").to_numpy(zero_copy_only=False)))
            total += len(words) + len(by_suffix[0])
            if total > _HOLD:
                yield send(held)
                held, total = [], 0
        if held:
            yield send(held)

    return asked.mapInArrow(tidy_map(each), _BLOCK)


def _read_segments(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """words, size, rid, place of a group's segments."""
    words, size, rid, place = [], [], [], []
    for block, flat, ids in _rows_of(table, _SEGMENTS, "block", "words", "ids"):
        of, at, n = unpack(block)
        words.append(unpack(flat)[0])
        size.append(n.astype(np.int64))
        rid.append(unpack(ids)[0].view(np.int64)[of.astype(np.int64)])
        place.append(at.astype(np.uint32))
    return _joined(words, np.uint64), _joined(size, np.int64), _joined(rid, np.int64), _joined(place, np.uint32)


def _deep(blocks: DataFrame, length: int, parts: int) -> DataFrame:
    """Places of suffixes below a node of `length` words or more, told by row."""

    def each(table: pa.Table) -> pa.Table:
        words, size, rid, place = _read_segments(table)
        tree = Subtrees(words, size, size - length + 1)
        deep = tree.deep(length)
        who = [rid[tree.segment[deep]]]
        at = [(place[tree.segment[deep]] + tree.place[deep]).astype(np.uint32)]
        keys, of, where, times = _entries(table, _LONG)
        order = np.argsort(keys, kind="stable")
        several = order[_repeated(keys[order]) | (times[order] > 1)]
        _, done_who, done_place, _ = _entries(table, _DONE)
        return _told(_by_row(np.concatenate((*who, of[several], done_who)), np.concatenate((*at, where[several], done_place)), parts))

    return blocks.groupBy("part").applyInArrow(tidy_group(each), _TOLD)


def _sizes(rows: DataFrame, most: int) -> tuple[int, int]:
    """Ranges of the census and groups of suffixes, by the bytes at hand: either holds half of `most` anchors, or less, if no passage is very common."""
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(shuffle_parts(rows.sparkSession), total // (_ANCHOR_BYTES * 1_000_000))
    return int(parts), int(max(parts, total // (_ANCHOR_BYTES * most // 2)))


def _blocks(rows: DataFrame, length: int, gram: int, most: int) -> tuple[DataFrame, int]:
    parts, groups = _sizes(rows, most)
    told = materialize(_census(rows, length, gram, parts, groups, most), "census")
    # one number for each overfull group; a group stands for at least `most` places of the corpus
    full = np.sort(_joined([unpack(r[0])[0].astype(np.int64) for r in told.filter("part < 0").select("block").toLocalIterator()], np.int64))
    asked = rows.join(_gathered(told.filter("part >= 0")), "rid")
    return _suffix_blocks(asked, length, gram, groups, rows.sparkSession.sparkContext.broadcast(full)), parts


def repeats(rows: DataFrame, length: int, gram: int, most: int) -> DataFrame:
    """rows (rid, text, ...) -> (rid, places): the words where a window starts whose words start anywhere else too."""
    blocks, parts = _blocks(rows, length, gram, most)
    return _gathered(_deep(blocks, length, parts))


def _covered(starts: np.ndarray, n: int, length: int) -> np.ndarray:
    """Words that a window from one of the starts covers."""
    change = np.zeros(n + 1, np.int64)
    np.add.at(change, np.unique(starts), 1)
    np.add.at(change, np.minimum(np.unique(starts) + length, n), -1)
    return np.cumsum(change[:-1]) > 0


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows by a key that any recomputation gives alike: of the id's and the text's hash. Rows that agree in both are one, with their count."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).alias("id"), text.alias("text")).withColumn("rid", F.xxhash64(F.col("id").cast("string"), F.isnull("id"), F.xxhash64("text")))


def drop_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 35, gram: int = 8, keep_text: bool = True, most: int = 32_000) -> DataFrame:
    """(id, n_words, n_removed, kept_sha256[, text]): documents without the words of any window of `length` words that occurs elsewhere too.

    Every copy goes, the first one too; windows are judged on the input.  Words are runs
    without ASCII white space, unchanged.  Kept words are joined by one space.
    Null and empty texts have no words.  Rows that repeat id and text repeat each other's
    windows: every row of theirs counts as a document.  An empty table gives an empty result.
    Columns beside id and text are not read.  `most` anchors (some 1.5 million words of
    segments) and no more meet in one group of suffixes.
    """
    if not 0 < gram < length:
        raise ValueError("gram is between 0 and length")
    id_type = docs.schema[id_col].dataType.simpleString()
    rows = _keyed(docs, id_col, text_col)
    found = repeats(rows, length, gram, most)

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text"):
            blobs = part.column("places").to_pylist()
            n_words, n_removed, digest, kept_texts = [], [], [], []
            for i, t in enumerate(texts):
                words = t.split()
                n = len(words)
                if blobs[i]:
                    gone = _covered(_places(blobs[i]), n, length)
                    words = [x for x, g in zip(words, gone.tolist(), strict=True) if not g]
                kept = b" ".join(words)
                n_words.append(n)
                n_removed.append(n - len(words))
                digest.append(hashlib.sha256(kept).hexdigest())
                kept_texts.append(kept)
            out = {"id": part.column("id"), "n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "kept_sha256": pa.array(digest)}
            if keep_text:
                out["text"] = pa.array([k.decode() for k in kept_texts], pa.string())
            yield pa.record_batch(out)

    schema = f"id {id_type}, n_words long, n_removed long, kept_sha256 string" + (", text string" if keep_text else "")
    return rows.join(found, "rid", "left").mapInArrow(tidy_map(cut), schema)


def maximal_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 35, gram: int = 8, most: int = 32_000) -> DataFrame:
    """(id, first_word, n_words): maximal runs of words all of whose windows of `length` words occur elsewhere too."""
    id_type = docs.schema[id_col].dataType.simpleString()
    rows = _keyed(docs, id_col, text_col)
    found = repeats(rows, length, gram, most)

    def runs(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, first, size = [], [], []
            for i, blobs in zip(b.column("id").to_pylist(), b.column("places").to_pylist(), strict=True):
                at = np.unique(_places(blobs))
                for run in np.split(at, np.flatnonzero(np.diff(at) > 1) + 1):
                    ids.append(i)
                    first.append(int(run[0]))
                    size.append(int(run[-1] - run[0]) + length)
            yield pa.record_batch({"id": pa.array(ids, b.schema.field("id").type), "first_word": pa.array(first, pa.int64()), "n_words": pa.array(size, pa.int64())})

    return rows.select("rid", "id").join(found, "rid").select("id", "places").mapInArrow(tidy_map(runs), f"id {id_type}, first_word long, n_words long")


