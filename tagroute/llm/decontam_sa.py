"""Benchmark decontamination by suffix arrays of the training shards.

Each shard (a chunk of documents in a task) gets a suffix array over its words;
every suffix of every test item is binary-searched in it, which gives the
longest verbatim match and all its places.  Words are numbered by the test
vocabulary, and 0 stands for any other word, so a suffix that starts with 0 can
match nothing and is left out of the array.  Suffixes are compared over their
first `window` words, as far as a decision needs; matches are then extended.

Test items are sent to the tasks in blocks of a bounded size, several to a pass.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .textblocks import WORD_ALNUM, Words, materialize, slice_batches, tidy_map

_U = np.uint64


class TestSuffixes:
    """Every suffix of a block of test items over the block's vocabulary, ready to be looked up."""

    def __init__(self, items: list[tuple[object, bytes]], window: int):
        self.window = window
        w = Words([t for _, t in items], WORD_ALNUM, lower=True)
        self.ids = [i for i, _ in items]
        self.vocabulary = np.unique(w.hash)
        self.known = np.zeros(1 << 16, bool)
        self.known[(self.vocabulary >> _U(48)).astype(np.int64)] = True
        self.words = np.searchsorted(self.vocabulary, w.hash).astype(np.int64) + 1
        self.first = w.first
        n = np.diff(w.first)
        self.item = np.repeat(np.arange(len(items)), n)
        self.left = np.repeat(w.first[1:], n) - np.arange(len(w))  # words from here to the item's end
        self.at = np.arange(len(w)) - np.repeat(w.first[:-1], n)
        self.size = np.repeat(n, n)
        #: Suffixes that a hit asks for: those with a whole window, and a short item's own.
        self.asked = np.flatnonzero((self.left >= window) | (self.at == 0) & (self.size < window))
        self.keys = _keys(np.append(self.words, np.zeros(window + 1, np.int64)), np.arange(len(w)), window, self.left)
        # pairs of words that some asked suffix starts with, and words that are a whole item
        two = self.asked[self.size[self.asked] > 1]
        self.base = len(self.vocabulary) + 1
        self.pairs = np.unique(self.words[two] * self.base + self.words[np.minimum(two + 1, len(w) - 1)]) if len(w) else np.zeros(0, np.int64)
        self.single = np.zeros(self.base, bool)
        self.single[self.words[self.asked[self.size[self.asked] == 1]]] = True

    def number(self, hashes: np.ndarray) -> np.ndarray:
        out = np.zeros(len(hashes), np.int64)
        maybe = np.flatnonzero(self.known[(hashes >> _U(48)).astype(np.int64)])
        h = hashes[maybe]
        at = np.minimum(np.searchsorted(self.vocabulary, h), len(self.vocabulary) - 1)
        hit = self.vocabulary[at] == h
        out[maybe[hit]] = at[hit] + 1
        return out


def _keys(words: np.ndarray, at: np.ndarray, window: int, left: np.ndarray) -> list[np.ndarray]:
    """The first `window` words of suffixes, two to a column, 0 behind a text's end; compared column by column."""
    columns = []
    for k in range(0, window, 2):
        a = np.where(k < left, words[at + k], 0)
        b = np.where(k + 1 < left, words[at + k + 1], 0) if k + 1 < window else np.zeros(len(at), np.int64)
        columns.append((a << 32) | b)
    return columns


def _bound(array: list[np.ndarray], wanted: list[np.ndarray], upper: bool) -> np.ndarray:
    """Binary search of many keys at once in sorted columns: the first place not below (or above) each key."""
    n, m = len(array[0]), len(wanted[0])
    lo, hi = np.zeros(m, np.int64), np.full(m, n, np.int64)
    while (open_ := lo < hi).any():
        mid = (lo + hi) >> 1
        probe = np.minimum(mid, n - 1)
        less, equal = np.zeros(m, bool), np.ones(m, bool)
        for a, w in zip(array, wanted, strict=True):
            v = a[probe]
            less |= equal & (v < w)
            equal &= v == w
        right = open_ & (less | equal if upper else less)
        lo, hi = np.where(right, mid + 1, lo), np.where(open_ & ~right, mid, hi)
    return lo


class Shard:
    """The suffix array of a chunk of texts, over the suffixes that test words can meet."""

    def __init__(self, w: Words, tests: TestSuffixes):
        self.tests, window = tests, tests.window
        self.w = w
        n = len(w)
        self.words = np.append(tests.number(w.hash), np.zeros(window + 1, np.int64)) if len(tests.vocabulary) else np.zeros(n + window + 1, np.int64)
        here = np.flatnonzero(self.words[:n])
        text = np.searchsorted(w.first, here, side="right") - 1
        left = w.first[text + 1] - here
        pair = self.words[here] * tests.base + np.where(left > 1, self.words[here + 1], 0)
        found = np.minimum(np.searchsorted(tests.pairs, pair), max(0, len(tests.pairs) - 1))
        some = tests.single[self.words[here]] | ((tests.pairs[found] == pair) if len(tests.pairs) else False)
        here, text, left = here[some], text[some], left[some]
        keys = _keys(self.words, here, window, left)
        order = np.lexsort(keys[::-1])
        self.at, self.text, self.left, self.keys = here[order], text[order], left[order], [k[order] for k in keys]

    def matches(self) -> tuple[np.ndarray, np.ndarray]:
        """(test suffix, place in the array) of every suffix that starts with an asked test window or short item."""
        t = self.tests
        if not len(self.at) or not len(t.asked):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        wanted = [k[t.asked] for k in t.keys]
        lo = _bound(self.keys, wanted, False)
        # the end of a suffix' range: a short item's is that of all its continuations
        size = np.minimum(t.left[t.asked], t.window)
        top = []
        for c, k in enumerate(wanted):
            rest = np.clip(size - 2 * c, 0, 2)
            top.append(np.where(rest == 2, k, np.where(rest == 1, k | 0xFFFFFFFF, np.int64(2**63 - 1))))
        if t.window % 2:
            top[-1] = np.where(size >= t.window, wanted[-1], top[-1])
        hi = _bound(self.keys, top, True)
        count = hi - lo
        which = np.repeat(t.asked, count)
        place = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(lo, count)
        return which, place

    def longest(self, which: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Words that each matched pair of suffixes has in common, beyond the window too."""
        t = self.tests
        common = np.minimum(t.left[which], t.window)
        open_ = np.flatnonzero(common >= t.window)
        words = np.append(self.words, 0)
        while len(open_):
            c, i = common[open_], open_
            more = (c < t.left[which[i]]) & (c < self.left[place[i]])
            a = t.words[np.minimum(which[i] + c, len(t.words) - 1)]
            b = words[np.minimum(self.at[place[i]] + c, len(words) - 1)]
            open_ = open_[more & (a == b)]
            common[open_] += 1
        return common


def item_blocks(benchmark: DataFrame, item_col: str, text_col: str, limit: int) -> Iterator[list[tuple[object, bytes]]]:
    """Test items by blocks of about `limit` bytes of text; one block at a time is on the driver."""
    held, total = [], 0
    for r in benchmark.select(F.col(item_col), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).filter(F.length("text") > 0).toLocalIterator():
        t = r[1].encode()
        if held and total + len(t) > limit:
            yield held
            held, total = [], 0
        held.append((r[0], t))
        total += len(t)
    if held:
        yield held


#: Blocks of test items that one pass of the documents looks up; passes after which what was found is written.
_BLOCKS_A_PASS, _PASSES_A_WRITE = 8, 8


def _scan(rows: DataFrame, sent: list, id_type: str, keep_text: bool, last: bool) -> DataFrame:
    """One pass of some blocks of test items. Spans of hit words and items add up; the last pass tells their sums."""

    def sums(n: int, spans: list[int], items: list[str]) -> tuple[int, list[str]]:
        change = np.zeros(n + 1, np.int64)
        np.add.at(change, spans[0::2], 1)
        np.add.at(change, spans[1::2], -1)
        return int((np.cumsum(change[:-1]) > 0).sum()), sorted(set(items))

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text"):
            w = Words(texts, WORD_ALNUM, lower=True)
            spans, items, longest = part.column("spans").to_pylist(), part.column("items").to_pylist(), part.column("longest").to_pylist()
            for tests in (x.value for x in sent):
                s = Shard(w, tests)
                which, place = s.matches()
                if not len(which):
                    continue
                text, at = s.text[place], s.at[place]
                size, common = np.minimum(tests.left[which], tests.window), s.longest(which, place)
                order = np.argsort(text, kind="stable")
                hit, cut = np.unique(text[order], return_index=True)
                for i, o in zip(hit.tolist(), np.split(order, cut[1:]), strict=True):
                    begin = at[o] - w.first[i]
                    spans[i] = spans[i] + np.unique(np.stack([begin, begin + size[o]], 1), axis=0).ravel().tolist()
                    items[i] = items[i] + [str(tests.ids[j]) for j in np.unique(tests.item[which[o]])]
                    longest[i] = max(longest[i], int(common[o].max()))
            n_words = np.diff(w.first).tolist()
            out = {"id": part.column("id")}
            if keep_text or not last:
                out["text"] = part.column("text")
            if last:
                told = [sums(*x) if x[1] else (0, []) for x in zip(n_words, spans, items, strict=True)]
                out |= {"n_words": pa.array(n_words, pa.int64()), "n_hit": pa.array([h for h, _ in told], pa.int64()), "n_items": pa.array([len(i) for _, i in told], pa.int64()), "items": pa.array([i for _, i in told], pa.list_(pa.string())), "contaminated": pa.array([h > 0 for h, _ in told], pa.bool_())}
            else:
                out |= {"spans": pa.array(spans, pa.list_(pa.int64())), "items": pa.array(items, pa.list_(pa.string()))}
            yield pa.record_batch(out | {"longest": pa.array(longest, pa.int64())})

    text = ", text string" if keep_text or not last else ""
    found = "n_words long, n_hit long, n_items long, items array<string>, contaminated boolean" if last else "spans array<long>, items array<string>"
    return rows.mapInArrow(tidy_map(each), f"id {id_type}{text}, {found}, longest long")


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", window: int = 10, block_bytes: int = 2 << 20, keep_text: bool = True) -> DataFrame:
    """(id[, text], n_words, n_hit, n_items, items, contaminated, longest) of every document.

    Words are runs of ASCII letters, digits and bytes from 0x80 on, with A-Z lower-cased.
    A document word is hit if it lies in any occurrence of `window` successive words of a
    test item, or of a whole item of fewer words.  items: the items with such occurrences,
    as distinct strings in order.  longest: words of the longest verbatim match among them, 0 without any.
    Items and documents without words hit nothing; a null text has no words, a null item id
    counts as the string "None".  Repeated rows give repeated results, repeated items count
    once an id.  An empty benchmark hits nothing, an empty table gives an empty result, and
    columns beside those named are not read.
    Test items go out in blocks of `block_bytes` (an item that is longer is a block alone), some
    blocks to each pass of the documents.
    """
    spark = docs.sparkSession
    id_type = docs.schema[id_col].dataType.simpleString()
    none = (F.array().cast("array<long>").alias("spans"), F.array().cast("array<string>").alias("items"), F.lit(0).cast("long").alias("longest"))
    now = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"), *none)
    held, passes = [], 0
    for items in item_blocks(benchmark, item_col, item_text, block_bytes):
        if len(held) == _BLOCKS_A_PASS:
            now, held, passes = _scan(now, held, id_type, keep_text, False), [], passes + 1
            if passes % _PASSES_A_WRITE == 0:
                now = materialize(now, "contamination")
        held.append(spark.sparkContext.broadcast(TestSuffixes(items, window)))
    return _scan(now, held, id_type, keep_text, True)


def longest_matches(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", window: int = 10, block_bytes: int = 2 << 20) -> DataFrame:
    """(id, item, doc_word, item_word, n_words): maximal verbatim matches of at least `window` words, or of whole shorter items."""
    spark = docs.sparkSession
    id_type = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    schema = T.StructType([T.StructField("id", docs.schema[id_col].dataType), T.StructField("item", T.StringType()), *(T.StructField(c, T.LongType()) for c in ("doc_word", "item_word", "n_words"))])

    def one(sent) -> DataFrame:
        def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tests = sent.value
            for part, texts in slice_batches(batches, "text"):
                s = Shard(Words(texts, WORD_ALNUM, lower=True), tests)
                which, place = s.matches()
                size = s.longest(which, place)
                # maximal: the words before differ, or one of the texts starts here
                a, b = which, s.at[place]
                before = (tests.at[a] > 0) & (b > s.w.first[s.text[place]]) & (tests.words[np.maximum(a - 1, 0)] == s.words[np.maximum(b - 1, 0)])
                keep = ~before | (tests.size[a] < tests.window)
                a, p, size = a[keep], place[keep], size[keep]
                yield pa.record_batch({
                    "id": part.column("id").take(pa.array(s.text[p])), "item": pa.array([str(tests.ids[i]) for i in tests.item[a]], pa.string()), "doc_word": pa.array(s.at[p] - s.w.first[s.text[p]], pa.int64()),
                    "item_word": pa.array(tests.at[a], pa.int64()), "n_words": pa.array(size, pa.int64()),
                })

        return rows.mapInArrow(tidy_map(each), schema)

    out = None
    for items in item_blocks(benchmark, item_col, item_text, block_bytes):
        found = one(spark.sparkContext.broadcast(TestSuffixes(items, window)))
        out = found if out is None else out.unionByName(found)
    return spark.createDataFrame([], schema) if out is None else out


def decontaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents with no hit; id and text only."""
    return contamination(docs, benchmark, **options).filter("not contaminated").select("id", "text")
