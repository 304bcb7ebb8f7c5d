"""Exact Jaccard join of word-shingle sets by token-combination prefixes.

A link of two sets x and y means 100 * |x & y| >= percent * |x | y|, so they
share at least percent/100 of the larger set.  The steps:

1. Each text's distinct shingles are hashed; equal sets get one identity (a
   64-bit signature of the set), so groups of copies count once everywhere.
2. A census counts in how many different sets each shingle occurs.  Shingles
   of one set alone can be in no link: a set with too many of them is done.
3. A set's shingles are ordered by (count, hash), the rarest first.  Its prefix
   is extended by one token, so linked sets share two tokens of it: either a
   rare one, which is indexed alone, or two frequent ones, which are indexed
   as a combination.  Long sets index frequent tokens alone, as combinations
   would grow with the square of the prefix; both ways meet where sizes overlap.
4. Each set is first compared with the most central set - the one with the fewest
   shingles of its own - that it meets in any bucket of the index.  Those links
   give components.  Then every bucket's pairs across components that can still
   reach the overlap are compared.  So a group of n near copies costs about n
   pairs, and no pair of a bucket goes unjudged.
5. Pairs are verified by counting common shingles; links give components.

Hashes have 48 bits in the census: a pair's count is wrong with a probability
near |x||y| / 2**48 (1e-9 for 500 shingles).
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .textblocks import WORD_BY_SPACE, Words, by_range, delta, discard, materialize, mix, pack, shuffle_parts, slice_batches, undelta, unpack, tidy_group, tidy_map

_BITS = 48
_U = np.uint64


#: Counts of sets that hold a shingle go up to this; above it, it is just frequent.
_OFTEN = 64


def _whole_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's k-word shingles (A-Z lower-cased, words by ASCII white space)."""
    w = Words(texts, WORD_BY_SPACE, lower=True)
    runs, out = w.runs(k), []
    for a, b in zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True):
        if b - a >= k:
            out.append(np.unique(runs[a : b - k + 1]))
        elif b > a:
            out.append(w.spans(np.array([a]), np.array([b - a])))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def _shortened(whole: np.ndarray) -> np.ndarray:
    """The same in 48 bits."""
    s = whole >> _U(64 - _BITS)
    return s[np.concatenate((np.ones(min(1, len(s)), bool), s[1:] != s[:-1]))]


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """Sorted distinct 48-bit hashes of each text's shingles."""
    return [_shortened(s) for s in _whole_sets(texts, k)]


def _signature(s: np.ndarray) -> int:
    """A set's identity: positive 63 bits, 0 for the empty set."""
    if not len(s):
        return 0
    m = mix(s + _U(0x51ED270B0A1F39C1))
    both = np.array([m.sum(dtype=np.uint64), np.bitwise_xor.reduce(m) + _U(len(s))], np.uint64)
    return max(1, int(mix(mix(both[:1]) + both[1:])[0] >> _U(1)))


def members(docs: DataFrame, id_col: str, text_col: str, k: int) -> DataFrame:
    """(id, n_shingles, rid) of every row."""
    id_type = docs.schema[id_col].dataType.simpleString()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text"):
            sets = _whole_sets(texts, k)
            yield pa.record_batch({"id": part.column("id"), "n_shingles": pa.array([len(s) for s in sets], pa.int64()), "rid": pa.array([_signature(_shortened(s)) for s in sets], pa.int64())})

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy_map(each), f"id {id_type}, n_shingles long, rid long")


def _census_blocks(docs: DataFrame, text_col: str, k: int, parts: int, hold: int = 800_000) -> DataFrame:
    """(part, done, block, sets): shingle hashes by hash range with the sets that hold them; a set is told once a task's chunk.

    A shingle that _OFTEN sets of a chunk hold is known to be frequent: its sets are told so at once (done, by ranges
    of sets), and one entry with that count goes to its range, so that no range has to hold all sets of a common line.
    """

    def flush(held: dict[int, np.ndarray]) -> pa.RecordBatch:
        rids = np.fromiter(held, np.uint64, len(held))
        sizes = np.array([len(s) for s in held.values()], np.uint64)
        keys, owner = np.concatenate(list(held.values())), np.repeat(np.arange(len(rids), dtype=np.uint32), sizes.astype(np.int64))
        order = np.argsort(keys, kind="stable")
        keys, owner = keys[order], owner[order]
        start = np.flatnonzero(np.concatenate((np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1])))
        times = np.diff(np.append(start, len(keys)))
        often = np.repeat(times >= _OFTEN, times)
        rows = _by_set(keys[often] << _U(8) | _U(_OFTEN), owner[often], rids, sizes, parts)
        one = np.zeros(len(keys), bool)
        one[start] = True
        weight = np.where(often, _OFTEN, 1).astype(np.uint64)
        keys, owner, weight = keys[~often | one], owner[~often | one], weight[~often | one]
        order, cut = by_range(keys, _BITS, parts)
        keys, owner, weight = keys[order], owner[order], weight[order]
        for p in range(parts):
            a, b = cut[p], cut[p + 1]
            if a < b:
                used, place = np.unique(owner[a:b], return_inverse=True)
                rows.append((p, False, pack(rids[used], sizes[used]), pack(delta(keys[a:b]), place, weight[a:b])))
        return pa.record_batch({"part": pa.array([r[0] for r in rows], pa.int32()), "done": pa.array([r[1] for r in rows], pa.bool_()), "sets": pa.array([r[2] for r in rows], pa.binary()), "block": pa.array([r[3] for r in rows], pa.binary())})

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total = {}, 0
        for _, texts in slice_batches(batches, "text"):
            for s in shingle_sets(texts, k):
                if len(s) and (rid := _signature(s)) not in held:
                    held[rid] = s
                    total += len(s)
            if total >= hold:
                yield flush(held)
                held, total = {}, 0
        if held:
            yield flush(held)

    return docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(tidy_map(each), "part int, done boolean, sets binary, block binary")


def _by_set(tokens: np.ndarray, owner: np.ndarray, rid: np.ndarray, size: np.ndarray, parts: int) -> list[tuple[int, bool, bytes, bytes]]:
    """Tokens on their way back to their sets."""
    order = np.lexsort((tokens, owner))
    tokens, owner = tokens[order], owner[order]
    to = (rid % _U(parts)).astype(np.int32)[owner]
    rows = []
    for p in np.unique(to).tolist():
        mine = to == p
        who, place = np.unique(owner[mine], return_inverse=True)
        rows.append((p, True, pack(rid[who], size[who]), pack(delta(place.astype(np.uint64)), tokens[mine])))
    return rows


def _census(blocks: DataFrame, parts: int) -> DataFrame:
    """(part, sets, block): shingles that several sets hold, by ranges of sets; a token is hash << 8 | min(count, _OFTEN)."""

    def count(table: pa.Table) -> pa.Table:
        keys, owner, weight, rids, sizes, base, rows = [], [], [], [], [], 0, []
        for i in range(table.num_rows):
            block, sets = table.column("block")[i].as_py(), table.column("sets")[i].as_py()
            if table.column("done")[i].as_py():
                rows.append((table.column("part")[i].as_py(), sets, block))
                continue
            gaps, place, w = unpack(block)
            rid, size = unpack(sets)
            keys.append(undelta(gaps))
            owner.append(place.astype(np.uint32) + np.uint32(base))
            weight.append(w.astype(np.uint8))
            rids.append(rid)
            sizes.append(size)
            base += len(rid)
        if keys:
            rid, known = np.unique(np.concatenate(rids), return_inverse=True)
            size = np.zeros(len(rid), np.uint64)
            size[known] = np.concatenate(sizes)
            keys, owner, weight = np.concatenate(keys), known.astype(np.uint32)[np.concatenate(owner)], np.concatenate(weight)
            order = np.argsort(keys, kind="stable")
            keys, owner, weight = keys[order], owner[order], weight[order]
            # a hash that only one entry has is out at once, unless that stands for many; of the rest, one set counts once
            same = keys[1:] == keys[:-1]
            many = np.concatenate((same, [False])) | np.concatenate(([False], same)) | (weight > 1)
            keys, owner, weight = keys[many], owner[many], weight[many]
            order = np.lexsort((-weight.astype(np.int16), owner, keys))
            keys, owner, weight = keys[order], owner[order], weight[order]
            fresh = np.concatenate((np.ones(min(1, len(keys)), bool), (keys[1:] != keys[:-1]) | (owner[1:] != owner[:-1])))
            keys, owner, weight = keys[fresh], owner[fresh], weight[fresh]
            start = np.flatnonzero(np.concatenate((np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1])))
            times = np.diff(np.append(start, len(keys)))
            # sets that are told at once are at least as many as one entry stands for
            total = np.repeat(np.minimum(np.add.reduceat(weight.astype(np.int64), start) if len(start) else times, _OFTEN), times)
            keep = total > 1
            rows += [(p, sets, block) for p, _, sets, block in _by_set((keys[keep] << _U(8)) | total[keep].astype(np.uint64), owner[keep], rid, size, parts)]
        return pa.table({"part": pa.array([r[0] for r in rows], pa.int32()), "sets": pa.array([r[1] for r in rows], pa.binary()), "block": pa.array([r[2] for r in rows], pa.binary())})

    return blocks.groupBy("part").applyInArrow(tidy_group(count), "part int, sets binary, block binary")


def _eligible(census: DataFrame, percent: int) -> DataFrame:
    """(rid, n, shared, tokens) of the sets with enough shared tokens for any link."""

    def gather(table: pa.Table) -> pa.Table:
        rids, sizes, owner, tokens, base = [], [], [], [], 0
        for sets, block in zip(table.column("sets").to_pylist(), table.column("block").to_pylist(), strict=True):
            rid, size = unpack(sets)
            place, token = unpack(block)
            rids.append(rid)
            sizes.append(size)
            owner.append(undelta(place).astype(np.int64) + base)
            tokens.append(token)
            base += len(rid)
        rid, known = np.unique(np.concatenate(rids), return_inverse=True)
        size = np.zeros(len(rid), np.int64)
        size[known] = np.concatenate(sizes)
        owner, tokens = known[np.concatenate(owner)], np.concatenate(tokens)
        order = np.lexsort((tokens, owner))
        owner, tokens = owner[order], tokens[order]
        # a set may hear of a frequent shingle more than once
        fresh = np.concatenate((np.ones(min(1, len(owner)), bool), (owner[1:] != owner[:-1]) | (tokens[1:] != tokens[:-1])))
        owner, tokens = owner[fresh], tokens[fresh]
        shared = np.bincount(owner, minlength=len(rid))
        fit = shared * 100 >= percent * size
        keep = fit[owner]
        owner, tokens = owner[keep], tokens[keep]
        who = np.flatnonzero(fit)
        cut = np.searchsorted(owner, np.append(who, len(rid))).tolist()
        return pa.table({
            "rid": pa.array(rid[who].astype(np.int64)), "n": pa.array(size[who].astype(np.int32)), "shared": pa.array(shared[who].astype(np.int32)),
            "tokens": pa.array([pack(delta(tokens[a:b])) for a, b in zip(cut[:-1], cut[1:], strict=True)], pa.binary()),
        })

    return census.groupBy("part").applyInArrow(tidy_group(gather), "rid long, n int, shared int, tokens binary")


def _tokens(blob: bytes) -> np.ndarray:
    return undelta(unpack(blob)[0])


def _ordered(tokens: bytes) -> np.ndarray:
    """A set's shared tokens, rarest first, then by hash."""
    t = _tokens(tokens)
    return t[np.lexsort((t, t & _U(255)))]


def _outline(t: np.ndarray) -> np.ndarray:
    """1024 bits of which each shared token sets one: bits that only one of two sets has are tokens that the other lacks."""
    on = np.zeros(1024, np.uint8)
    on[((t >> _U(8)) & _U(1023)).astype(np.int64)] = 1
    return np.packbits(on).view(np.uint64)


def _index(eligible: DataFrame, percent: int, rare: int, long: int, parts: int, outlines: bool, hold: int = 800_000) -> DataFrame:
    """(part, block, sets): the index entries of eligible sets. sets: rid, n, shared, component, and outlines if asked for."""

    def entries(n: int, shared: int, t: np.ndarray) -> np.ndarray:
        need = -(-n * percent // 100)
        one, alone = n - need + 1, n - shared  # a prefix of one token more than can be missed; those of no other set come first
        seldom = (t & _U(255)) <= rare
        first, extended = t[: max(0, one - alone)], t[: max(0, one + 1 - alone)]
        out = [mix(extended[seldom[: len(extended)]])]
        if 4 * n >= 3 * long:
            out.append(mix(first[~seldom[: len(first)]]))
        if n <= long or need < 2:
            often = extended[~seldom[: len(extended)]]
            if need < 2:
                out.append(mix(often))
            i, j = np.triu_indices(len(often), 1)
            lo, hi = np.minimum(often[i], often[j]), np.maximum(often[i], often[j])
            out.append(mix(mix(lo) * _U(3) + hi))
        return np.unique(np.concatenate(out) >> _U(64 - _BITS))

    def flush(held: list) -> pa.RecordBatch:
        keys = np.concatenate([h[1] for h in held])
        owner = np.repeat(np.arange(len(held)), [len(h[1]) for h in held])
        about = np.array([h[0] for h in held], np.uint64)
        if outlines:
            about = np.concatenate((about, np.stack([h[2] for h in held])), 1)
        order, cut = by_range(keys, _BITS, parts)
        keys, owner = keys[order], owner[order]
        rows = []
        for p in range(parts):
            a, b = cut[p], cut[p + 1]
            if a < b:
                used, place = np.unique(owner[a:b], return_inverse=True)
                rows.append((p, pack(delta(keys[a:b]), place), pack(*about[used].T)))
        return pa.record_batch({"part": pa.array([r[0] for r in rows], pa.int32()), "block": pa.array([r[1] for r in rows], pa.binary()), "sets": pa.array([r[2] for r in rows], pa.binary())})

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total = [], 0
        for b in batches:
            for rid, n, shared, tokens, root in zip(*(b.column(c).to_pylist() for c in ("rid", "n", "shared", "tokens", "root")), strict=True):
                t = _ordered(tokens)
                e = entries(n, shared, t)
                if len(e):
                    held.append(((rid, n, shared, root), e, _outline(t) if outlines else None))
                    total += len(e)
                if total >= hold:
                    yield flush(held)
                    held, total = [], 0
        if held:
            yield flush(held)

    return eligible.mapInArrow(tidy_map(each), "part int, block binary, sets binary")


def _pairs(index: DataFrame, percent: int, rest: bool) -> DataFrame:
    """(a, b) candidate pairs of sets: each set with the most central one it meets, or (rest) all that these have left open."""
    share = percent / (100 + percent)

    def could(x, y, n, s, outline):
        """Sizes, shared tokens and outlines allow the overlap."""
        need = share * (n[x] + n[y]) - 1e-9
        ok = np.flatnonzero((np.minimum(n[x], n[y]) * 100 >= percent * np.maximum(n[x], n[y])) & (np.minimum(s[x], s[y]) >= need))
        if rest:
            a, b = outline[x[ok]], outline[y[ok]]
            most = np.minimum(s[x[ok]] - np.bitwise_count(a & ~b).sum(1, dtype=np.int64), s[y[ok]] - np.bitwise_count(b & ~a).sum(1, dtype=np.int64))
            ok = ok[most >= need[ok]]
        return ok

    def of_bucket(who, rid, root) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Each set outside the largest component against all of other components."""
        roots, size = np.unique(root[who], return_counts=True)
        if len(roots) > 1:
            for x in who[root[who] != roots[size.argmax()]]:
                y = who[root[who] != root[x]]
                yield np.full(len(y), x), y

    def each(table: pa.Table) -> pa.Table:
        keys, owner, about, base = [], [], [], 0
        for block, sets in zip(table.column("block").to_pylist(), table.column("sets").to_pylist(), strict=True):
            gaps, place = unpack(block)
            of = np.stack(unpack(sets), 1)
            keys.append(undelta(gaps))
            owner.append(place.astype(np.int64) + base)
            about.append(of)
            base += len(of)
        about, owner, keys = np.concatenate(about), np.concatenate(owner), np.concatenate(keys)
        (rid, n, s, root), outline = about[:, :4].astype(np.int64).T, about[:, 4:]
        order = np.lexsort((rid[owner], keys))
        keys, owner = keys[order], owner[order]
        start = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        size = np.diff(np.append(start, len(keys)))
        found, held = set(), []

        def gather() -> None:
            if held:
                x, y = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])
                ok = could(x, y, n, s, outline)
                x, y = x[ok], y[ok]
                x, y = x[rid[x] != rid[y]], y[rid[x] != rid[y]]
                found.update(zip(np.minimum(rid[x], rid[y]).tolist(), np.maximum(rid[x], rid[y]).tolist(), strict=True))
                held.clear()

        if not rest:  # the most central set that each set meets in any bucket
            central = np.lexsort((rid, n - s))
            rank = np.empty(len(rid), np.int64)
            rank[central] = np.arange(len(rid))
            best = np.full(len(rid), len(rid))
            np.minimum.at(best, owner, np.repeat(np.minimum.reduceat(rank[owner], start), size))
            held.append((np.arange(len(rid)), central[np.minimum(best, len(rid) - 1)]))
        else:
            waiting = 0
            for a, b in zip(start[size > 1].tolist(), (start + size)[size > 1].tolist(), strict=True):
                for x, y in of_bucket(owner[a:b], rid, root):
                    held.append((x, y))
                    waiting += len(x)
                    if waiting > 50_000:
                        gather()
                        waiting = 0
        gather()
        found = sorted(found)
        return pa.table({"a": pa.array([f[0] for f in found], pa.int64()), "b": pa.array([f[1] for f in found], pa.int64())})

    return index.groupBy("part").applyInArrow(tidy_group(each), "a long, b long").distinct()


def _verified(pairs: DataFrame, eligible: DataFrame, percent: int) -> DataFrame:
    """The pairs whose sets overlap enough; all common tokens are among the shared ones."""
    left = eligible.select(F.col("rid").alias("a"), F.col("n").alias("n1"), F.col("tokens").alias("t1"))
    right = eligible.select(F.col("rid").alias("b"), F.col("n").alias("n2"), F.col("tokens").alias("t2"))

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = []
            t1, t2 = b.column("t1").to_pylist(), b.column("t2").to_pylist()
            for i, (n1, n2) in enumerate(zip(b.column("n1").to_pylist(), b.column("n2").to_pylist(), strict=True)):
                both = np.sort(np.concatenate((_tokens(t1[i]), _tokens(t2[i]))))
                common = int((both[1:] == both[:-1]).sum())
                keep.append(100 * common >= percent * (n1 + n2 - common))
            yield pa.record_batch([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(left, "a").join(right, "b").select("a", "b", "n1", "n2", "t1", "t2").mapInArrow(tidy_map(each), "a long, b long")


def shingle_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, percent: int = 80, rare: int = 8, long: int = 240) -> DataFrame:
    """(id, n_shingles, component_id) for every row: the least id that links of the join reach.

    rare: tokens of up to so many sets are indexed alone.  long: frequent tokens of sets beyond
    this size are indexed alone, those of sets up to 4/3 of it as combinations of two.
    Rows without words (null, empty, white space) have size 0 and stand alone.  Rows with a
    null id stand alone too, as null.  Repeated rows give repeated results.  An empty table
    gives an empty result.  Columns beside id and text are not read.
    """
    if not 75 <= percent <= 100:
        raise ValueError("percent is 75 to 100: the sizes of linked sets must let singles and combinations meet")
    spark = docs.sparkSession
    parts = shuffle_parts(spark)
    rows = materialize(members(docs, id_col, text_col, k), "rows")
    eligible = materialize(_eligible(_census(_census_blocks(docs, text_col, k, parts), parts), percent), "sets")
    size = eligible.count()
    index_parts = max(1, min(parts, size // 4000))
    alone = eligible.withColumn("root", F.col("rid"))
    stars = materialize(_verified(_pairs(_index(alone, percent, rare, long, index_parts, False), percent, False), eligible, percent), "stars")
    first = connected_components(stars)
    discard(stars)
    joined = eligible.join(first.withColumnRenamed("node", "rid"), "rid", "left").withColumn("root", F.coalesce("root", "rid"))
    rest = _verified(_pairs(_index(joined, percent, rare, long, index_parts, True), percent, True), eligible, percent)
    links = materialize(first.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(rest), "found")
    roots = connected_components(links)
    named = rows.filter("rid > 0 and id is not null").groupBy("rid").agg(F.min("id").alias("least"))
    roots = named.join(roots.withColumnRenamed("node", "rid"), "rid", "left").withColumn("root", F.coalesce("root", "rid"))
    least = roots.groupBy("root").agg(F.min("least").alias("component_id"))
    of_class = roots.select("rid", "root").join(least, "root").select("rid", "component_id")
    return rows.join(of_class, "rid", "left").select("id", "n_shingles", F.when(F.col("id").isNotNull() & (F.col("rid") > 0), F.col("component_id")).otherwise(F.col("id")).alias("component_id"))
