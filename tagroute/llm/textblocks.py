"""Vectorised word hashing and packed blocks, shared by the text operators.

Texts are hashed a chunk at a time with prefix sums of a polynomial over bytes
(then over words), so that any word or any run of k words costs a constant
number of array operations.  Hashed rows travel between stages as packed
blocks: a Spark row then holds thousands of entries, as byte planes under zstd.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession

from ..plans.rounds import discard, shared_dir
from ..plans.rounds import materialize as written

_U = np.uint64
_RNG = np.random.default_rng(20240607)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * _U(2) + _U(1)
_P = 0x9E3779B97F4A7C15  # odd: has an inverse modulo 2**64
_Q = 0xC2B2AE3D27D4EB4F
_M64 = (1 << 64) - 1

#: ASCII white space as the contracts name it: space and bytes 9 to 13.
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
WORD_BY_SPACE = ~SPACE
#: ASCII letters and every byte from 0x80 on.
WORD_LETTERS = np.zeros(256, bool)
WORD_LETTERS[65:91] = WORD_LETTERS[97:123] = WORD_LETTERS[128:] = True
#: Letters, digits and every byte from 0x80 on.
WORD_ALNUM = np.zeros(256, bool)
WORD_ALNUM[48:58] = WORD_ALNUM[65:91] = WORD_ALNUM[97:123] = WORD_ALNUM[128:] = True


class _Powers:
    """Powers of a base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inv = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up))
            up, down = np.full(size, self.base, np.uint64), np.full(size, self.inv, np.uint64)
            up[0] = down[0] = 1
            self.up, self.down = np.multiply.accumulate(up), np.multiply.accumulate(down)
        return self.up[:n], self.down[:n]


_BYTES_POW, _WORDS_POW = _Powers(_P), _Powers(_Q)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class Words:
    """Words of a chunk of texts: 64-bit hashes, byte spans, and each text's range of words."""

    def __init__(self, texts: list[bytes], word_bytes: np.ndarray, lower: bool):
        joined = b"\n".join(texts) + b"\n"
        if lower:
            joined = joined.lower()  # bytes.lower() moves A-Z alone
        self.buffer = joined
        raw = np.frombuffer(joined, np.uint8)
        inside = word_bytes[raw]
        edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        if len(inside) and inside[0]:
            edge = np.concatenate(([0], edge))
        self.start, self.end = edge[0::2], edge[1::2]
        up, down = _BYTES_POW.get(len(raw) + 1)
        total = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(_BYTE[raw] * up[: len(raw)], out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * down[self.start])
        self.text_start = np.concatenate(([0], np.cumsum([len(t) + 1 for t in texts], dtype=np.int64)))[: len(texts) + 1]
        self.first = np.searchsorted(self.start, self.text_start)  # words of text i: first[i]:first[i + 1]
        self._sums, self._total = None, total

    def heads(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(word, hash of its first bytes) of the words that have so many bytes."""
        at = np.flatnonzero(self.end - self.start >= size)
        _, down = _BYTES_POW.get(len(self._total))
        start = self.start[at]
        return at, mix((self._total[start + size] - self._total[start]) * down[start] + _U(size))

    def __len__(self) -> int:
        return len(self.hash)

    def runs(self, k: int) -> np.ndarray:
        """Hashes of the k words that start at each word, as far as the chunk goes (texts' ends are the caller's care)."""
        n = len(self.hash)
        if n < k:
            return np.zeros(0, np.uint64)
        return self.spans(np.arange(n - k + 1), np.full(n - k + 1, k))

    def spans(self, at: np.ndarray, count: np.ndarray) -> np.ndarray:
        if self._sums is None:
            up, _ = _WORDS_POW.get(len(self.hash) + 1)
            self._sums = np.zeros(len(self.hash) + 1, np.uint64)
            np.cumsum(self.hash * up[: len(self.hash)], out=self._sums[1:])
        _, down = _WORDS_POW.get(len(self.hash) + 1)
        return mix((self._sums[at + count] - self._sums[at]) * down[at] + count.astype(np.uint64) * _U(0xD6E8FEB86659FD93))

    def valid(self, k: int) -> np.ndarray:
        """Which starts leave k words in their own text; as long as runs(k)."""
        n = max(0, len(self.hash) - k + 1)
        ok = np.ones(n, bool)
        for f in (self.first[1:-1] if k > 1 else []):
            ok[max(0, f - k + 1) : f] = False
        return ok


def as_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """A string column as UTF-8, null as empty."""
    return [b"" if t is None else t for t in column.cast(pa.binary()).to_pylist()]


def chunks(sizes: Iterable[int], limit: int = 1 << 20) -> Iterator[slice]:
    """Slices of consecutive rows whose bytes stay near the limit; a longer row stands alone."""
    start = total = 0
    i = -1
    for i, n in enumerate(sizes):
        if total and total + n > limit:
            yield slice(start, i)
            start, total = i, 0
        total += n + 1
    if i >= start:
        yield slice(start, i + 1)


def pack(*columns: np.ndarray) -> bytes:
    """Unsigned columns of one length as byte planes, each as wide as its largest value."""
    parts, widths = [], []
    for c in columns:
        c = np.ascontiguousarray(c, np.uint64)
        wide = max(1, (int(c.max()).bit_length() + 7) // 8) if len(c) else 1
        widths.append(wide)
        parts.append(np.ascontiguousarray(c.view(np.uint8).reshape(-1, 8)[:, :wide].T).tobytes())
    head = np.array([len(columns[0]), len(columns), *widths], np.uint32).tobytes()
    return zstandard.ZstdCompressor(level=1).compress(head + b"".join(parts))


def unpack(blob: bytes) -> list[np.ndarray]:
    data = zstandard.ZstdDecompressor().decompress(blob)
    n, k = np.frombuffer(data, np.uint32, 2)
    widths = np.frombuffer(data, np.uint32, k, 8)
    at, out = 8 + 4 * int(k), []
    for wide in widths.tolist():
        planes = np.zeros((int(n), 8), np.uint8)
        planes[:, :wide] = np.frombuffer(data, np.uint8, int(n) * wide, at).reshape(wide, int(n)).T
        out.append(planes.view(np.uint64).reshape(-1))
        at += int(n) * wide
    return out


def delta(sorted_values: np.ndarray) -> np.ndarray:
    return np.diff(sorted_values, prepend=_U(0))


def undelta(gaps: np.ndarray) -> np.ndarray:
    return np.cumsum(gaps, dtype=np.uint64)


def by_range(keys: np.ndarray, bits: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """The order that sorts keys of so many bits, and where each of `parts` equal ranges starts in it (parts + 1 bounds)."""
    order = np.argsort(keys)
    limits = np.array([(i << bits) // parts for i in range(1, parts)], np.uint64)
    return order, np.concatenate(([0], np.searchsorted(keys[order], limits), [len(keys)]))


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write to the shared folder and read again."""
    return written(df, name, compression="zstd")


def shuffle_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def slice_batches(batches: Iterable[pa.RecordBatch], column: str, limit: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Record batches cut to chunks of about `limit` bytes of one text column, with its bytes."""
    for b in batches:
        texts = as_bytes(b.column(column))
        for s in chunks(map(len, texts), limit):
            yield b.slice(s.start, s.stop - s.start), texts[s]


def _give_back() -> None:
    """Return freed memory to the system: Python workers wait for their next task, several to an executor."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


#: Bytes of an Arrow batch on its way to a Python worker; several workers and the JVM's own buffers share an executor.
BATCH_BYTES = 4 << 20


def _bound_batches() -> None:
    """Lower the session's batch size to ours, where it is larger; called as a plan is made, on the driver."""
    spark = SparkSession.getActiveSession()
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark is not None and spark.conf.isModifiable(key):
        now = spark.conf.get(key, "67108864b").rstrip("b")
        if not now.isdigit() or int(now) > BATCH_BYTES or int(now) <= 0:
            spark.conf.set(key, f"{BATCH_BYTES}b")


def tidy_map(f: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable:
    _bound_batches()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from f(batches)
        _give_back()

    return run


def tidy_group(f: Callable[[pa.Table], pa.Table]) -> Callable:
    _bound_batches()

    def run(table: pa.Table) -> pa.Table:
        out = f(table)
        _give_back()
        return out

    return run


__all__ = [
    "SPACE", "WORD_ALNUM", "WORD_BY_SPACE", "WORD_LETTERS", "Words", "as_bytes", "by_range", "chunks", "delta", "discard", "materialize", "mix", "pack",
    "shared_dir", "shuffle_parts", "slice_batches", "tidy_group", "tidy_map", "undelta", "unpack",
]
