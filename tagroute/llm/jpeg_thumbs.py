"""Baseline JPEG in numpy: marker parsing, Huffman decoding of scans, DC-only luminance thumbnails.

`decode` reads any baseline (SOF0) or 8-bit extended sequential (SOF1) JPEG with
interleaved or separate scans, and keeps the DC coefficients alone: a thumbnail
has one sample for each 8 x 8 block of luminance.  All restart intervals of all
pictures of a batch are decoded side by side, one Huffman symbol of each at a
step, so the cost is that of array operations.

`encode_payload` stores bytes as the unit that such a thumbnail keeps without
loss: one byte is the DC level of one block of a grey picture whose DC quantiser
is 8, so the block's mean is the byte.  Restart intervals have 192 blocks.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import slice_batches, tidy_map

#: Blocks of a restart interval, and of the shortest picture row.
UNIT = 192
#: A picture has at most so many blocks a side (65535 pixels).
_SIDE = 8191
#: Fixed values, the luminance DC code of the JPEG standard: number of codes of each length, then symbols.
_DC_LENGTHS = (0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0)
_DC_SYMBOLS = tuple(range(12))
#: An AC code of one word: end of block.
_AC_LENGTHS = (1, *[0] * 15)
_AC_SYMBOLS = (0,)


def _codes(lengths: Iterable[int], symbols: Iterable[int]) -> list[tuple[int, int, int]]:
    """(code, length, symbol): canonical Huffman codes from their counts by length."""
    out, code, symbols = [], 0, iter(symbols)
    for size, count in enumerate(lengths, 1):
        for _ in range(count):
            out.append((code, size, next(symbols)))
            code += 1
        code <<= 1
    return out


def _lookup(lengths: Iterable[int], symbols: Iterable[int]) -> np.ndarray:
    """By the next 16 bits: length << 8 | symbol, 0 where no code fits."""
    table = np.zeros(1 << 16, np.uint16)
    for code, size, symbol in _codes(lengths, symbols):
        table[code << (16 - size) : (code + 1) << (16 - size)] = size << 8 | symbol
    return table


# ---------------------------------------------------------------- encoding


def _dc_words() -> tuple[np.ndarray, np.ndarray]:
    """Bits and bit count of each DC difference -255..255 followed by the end of block."""
    code = {s: (c, n) for c, n, s in _codes(_DC_LENGTHS, _DC_SYMBOLS)}
    bits, size = np.zeros(511, np.uint64), np.zeros(511, np.int64)
    for d in range(-255, 256):
        k = abs(d).bit_length()
        c, n = code[k]
        bits[d + 255] = ((c << k | (d if d >= 0 else d + (1 << k) - 1)) << 1) if k else c << 1
        size[d + 255] = n + k + 1
    return bits, size


_DC_BITS, _DC_SIZE = _dc_words()


def _scan_bytes(levels: np.ndarray) -> bytes:
    """The entropy-coded data of blocks with these DC levels (bytes), with restart markers and byte stuffing."""
    n = len(levels) // UNIT
    v = levels.astype(np.int16).reshape(n, UNIT)
    diff = np.empty((n, UNIT), np.int64)
    diff[:, 0] = v[:, 0] - 128
    diff[:, 1:] = np.diff(v, axis=1)
    size = _DC_SIZE[diff + 255]
    word = _DC_BITS[diff + 255]
    total = size.sum(1)
    whole = (total + 7) >> 3  # bytes of each interval, padded with 1 bits
    at_byte = np.concatenate(([0], np.cumsum(whole)))
    bit = (np.cumsum(size, 1) - size) + (at_byte[:-1] << 3)[:, None]
    pad = (whole << 3) - total
    bit = np.concatenate((bit.ravel(), (at_byte[:-1] << 3) + total))
    size = np.concatenate((size.ravel(), pad))
    word = np.concatenate((word.ravel(), (np.uint64(1) << pad.astype(np.uint64)) - np.uint64(1)))
    shifted = word << (64 - size - (bit & 31)).astype(np.uint64)
    shifted[size == 0] = 0
    cells = int(at_byte[-1] >> 2) + 2
    sums = np.bincount(bit >> 5, weights=(shifted >> np.uint64(32)).astype(np.float64), minlength=cells) + np.bincount((bit >> 5) + 1, weights=(shifted & np.uint64(0xFFFFFFFF)).astype(np.float64), minlength=cells)[:cells]
    raw = sums.astype(np.uint64).astype(">u4").tobytes()
    if n == 1:
        return raw[: at_byte[1]].replace(b"\xff", b"\xff\x00")
    return b"".join(
        raw[a:b].replace(b"\xff", b"\xff\x00") + (bytes((0xFF, 0xD0 + (i & 7))) if i < n - 1 else b"")
        for i, (a, b) in enumerate(zip(at_byte[:-1].tolist(), at_byte[1:].tolist(), strict=True))
    )


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


_TABLES = (
    _segment(0xDB, bytes([0, 8, *[1] * 63])),
    _segment(0xC4, bytes([0x00, *_DC_LENGTHS, *_DC_SYMBOLS]) + bytes([0x10, *_AC_LENGTHS, *_AC_SYMBOLS])),
    _segment(0xDD, struct.pack(">H", UNIT)),
    _segment(0xDA, bytes([1, 1, 0, 0, 63, 0])),
)


def encode_payload(payload: bytes) -> bytes:
    """A payload of a positive multiple of 192 bytes as grey JPEGs, one byte a block; one picture up to 8191 rows of the widest side."""
    if not payload or len(payload) % UNIT:
        raise ValueError(f"a payload has a positive multiple of {UNIT} bytes")
    out, widest = [], _SIDE // UNIT * UNIT
    for at in range(0, len(payload), widest * _SIDE):
        part = payload[at : at + widest * _SIDE]
        units = len(part) // UNIT
        wide = next((w for w in range(1, widest // UNIT + 1) if units % w == 0 and units // w <= _SIDE), None)
        if wide is None:  # a last picture of no fitting shape: full rows, then the rest
            full = len(part) // widest * widest
            out.append(encode_payload(part[:full]) + encode_payload(part[full:]))
            continue
        size = struct.pack(">BHHB", 8, 8 * (units // wide), 8 * UNIT * wide, 1) + bytes([1, 0x11, 0])
        out.append(b"".join((b"\xff\xd8", _TABLES[0], _segment(0xC0, size), *_TABLES[1:], _scan_bytes(np.frombuffer(part, np.uint8)), b"\xff\xd9")))
    return b"".join(out)


# ---------------------------------------------------------------- decoding


@dataclass
class Picture:
    """What the markers of one picture say."""

    width: int = 0
    height: int = 0
    components: list[tuple[int, int, int, int]] = field(default_factory=list)  # id, h, v, quantiser
    quantisers: dict[int, int] = field(default_factory=dict)  # the DC entry alone
    scans: list[tuple] = field(default_factory=list)  # components, tables, restart interval, first byte, past the last
    end: int = 0


def _words(b: bytes, at: int) -> int:
    return b[at] << 8 | b[at + 1]


def parse(data: bytes, at: int = 0) -> Picture:
    """The markers of the picture that starts at a byte."""
    if data[at : at + 2] != b"\xff\xd8":
        raise ValueError("no start of image")
    p, tables, restart = Picture(), {}, 0
    at += 2
    while True:
        while data[at] == 0xFF and data[at + 1] == 0xFF:
            at += 1
        if data[at] != 0xFF:
            raise ValueError("no marker")
        marker = data[at + 1]
        at += 2
        if marker == 0xD9:
            p.end = at
            return p
        if 0xD0 <= marker <= 0xD7 or marker == 0x01:
            continue
        size = _words(data, at)
        body, at = data[at + 2 : at + size], at + size
        if marker in (0xC0, 0xC1):
            if body[0] != 8:
                raise ValueError("8-bit samples only")
            p.height, p.width = _words(body, 1), _words(body, 3)
            p.components = [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(body[5])]
        elif 0xC2 <= marker <= 0xCF and marker not in (0xC4, 0xC8, 0xCC):
            raise ValueError("sequential Huffman pictures only")
        elif marker == 0xDB:
            i = 0
            while i < len(body):
                wide = 2 if body[i] >> 4 else 1
                p.quantisers[body[i] & 15] = int.from_bytes(body[i + 1 : i + 1 + wide], "big")
                i += 1 + 64 * wide
        elif marker == 0xC4:
            i = 0
            while i < len(body):
                n = sum(body[i + 1 : i + 17])
                tables[body[i]] = (bytes(body[i + 1 : i + 17]), bytes(body[i + 17 : i + 17 + n]))
                i += 17 + n
        elif marker == 0xDD:
            restart = _words(body, 0)
        elif marker == 0xDA:
            used = [(body[1 + 2 * i], tables[body[2 + 2 * i] >> 4], tables[16 | body[2 + 2 * i] & 15]) for i in range(body[0])]
            first = at
            while True:
                at = data.index(b"\xff", at)
                if data[at + 1] == 0 or 0xD0 <= data[at + 1] <= 0xD7:
                    at += 2
                else:
                    break
            p.scans.append((used, restart, first, at))


def _ceil(a: int, b: int) -> int:
    return -(-a // b)


@dataclass
class _Job:
    """A scan: the order of its blocks and where each one's level goes."""

    data: bytes
    order: list[int]  # component of each block of an MCU
    tables: list[tuple]
    mcus: int
    restart: int
    first: int
    end: int
    levels: list[np.ndarray] = field(default_factory=list)


def _decode_jobs(jobs: list[_Job]) -> None:
    """Fill each job's levels: differences of DC are summed within a restart interval. All jobs share tables and block order."""
    order, dc_tables, ac_tables = jobs[0].order, [_lookup(*t[1]) for t in jobs[0].tables], [_lookup(*t[2]) for t in jobs[0].tables]
    # without stuffing and markers, each interval's bytes follow the other
    pieces, job_of, mcus_of = [], [], []
    for j, job in enumerate(jobs):
        raw = np.frombuffer(job.data, np.uint8)[job.first : job.end]
        ff = np.flatnonzero(raw[:-1] == 255)
        cut = ff[raw[ff + 1] != 0].tolist()
        bounds = [-2, *cut, len(raw)]
        left = job.mcus
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):
            pieces.append(job.data[job.first + a + 2 : job.first + b].replace(b"\xff\x00", b"\xff"))
            job_of.append(j)
            mcus_of.append(min(left, job.restart or left))
            left -= mcus_of[-1]
        if left:
            raise ValueError("the scan ends too soon")
    buffer = np.frombuffer(b"\x00\x00\x00\x00".join(pieces) + b"\x00" * 8, np.uint8).astype(np.uint32)
    word = (buffer[:-3] << 24) | (buffer[1:-2] << 16) | (buffer[2:-1] << 8) | buffer[3:]
    starts = np.concatenate(([0], np.cumsum([len(x) + 4 for x in pieces])[:-1]))
    bit = (starts << 3).astype(np.int64)
    blocks = np.array(mcus_of, np.int64) * len(order)
    longest = int(blocks.max())
    levels = np.zeros((len(pieces), longest), np.int32)
    pred = np.zeros((len(pieces), max(order) + 1), np.int32)

    def peek(b: np.ndarray) -> np.ndarray:
        return (word[b >> 3] << (b & 7).astype(np.uint32)) >> np.uint32(16)

    by_length = np.argsort(-blocks, kind="stable")
    at = bit[by_length]
    amount = blocks[by_length]
    place = np.empty(len(pieces), np.int64)
    place[by_length] = np.arange(len(pieces))
    for k in range(longest):
        live = int(np.searchsorted(-amount, -k))  # pieces with more than k blocks come first
        b, c = at[:live], order[k % len(order)]
        code = dc_tables[c][peek(b)]
        if not code.all():
            raise ValueError("a code that the table has not")
        b = b + (code >> 8)
        size = (code & 255).astype(np.int64)
        extra = (peek(b).astype(np.int64)) >> (16 - size)
        b = b + size
        value = np.where(extra < (np.int64(1) << size) >> 1, extra - (np.int64(1) << size) + 1, extra)
        pred[:live, c] += value.astype(np.int32)
        levels[:live, k] = pred[:live, c]
        # AC: symbols are skipped up to the end of the block
        ac, index = ac_tables[c], np.ones(live, np.int64)
        code = ac[peek(b)]
        b = b + (code >> 8)
        open_ = np.flatnonzero((code & 255) != 0)
        if not code.all():
            raise ValueError("a code that the table has not")
        symbol = code[open_].astype(np.int64) & 255
        while len(open_):
            b[open_] += symbol & 15
            index[open_] += (symbol >> 4) + 1
            more = index[open_] < 64
            open_ = open_[more]
            code = ac[peek(b[open_])].astype(np.int64)
            b[open_] += code >> 8
            symbol = code & 255
            open_, symbol = open_[symbol != 0], symbol[symbol != 0]
        at[:live] = b
    for j in range(len(jobs)):
        jobs[j].levels = []
    for i, (j, n) in enumerate(zip(job_of, blocks.tolist(), strict=True)):
        jobs[j].levels.append(levels[place[i], :n])


def _thumbnail(p: Picture, jobs: list[tuple[int, _Job, int]]) -> np.ndarray:
    """The luminance samples of a decoded picture: rows x columns of blocks."""
    ident, h, v, quantiser = p.components[0]
    hmax, vmax = max(c[1] for c in p.components), max(c[2] for c in p.components)
    rows, columns = _ceil(_ceil(p.height * v, vmax), 8), _ceil(_ceil(p.width * h, hmax), 8)
    for which, job, wide in jobs:
        levels = np.concatenate(job.levels)
        per = len(job.order)
        mine = [i for i, c in enumerate(job.order) if c == which]
        if per == 1 and len(job.tables) == 1:
            grid = levels.reshape(-1, columns)[:rows]
        else:
            grid = levels.reshape(-1, wide, per)[:, :, mine].reshape(-1, wide, v, h).transpose(0, 2, 1, 3).reshape(-1, wide * h)[:rows, :columns]
        return np.clip((grid * p.quantisers[quantiser] + 4 >> 3) + 128, 0, 255).astype(np.uint8)
    raise ValueError("no scan has luminance")


def decode(pictures: list[bytes]) -> list[list[tuple[Picture, np.ndarray]]]:
    """Of each file: its pictures (one after the other) with their luminance thumbnails."""
    files, groups = [], {}
    for data in pictures:
        at, found = 0, []
        while at < len(data):
            p = parse(data, at)
            at = p.end
            hmax, vmax = max(c[1] for c in p.components), max(c[2] for c in p.components)
            mine = []
            for used, restart, first, end in p.scans:
                comps = [next(c for c in p.components if c[0] == u[0]) for u in used]
                luma = next((i for i, c in enumerate(comps) if c == p.components[0]), None)
                if luma is None:
                    continue
                if len(comps) == 1:
                    c = comps[0]
                    order, wide = [0], _ceil(_ceil(p.width * c[1], hmax), 8)
                    mcus = wide * _ceil(_ceil(p.height * c[2], vmax), 8)
                else:
                    order = [i for i, c in enumerate(comps) for _ in range(c[1] * c[2])]
                    wide = _ceil(p.width, 8 * hmax)
                    mcus = wide * _ceil(p.height, 8 * vmax)
                job = _Job(data, order, used, mcus, restart, first, end)
                mine.append((luma, job, wide))
                groups.setdefault((tuple(order), tuple(used)), []).append(job)
            found.append((p, mine))
        files.append(found)
    for jobs in groups.values():
        _decode_jobs(jobs)
    return [[(p, _thumbnail(p, mine)) for p, mine in found] for found in files]


def average_hash(thumbnail: np.ndarray, side: int = 8) -> str:
    """64 bits: whether each cell of a side x side grid of means lies above the mean of the cells."""
    r, c = (np.linspace(0, n, side + 1).astype(int) for n in thumbnail.shape)
    lo_r, hi_r, lo_c, hi_c = r[:-1], np.maximum(r[1:], r[:-1] + 1), c[:-1], np.maximum(c[1:], c[:-1] + 1)
    lo_r, lo_c = np.minimum(lo_r, thumbnail.shape[0] - 1), np.minimum(lo_c, thumbnail.shape[1] - 1)
    hi_r, hi_c = np.minimum(hi_r, thumbnail.shape[0]), np.minimum(hi_c, thumbnail.shape[1])
    s = np.zeros((thumbnail.shape[0] + 1, thumbnail.shape[1] + 1), np.int64)
    np.cumsum(np.cumsum(thumbnail, 0, dtype=np.int64), 1, out=s[1:, 1:])
    total = s[hi_r][:, hi_c] - s[lo_r][:, hi_c] - s[hi_r][:, lo_c] + s[lo_r][:, lo_c]
    count = (hi_r - lo_r)[:, None] * (hi_c - lo_c)[None, :]
    cells = (total << 8) // count
    return f"{int(np.packbits((cells * cells.size > cells.sum()).ravel()).view('>u8')[0]):016x}"


# ---------------------------------------------------------------- columns


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, media): each text as UTF-8, padded with spaces to a positive multiple of 192, as JPEG.

    Null is empty; long texts become several pictures, one after the other.  Repeated rows give
    repeated results, an empty table an empty one; columns beside id and text are not read.
    """
    id_type = docs.schema[id_col].dataType.simpleString()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text"):
            media = [encode_payload(t + b" " * (-len(t) % UNIT or (0 if t else UNIT))) for t in texts]
            yield pa.record_batch({"id": part.column("id"), "n_bytes": pa.array([len(t) for t in texts], pa.int64()), "media": pa.array(media, pa.binary())})

    return docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).mapInArrow(tidy_map(each), f"id {id_type}, n_bytes long, media binary")


def features(media: DataFrame) -> DataFrame:
    """(id, n_bytes, media) -> sizes, digests of what is read back and of the stored form, picture sizes and thumbnail hashes.

    Media are those of `store`; null reads as no picture.  Rows repeat as they come, an empty table gives an empty result.
    """
    id_type = media.schema["id"].dataType.simpleString()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, stored in slice_batches(batches, "media", 2 << 20):
            out = []
            for data, found in zip(stored, decode(stored), strict=True):
                payload = b"".join(t.tobytes() for _, t in found)
                said = ";".join(f"{p.width}x{p.height}:{average_hash(t)}" for p, t in found)
                out.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(data), hashlib.sha256(data).hexdigest(), said))
            c = list(zip(*out, strict=True))
            yield pa.record_batch({
                "id": part.column("id"), "n_bytes": part.column("n_bytes"), "payload_bytes": pa.array(c[0], pa.int64()), "payload_sha256": pa.array(c[1]), "tail_crc32": pa.array(c[2], pa.int64()),
                "media_bytes": pa.array(c[3], pa.int64()), "media_sha256": pa.array(c[4]), "feature": pa.array(c[5]),
            })

    return media.mapInArrow(tidy_map(each), f"id {id_type}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def thumbnails(media: DataFrame, id_col: str = "id", media_col: str = "media") -> DataFrame:
    """(id, width, height, thumb_hash, error) of stored JPEGs, the first picture of each; null media and what isn't such a JPEG give the error alone.

    Rows repeat as they come; an empty table gives an empty result; other columns are not read.
    """
    id_type = media.schema[id_col].dataType.simpleString()

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for data in b.column("media").to_pylist():
                try:
                    p, t = decode([data])[0][0]
                    rows.append((p.width, p.height, average_hash(t), None))
                except (ValueError, IndexError, KeyError, TypeError, StopIteration) as e:
                    rows.append((None, None, None, str(e) or type(e).__name__))
            c = list(zip(*rows, strict=True)) or [(), (), (), ()]
            yield pa.record_batch({"id": b.column("id"), "width": pa.array(c[0], pa.int32()), "height": pa.array(c[1], pa.int32()), "thumb_hash": pa.array(c[2], pa.string()), "error": pa.array(c[3], pa.string())})

    return media.select(F.col(id_col).alias("id"), F.col(media_col).alias("media")).mapInArrow(tidy_map(each), f"id {id_type}, width int, height int, thumb_hash string, error string")
