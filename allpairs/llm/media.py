"""Media columns: baseline JPEG, written and read in numpy.

A payload of bytes becomes the quantised coefficients of a baseline JPEG (4:4:4, all quantiser steps
1): 192 bytes are the three blocks of one unit, 64 coefficients each, in scan order.  Coefficients
are the format's unit that survives unchanged, so the payload comes back bit for bit.  Frequent
bytes of text get small amplitudes, which the entropy coder stores in few bits.  Each unit is a
restart interval of its own; the decoder lets all intervals of a batch of images advance together,
one table lookup for each coefficient.

The reader takes any baseline JPEG (runs, end of block, any sampling, with or without restart
intervals); from luminance it keeps the DC values, an eighth-size thumbnail, and hashes it.

Null text is the empty text, whose payload is 192 blanks.  Equal texts give equal files.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, keep, ship, size_bounded_batches

UNIT = 192
COLUMNS = 4
MOST_UNITS_A_SIDE = 8191
# Bytes by falling frequency in European text; the others follow in ascending order.
FREQUENT = b" enitarsohdlu\xc3cmgpbf,.vw\n\xa9qTzyAExkEIDS"
# Code length of amplitude sizes 1 to 8, the same for DC and AC.
SIZE_BITS = {1: 2, 2: 2, 3: 2, 4: 3, 5: 4, 6: 5, 7: 6, 8: 7}
# The order in which a block's coefficients are scanned, row * 8 + column.
ZIGZAG = np.array(sorted(range(64), key=lambda k: (k // 8 + k % 8, k // 8 if (k // 8 + k % 8) % 2 else k % 8)))


def _ranks() -> np.ndarray:
    first = list(dict.fromkeys(FREQUENT))
    rank = np.empty(256, np.int64)
    rank[first + [b for b in range(256) if b not in set(first)]] = np.arange(256)
    return rank


_RANK = _ranks()
#: Byte to coefficient, never 0: ranks 0, 1, 2, 3 become 1, -1, 2, -2.
VALUE = (_RANK // 2 + 1) * np.where(_RANK % 2, -1, 1)
BYTE = np.zeros(512, np.uint8)
BYTE[VALUE + 256] = np.arange(256)


def _codes(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Symbol to (code, length), shorter codes first, as the format's tables imply."""
    out, code, before = {}, 0, 0
    for symbol, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= n - before
        out[symbol], before = (code, n), n
        code += 1
    return out


def _byte_codes() -> tuple[np.ndarray, np.ndarray]:
    codes = _codes(SIZE_BITS)
    bits, lens = np.empty(256, np.uint64), np.empty(256, np.int64)
    for b in range(256):
        v = int(VALUE[b])
        size = abs(v).bit_length()
        code, n = codes[size]
        bits[b], lens[b] = code << size | (v if v > 0 else v + (1 << size) - 1), n + size
    return bits, lens


_BITS, _LENS = _byte_codes()


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _tables() -> bytes:
    counts = bytes(sum(n == k for n in SIZE_BITS.values()) for k in range(1, 17))
    symbols = bytes(s for s, _ in sorted(SIZE_BITS.items(), key=lambda x: (x[1], x[0])))
    return _segment(0xDB, b"\0" + b"\1" * 64) + _segment(0xC4, b"\x00" + counts + symbols + b"\x10" + counts + symbols)


_TABLES = _tables()


def _layout(units: int) -> tuple[int, int]:
    columns = max(COLUMNS, -(-units // MOST_UNITS_A_SIDE))
    return columns, -(-units // columns)


def _head(payload: int, columns: int, rows: int) -> bytes:
    frame = struct.pack(">BHHB", 8, rows * 8, columns * 8, 3) + b"".join(bytes((c, 0x11, 0)) for c in (1, 2, 3))
    scan = b"\3" + b"".join(bytes((c, 0)) for c in (1, 2, 3)) + b"\0\x3f\0"
    return b"\xff\xd8" + _segment(0xFE, b"payload=%d" % payload) + _TABLES + _segment(0xC0, frame) + _segment(0xDD, struct.pack(">H", 1)) + _segment(0xDA, scan)


def payload_of(text: bytes) -> bytes:
    return text + b" " * (max(UNIT, -(-len(text) // UNIT) * UNIT) - len(text))


def write_jpegs(payloads: list[bytes]) -> list[bytes]:
    """A file for each payload; all units of all payloads are coded at once."""
    shapes = [_layout(len(p) // UNIT) for p in payloads]
    units = np.array([c * r for c, r in shapes], np.int64)
    data = np.frombuffer(b"".join(p + b" " * (int(u) * UNIT - len(p)) for p, u in zip(payloads, units, strict=True)), np.uint8).reshape(-1, UNIT)
    lens = _LENS[data]
    ends = np.cumsum(lens, 1)
    n_bytes = -(-ends[:, -1] // 8)
    starts = np.concatenate([[0], np.cumsum(n_bytes)])
    pos = (ends - lens + starts[:-1, None] * 8).reshape(-1)
    lens = lens.reshape(-1)
    # codes have at most 15 bits, so each touches at most two 32-bit words; bits never overlap, so sums are unions
    spread = _BITS[data.reshape(-1)] << (64 - lens - (pos & 31)).astype(np.uint64)
    n_words = int(starts[-1]) // 4 + 3
    words = np.bincount(pos >> 5, (spread >> np.uint64(32)).astype(float), n_words) + np.bincount((pos >> 5) + 1, (spread & np.uint64(0xFFFFFFFF)).astype(float), n_words)
    coded = np.frombuffer(words.astype(">u4").tobytes(), np.uint8)[: starts[-1]].copy()
    coded[starts[1:] - 1] |= ((1 << (n_bytes * 8 - ends[:, -1])) - 1).astype(np.uint8)
    # a zero follows each 255; two bytes of a restart marker follow each unit, the last one's are dropped below
    of_unit = np.repeat(np.arange(len(n_bytes)), n_bytes)
    full = coded == 255
    to = np.arange(len(coded)) + np.cumsum(full) - full + 2 * of_unit
    out = np.zeros(len(coded) + int(full.sum()) + 2 * len(n_bytes), np.uint8)
    out[to] = coded
    last = to[starts[1:] - 1] + full[starts[1:] - 1]
    first_unit = np.concatenate([[0], np.cumsum(units)])
    in_doc = np.arange(len(n_bytes)) - np.repeat(first_unit[:-1], units)
    out[last + 1], out[last + 2] = 255, 0xD0 + in_doc % 8
    cuts = np.concatenate([[0], last[first_unit[1:] - 1] + 3])
    body = out.tobytes()
    return [_head(len(p), *shape) + body[cuts[k] : cuts[k + 1] - 2] + b"\xff\xd9" for k, (p, shape) in enumerate(zip(payloads, shapes, strict=True))]


@dataclass
class Jpeg:
    """What the markers say, and the entropy-coded bytes of each restart interval."""

    width: int = 0
    height: int = 0
    parts: list = field(default_factory=list)  # (id, h, v, quantiser, dc table, ac table)
    quantisers: dict = field(default_factory=dict)
    huffman: dict = field(default_factory=dict)
    interval: int = 0
    comment: bytes = b""
    scans: list = field(default_factory=list)

    @property
    def units(self) -> tuple[int, int]:
        h, v = (max(p[k] for p in self.parts) for k in (1, 2)) if len(self.parts) > 1 else (1, 1)
        return -(-self.width // (8 * h)), -(-self.height // (8 * v))


def parse(data: bytes) -> Jpeg:
    image, at = Jpeg(), 2
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG")
    while True:
        if data[at] != 0xFF:
            raise ValueError("a marker is missing")
        marker = data[at + 1]
        if marker == 0xFF:
            at += 1
            continue
        if marker == 0xD9:
            return image
        n = struct.unpack_from(">H", data, at + 2)[0]
        body = data[at + 4 : at + 2 + n]
        at += 2 + n
        if marker == 0xDB:
            while body:
                wide = body[0] >> 4
                image.quantisers[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[65 + 64 * wide :]
        elif marker == 0xC4:
            while body:
                total = sum(body[1:17])
                image.huffman[body[0]] = body[1 : 17 + total]
                body = body[17 + total :]
        elif marker == 0xC0:
            _, image.height, image.width, n_parts = struct.unpack_from(">BHHB", body)
            image.parts = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k], 0, 0) for k in range(n_parts)]
        elif 0xC1 <= marker <= 0xCF and marker not in (0xC4, 0xC8, 0xCC):
            raise ValueError("not a baseline JPEG")
        elif marker == 0xDD:
            image.interval = struct.unpack(">H", body)[0]
        elif marker == 0xFE:
            image.comment = body
        elif marker == 0xDA:
            chosen = {body[1 + 2 * k]: body[2 + 2 * k] for k in range(body[0])}
            if len(chosen) != len(image.parts):
                raise ValueError("one scan with all components is read")
            image.parts = [(*p[:4], chosen[p[0]] >> 4, chosen[p[0]] & 15) for p in image.parts]
            image.scans, at = _intervals(data, at)


def _intervals(data: bytes, at: int) -> tuple[list[bytes], int]:
    raw = np.frombuffer(data, np.uint8, offset=at)
    marks = np.flatnonzero(raw[:-1] == 255)
    kinds = raw[marks + 1]
    end = int(marks[(kinds != 0) & ((kinds < 0xD0) | (kinds > 0xD7))][0])
    stops = [int(m) for m in marks[(kinds >= 0xD0) & (kinds <= 0xD7) & (marks < end)]]
    cut = [0, *(s + 2 for s in stops)]
    return [data[at + a : at + b].replace(b"\xff\x00", b"\xff") for a, b in zip(cut, [*stops, end], strict=True)], at + end


def _lookup(table: bytes, dc: bool) -> np.ndarray:
    """For each 16 bits ahead: value << 16 | odd << 10 | run << 6 | bits used.

    odd: 0 a value, 1 end of block, 2 no value but a run (or a DC of 0), 3 more than 16 bits: value holds the size.
    """
    out, code, at = np.full(1 << 16, 3 << 10, np.int64), 0, 16
    for n in range(1, 17):
        for symbol in table[at : at + table[n - 1]]:
            lo = code << (16 - n)
            ahead = np.arange(lo, lo + (1 << (16 - n)))
            run, size = (0, symbol) if dc else (symbol >> 4, symbol & 15)
            if size == 0:
                kind = 2 if dc or run == 15 else 1
                out[ahead] = kind << 10 | run << 6 | n
            elif n + size > 16:
                out[ahead] = size << 16 | 3 << 10 | run << 6 | n
            else:
                amp = (ahead >> (16 - n - size)) & ((1 << size) - 1)
                value = np.where(amp >> (size - 1), amp, amp - (1 << size) + 1)
                out[ahead] = (value << 16) | run << 6 | (n + size)
            code += 1
        at += table[n - 1]
        code <<= 1
    return out


def _advance(words: np.ndarray, pos: np.ndarray, lut: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, bool]:
    """One symbol for each lane: value, run, kind; moves pos."""
    ahead = (words[pos >> 3] << (pos & 7).astype(np.uint64)) >> np.uint64(48)
    e = lut[ahead]
    pos += e & 63
    if not (e & 0xFC0).any():
        return e >> 16, None, None, False
    value, run, kind = e >> 16, (e >> 6) & 15, (e >> 10) & 3
    if (long := kind == 3).any():
        p, size = pos[long], value[long]
        amp = ((words[p >> 3] << (p & 7).astype(np.uint64)) >> np.uint64(32)).astype(np.int64) >> (32 - size)
        value[long] = np.where(amp >> (size - 1), amp, amp - (1 << size) + 1)
        pos[long] = p + size
        kind[long] = 0
    value[kind != 0] = 0
    return value, run, kind, True


def decode_scans(images: list[Jpeg]) -> list[np.ndarray]:
    """Coefficients of each image, (units, blocks in a unit, 64) in scan order; images with like tables go together."""
    groups = defaultdict(list)
    for k, x in enumerate(images):
        groups[(tuple(p[1:3] + p[4:] for p in x.parts), tuple(sorted(x.huffman.items())))].append(k)
    out: list = [None] * len(images)
    for (parts, huffman), members in groups.items():
        tables = dict(huffman)
        plan = [(c, _lookup(tables[p[2]], True), _lookup(tables[16 + p[3]], False)) for c, p in enumerate(parts) for _ in range(p[0] * p[1] if len(parts) > 1 else 1)]
        chunks, left, owner = [], [], []
        for k in members:
            total = int(np.prod(images[k].units))
            step = images[k].interval or total
            for n, s in enumerate(images[k].scans):
                chunks.append(s + b"\xff" * 10)
                left.append(min(step, total - n * step))
                owner.append(k)
        left = np.array(left)
        begin = np.cumsum([0, *map(len, chunks)])[:-1]
        raw = np.frombuffer(b"".join(chunks), np.uint8).astype(np.uint64)
        words = np.zeros(len(raw), np.uint64)
        for b in range(8):
            words[: len(raw) - b] |= raw[b:] << np.uint64(56 - 8 * b)
        first = np.concatenate([[0], np.cumsum(left)])
        coefs = np.zeros((int(first[-1]), len(plan), 64), np.int16)
        pos, before = begin * 8, np.zeros((len(parts), len(chunks)), np.int64)
        lanes = np.arange(len(chunks))
        for unit in range(int(left.max(initial=0))):
            if unit:
                keep_ = left[lanes] > unit
                lanes, pos = lanes[keep_], pos[keep_]
            row = first[lanes] + unit
            for b, (c, dc, ac) in enumerate(plan):
                value, *_ = _advance(words, pos, dc)
                before[c, lanes] += value
                coefs[row, b, 0] = before[c, lanes]
                _block(words, pos, ac, coefs, row, b)
        for k in set(owner):
            mine = [n for n, o in enumerate(owner) if o == k]
            out[k] = coefs[first[mine[0]] : first[mine[-1] + 1]]
    return out


def _block(words, pos, lut, coefs, row, b) -> None:
    """The 63 other coefficients; lanes stay in step until one meets a run or an end of block."""
    k = 1
    while k < 64:
        value, run, kind, odd = _advance(words, pos, lut)
        if odd:
            break
        coefs[row, b, k] = value
        k += 1
    else:
        return
    at, on = np.full(len(pos), k), np.arange(len(pos))
    while True:
        if odd:
            at[on] += run
            some = kind == 0
            coefs[row[on[some]], b, np.minimum(at[on[some]], 63)] = value[some]
            at[on] = np.where(kind == 1, 64, at[on] + 1)
        else:
            coefs[row[on], b, at[on]] = value
            at[on] += 1
        on = on[at[on] < 64]
        if not len(on):
            return
        p = pos[on]
        value, run, kind, odd = _advance(words, p, lut)
        pos[on] = p


def payload_from(image: Jpeg, coefs: np.ndarray) -> bytes:
    return BYTE[coefs.reshape(-1).astype(np.int64) + 256][: int(image.comment.removeprefix(b"payload="))].tobytes()


def thumbnail(image: Jpeg, coefs: np.ndarray) -> np.ndarray:
    """Luminance from DC values alone, one pixel for each 8 x 8 block."""
    across, down = image.units
    h, v = image.parts[0][1:3] if len(image.parts) > 1 else (1, 1)
    dc = coefs[:, : h * v, 0].astype(np.int64) * int(image.quantisers[image.parts[0][3]][0])
    grid = dc.reshape(down, across, v, h).transpose(0, 2, 1, 3).reshape(down * v, across * h)
    return np.clip((grid + 4) // 8 + 128, 0, 255).astype(np.uint8)


def feature(image: Jpeg, coefs: np.ndarray) -> str:
    """width x height, a 64-bit difference hash and a crc of the thumbnail."""
    thumb = thumbnail(image, coefs)
    flat = thumb.reshape(-1).astype(np.int64)
    means = np.add.reduceat(np.concatenate([flat, flat[-1:]]), np.minimum(np.arange(65) * len(flat) // 65, len(flat))) / np.maximum(1, np.diff([*(np.arange(65) * len(flat) // 65), len(flat)]))
    rising = np.packbits(means[1:] > means[:-1]).tobytes().hex()
    return f"{image.width}x{image.height}:{rising}:{zlib.crc32(thumb.tobytes()):08x}"


_STORED = "doc_id long, n_bytes long, media binary"
_FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes and the media column, written to a table."""
    ship(docs.sparkSession)

    def files(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in size_bounded_batches(batches, 1, 1 << 20):
            texts = [t.encode() for t in batch.column(1).to_pylist()]
            media = write_jpegs([payload_of(t) for t in texts])
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    return keep(id_and_text(docs, id_col, text_col).mapInArrow(files, _STORED), "media")


def features(stored: DataFrame) -> DataFrame:
    """What the stored bytes hold: payload digests, file digests, thumbnail feature."""
    ship(stored.sparkSession)

    def read(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in size_bounded_batches(batches, 2, 1 << 19):
            files = batch.column(2).to_pylist()
            images = [parse(f) for f in files]
            rows = []
            for doc_id, n, f, image, coefs in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), files, images, decode_scans(images), strict=True):
                payload = payload_from(image, coefs)
                rows.append((doc_id, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(f), hashlib.sha256(f).hexdigest(), feature(image, coefs)))
            types = [pa.int64()] * 3 + [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            names = [c.split()[0] for c in _FEATURES.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)

    return keep(stored.select("doc_id", "n_bytes", F.col("media")).mapInArrow(read, _FEATURES), "media_features")
