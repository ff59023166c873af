"""Token ids in a fixed-width bit-packed format with random access.

An image holds consecutive documents: a header, document ids and lengths, block offsets, then the
ids in blocks, each id in as few bits as the vocabulary needs.  64 ids fill a whole number of 64-bit
words, so packing and unpacking are 64 numpy shifts for any count, and any block can be unpacked
alone.  Images are rows of a Parquet table (part, seq, at, n_ids, n_docs, image), so any store that
Spark writes to can hold them, a lost executor's task is simply run again, and the columns beside
the image answer which image has the k-th id of the corpus without reading any.

Documents come in ascending id order (null first, ties by text); null text is empty: only its end
id.  An empty table gives no image.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_and_text, keep, ship, size_bounded_batches

MAGIC = b"idpack01"
_HEAD = struct.Struct("<8sBIQQ")
BLOCK_IDS = 4096
#: An image is closed when it holds so many ids, or more with the last document.
IMAGE_IDS = 1 << 19
NO_ID = -(1 << 63)


def width(vocabulary: int) -> int:
    return max(1, (vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Rows of 64 ids become rows of ``bits`` 64-bit words."""
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    rows = -(-len(ids) // 64)
    lanes = np.zeros((rows, 64), np.uint64)
    lanes.reshape(-1)[: len(ids)] = ids
    words = np.zeros((rows, bits + 1), np.uint64)
    for k in range(64):
        at, low = divmod(k * bits, 64)
        words[:, at] |= lanes[:, k] << np.uint64(low)
        if low + bits > 64:
            words[:, at + 1] |= lanes[:, k] >> np.uint64(64 - low)
    return words[:, :bits].astype("<u8").tobytes()


def unpack(data: bytes | memoryview, n: int, bits: int) -> np.ndarray:
    if bits in (8, 16, 32):
        return np.frombuffer(data, f"<u{bits // 8}", n).astype(np.uint32)
    rows = -(-n // 64)
    words = np.frombuffer(data, "<u8", rows * bits).reshape(rows, bits)
    lanes, mask = np.empty((rows, 64), np.uint32), np.uint64((1 << bits) - 1)
    for k in range(64):
        at, low = divmod(k * bits, 64)
        lane = words[:, at] >> np.uint64(low)
        if low + bits > 64:
            lane = lane | words[:, at + 1] << np.uint64(64 - low)
        lanes[:, k] = lane & mask
    return lanes.reshape(-1)[:n]


def write_image(doc_ids: list[int], lengths: list[int], ids: np.ndarray, bits: int) -> bytes:
    blocks = [pack(ids[k : k + BLOCK_IDS], bits) for k in range(0, len(ids), BLOCK_IDS)]
    offsets = np.cumsum([0, *map(len, blocks)], dtype="<u8")
    return b"".join([_HEAD.pack(MAGIC, bits, BLOCK_IDS, len(doc_ids), len(ids)), np.array(doc_ids, "<i8").tobytes(), np.array(lengths, "<u8").tobytes(), offsets.tobytes(), *blocks])


class Image:
    """A written image; ``ids(start, stop)`` unpacks only the blocks that it needs."""

    def __init__(self, data: bytes):
        magic, self.bits, self.block, self.n_docs, self.n_ids = _HEAD.unpack_from(data)
        if magic != MAGIC:
            raise ValueError("not an image of this format")
        at = _HEAD.size
        self.doc_ids = np.frombuffer(data, "<i8", self.n_docs, at)
        self.lengths = np.frombuffer(data, "<u8", self.n_docs, at + 8 * self.n_docs).astype(np.int64)
        at += 16 * self.n_docs
        n_blocks = -(-self.n_ids // self.block)
        self.offsets = np.frombuffer(data, "<u8", n_blocks + 1, at).astype(np.int64)
        self.blocks = memoryview(data)[at + 8 * (n_blocks + 1) :]

    def ids(self, start: int, stop: int) -> np.ndarray:
        parts = []
        for b in range(start // self.block, -(-stop // self.block)):
            n = min(self.block, self.n_ids - b * self.block)
            got = unpack(self.blocks[self.offsets[b] : self.offsets[b + 1]], n, self.bits)
            parts.append(got[max(0, start - b * self.block) : stop - b * self.block])
        return np.concatenate(parts) if parts else np.empty(0, np.uint32)


_IMAGES = "part int, seq int, at long, n_ids long, n_docs long, image binary"


def write(docs: DataFrame, model: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The table of images of all documents."""
    ship(docs.sparkSession)

    def images(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark import TaskContext

        from allpairs.llm.tokens import encoder

        enc, part = encoder(model), TaskContext.get().partitionId()
        bits, end = width(max(enc.vocabulary, end_id + 1)), np.uint32(end_id).tobytes()
        doc_ids, lengths, parts, seq, at, n = [], [], [], 0, 0, 0

        def closed():
            image = write_image(doc_ids, lengths, np.frombuffer(b"".join(parts), "<u4"), bits)
            return pa.RecordBatch.from_pylist([{"part": part, "seq": seq, "at": at, "n_ids": n, "n_docs": len(doc_ids), "image": image}], schema=pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("at", pa.int64()), ("n_ids", pa.int64()), ("n_docs", pa.int64()), ("image", pa.binary())]))

        for batch in size_bounded_batches(batches, 1, 1 << 20):
            for doc_id, ids in zip(batch.column(0).to_pylist(), enc.encode(batch.column(1).to_pylist()), strict=True):
                ids += end
                doc_ids.append(NO_ID if doc_id is None else doc_id)
                lengths.append(len(ids) // 4)
                parts.append(ids)
                n += lengths[-1]
                if n >= IMAGE_IDS:
                    yield closed()
                    seq, at, n = seq + 1, at + n, 0
                    doc_ids, lengths, parts = [], [], []
        if doc_ids:
            yield closed()

    order = [F.col("doc_id").asc_nulls_first(), F.col("text")]
    rows = id_and_text(docs, id_col, text_col).repartitionByRange(order[0]).sortWithinPartitions(*order)
    return keep(rows.mapInArrow(images, _IMAGES), "images")


def starts(images: DataFrame) -> DataFrame:
    """Ids before each part: one row for each part that was written, so a bounded table."""
    parts = images.groupBy("part").agg(F.sum("n_ids").alias("n"))
    return parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("part_start"))


def read(images: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the stored images."""
    ship(images.sparkSession)

    def documents_of(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            for k in range(batch.num_rows):
                image = Image(batch.column(1)[k].as_py())
                ids = image.ids(0, image.n_ids).astype("<u4")
                ends = np.cumsum(image.lengths)
                begins = ends - image.lengths
                crcs = [zlib.crc32(ids[b:e]) for b, e in zip(begins, ends, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(image.doc_ids, mask=image.doc_ids == NO_ID), pa.array(begins + batch.column(0)[k].as_py()), pa.array(image.lengths), pa.array(crcs, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    placed = images.join(F.broadcast(starts(images)), "part").select((F.col("part_start") + F.col("at")).alias("start"), "image")
    return keep(placed.mapInArrow(documents_of, "doc_id long, start long, n_tokens long, ids_crc32 long"), "token_rows")


def slice_ids(images: DataFrame, start: int, stop: int) -> np.ndarray:
    """Ids ``start`` to ``stop`` of the corpus: only the images that hold them are read, only their blocks unpacked, and only these ids reach the driver."""
    ship(images.sparkSession)

    def cut(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            for k in range(batch.num_rows):
                begin, n, image = (batch.column(c)[k].as_py() for c in range(3))
                ids = Image(image).ids(max(0, start - begin), min(n, stop - begin)).astype("<u4")
                yield pa.RecordBatch.from_arrays([pa.array([begin], pa.int64()), pa.array([ids.tobytes()], pa.binary())], ["begin", "ids"])

    begin = F.col("part_start") + F.col("at")
    hit = images.join(F.broadcast(starts(images)), "part").withColumn("begin", begin).filter((F.col("begin") < stop) & (F.col("begin") + F.col("n_ids") > start))
    parts = hit.select("begin", "n_ids", "image").mapInArrow(cut, "begin long, ids binary").orderBy("begin").collect()
    return np.frombuffer(b"".join(bytes(r["ids"]) for r in parts), "<u4")
