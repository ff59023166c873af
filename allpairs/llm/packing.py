"""Best-fit packing of documents into sequences, by residuals up a tree.

Each task tokenizes its documents and packs their pieces best-fit, longest first, in blocks of
bounded size.  Sequences that are nearly full are final.  The others become items of their own: a
round deals them into nodes of about NODE_ITEMS, packs each node best-fit again, and so on with
what is still underfull.  A round has so many nodes that none holds more than twice that, so the
tree is as wide as the data asks for and nothing is left out; it ends at one node, or when a round
no longer joins one item in LEAST_GAIN.

Only documents longer than a sequence are cut, into whole sequences; the last piece may be shorter.
Null text is the empty text, one end id.  Repeated rows are packed each.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, keep, ship, size_bounded_batches

BLOCK_PIECES = 1 << 16
NODE_ITEMS = 1 << 15
#: Items of which a round must join at least one, or it is the last.
LEAST_GAIN = 1000
#: A sequence with less room than this is final.
NEARLY_FULL = 4


def best_fit(lengths: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin and offset of each item, and what each bin holds; longest items first, each into the fullest bin that takes it."""
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    by_room: list[list[int]] = [[] for _ in range(room + 1)]
    fill: list[int] = []
    some = 0  # bit r: there is a bin with r left
    for k in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[k])
        fitting = some >> n
        if fitting:
            left = n + (fitting & -fitting).bit_length() - 1
            b = by_room[left].pop()
            if not by_room[left]:
                some ^= 1 << left
        else:
            left, b = room, len(fill)
            fill.append(0)
        bins[k], offsets[k] = b, fill[b]
        fill[b] += n
        if left > n:
            by_room[left - n].append(b)
            some |= 1 << (left - n)
    return bins, offsets, np.array(fill, np.int64)


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, bin long, at long"


def _pieces(docs: DataFrame, model: str, room: int, end_id: int) -> DataFrame:
    def packed(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark import TaskContext

        from allpairs.llm.tokens import encoder

        enc, end = encoder(model), np.uint32(end_id).tobytes()
        first = TaskContext.get().partitionId() << 32
        rows: list[tuple] = []

        def block():
            nonlocal first
            doc, piece, start, length, crc = zip(*rows, strict=True)
            bins, at, fill = best_fit(np.array(length, np.int64), room)
            out = pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array(bins + first), pa.array(at)], ["doc_id", "piece", "start", "length", "ids_crc32", "bin", "at"])
            first += len(fill)
            return out

        for batch in size_bounded_batches(batches, 1, 1 << 20):
            for doc_id, ids in zip(batch.column(0).to_pylist(), enc.encode(batch.column(1).to_pylist()), strict=True):
                ids += end
                for k in range(0, len(ids), 4 * room):
                    part = ids[k : k + 4 * room]
                    rows.append((doc_id, k // (4 * room), k // 4, len(part) // 4, zlib.crc32(part)))
            if len(rows) >= BLOCK_PIECES:
                yield block()
                rows = []
        if rows:
            yield block()

    return docs.mapInArrow(packed, _PIECES)


def _merged(items: DataFrame, room: int) -> DataFrame:
    """One round: items (bin, fill, node) become (bin, into, at, held)."""

    def node(table):
        import pyarrow as pa

        table = table.sort_by("bin")
        of, lengths = table.column("bin").to_numpy(), table.column("fill").to_numpy()
        bins, at, fill = best_fit(lengths, room)
        head = np.full(len(fill), np.iinfo(np.int64).max)
        np.minimum.at(head, bins, of)
        return pa.table({"bin": of, "into": head[bins], "at": at, "held": fill[bins]})

    return items.groupBy("node").applyInArrow(node, "bin long, into long, at long, held long")


def pack(docs: DataFrame, model: str, room: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    spark = docs.sparkSession
    ship(spark)
    pieces = keep(_pieces(id_and_text(docs, id_col, text_col), model, room, end_id), "pieces")
    items = pieces.groupBy("bin").agg(F.sum("length").cast("long").alias("fill")).filter(F.col("fill") <= room - NEARLY_FULL)
    items = keep(items, "residuals")
    places, n, turn = None, items.count(), 0
    while n:
        turn += 1
        # a hash of bin and round deals every node a like mixture of all tasks' bins
        nodes = -(-n // NODE_ITEMS)
        level = keep(_merged(items.withColumn("node", F.pmod(F.xxhash64("bin", F.lit(turn)), F.lit(nodes))), room), "merged")
        step = level.select("bin", "into", "at")
        if places is None:
            places = step.select("bin", "into", F.col("at").alias("base"))
        else:
            up = step.select(F.col("bin").alias("into"), F.col("into").alias("_into"), F.col("at").alias("_at"))
            places = keep(places.join(up, "into", "left").select("bin", F.coalesce("_into", "into").alias("into"), (F.col("base") + F.coalesce("_at", F.lit(0))).alias("base")), "places")
        left = level.filter(F.col("held") <= room - NEARLY_FULL).groupBy(F.col("into").alias("bin")).agg(F.first("held").alias("fill"))
        items = keep(left, "residuals")
        before, n = n, items.count()
        if nodes == 1 or level.agg(F.count_distinct("into").alias("n")).first()["n"] >= before - before // LEAST_GAIN:
            break
    if places is None:
        return pieces.select("doc_id", "piece", "start", "length", "ids_crc32", F.col("bin").alias("sequence_id"), F.col("at").alias("offset"))
    final = pieces.join(places, "bin", "left")
    return final.select("doc_id", "piece", "start", "length", "ids_crc32", F.coalesce("into", "bin").alias("sequence_id"), (F.coalesce("base", F.lit(0)) + F.col("at")).alias("offset"))
