"""Sharding by a keyed permutation of global row numbers, in DataFrame functions only.

Rows get dense numbers in key order; a Feistel network over Z_a x Z_b (a*b is about the row count,
and never below it) permutes them, and cycle walking brings the few values outside back in.  Row
``p`` of the permuted order goes to shard ``p mod n``, slot ``p div n``: shard sizes differ by one
at most, slots have no gaps, and a row's place follows from its number, the row count and the seed
alone.

Nulls: a null id sorts first; null text has no bytes.  Repeated rows are numbered one after the
other.  An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import id_and_text, keep

ROUNDS = 6
#: Only about two in sqrt(rows) values need a walk at all, so more steps in a row than this don't occur; if one did, the job stops.
MOST_WALKS = 256


def _div(x: Column, y: Column) -> Column:
    return ((x - F.pmod(x, y)) / y).cast("long")


def _permuted(x: Column, a: Column, b: Column, seed: int) -> Column:
    """One pass of the network: the two coordinates take turns, each moved by a hash of the other."""
    left, right = _div(x, b), F.pmod(x, b)
    for k in range(ROUNDS):
        if k % 2 == 0:
            left = F.pmod(left + F.pmod(F.xxhash64(F.lit(seed).cast("long"), F.lit(k).cast("long"), right), a), a)
        else:
            right = F.pmod(right + F.pmod(F.xxhash64(F.lit(seed).cast("long"), F.lit(k).cast("long"), left), b), b)
    return left * b + right


def permuted_rows(numbered: DataFrame, seed: int = 1) -> DataFrame:
    """``numbered`` has ``row`` (0 to n_rows - 1) and ``n_rows``; adds ``place``, a permutation of the same numbers."""
    sized = numbered.withColumn("_a", F.ceil(F.sqrt(F.col("n_rows").cast("double"))).cast("long"))
    sized = sized.withColumn("_b", _div(F.col("n_rows") + F.col("_a") - 1, F.col("_a")))
    n, a, b = F.col("n_rows"), F.col("_a"), F.col("_b")
    once = sized.withColumn("_p", _permuted(F.col("row"), a, b, seed))
    # a walk that starts inside comes back inside after at most as many steps as there are values outside
    steps = F.sequence(F.lit(1).cast("long"), F.least(a * b - n + 1, F.lit(MOST_WALKS).cast("long")))
    walked = F.aggregate(steps, F.col("_p"), lambda p, _: F.when(p < n, p).otherwise(_permuted(p, a, b, seed)))
    found = F.when(F.col("_p") < n, F.col("_p")).otherwise(walked)
    return (
        once.withColumn("place", found)
        .withColumn("place", F.when(F.col("place") < n, F.col("place")).otherwise(F.raise_error(F.lit("a walk didn't end")).cast("long")))
        .drop("_a", "_b", "_p")
    )


def row_numbers(rows: DataFrame, *order: Column, name: str = "rows") -> DataFrame:
    """Dense numbers from 0 as ``row`` in the given order, and ``n_rows``, with no window over all rows.

    Range-partitioned rows are numbered within their partition; what is summed up over partitions
    is one row for each, so the broadcast is bounded by the number of shuffle partitions.
    """
    low = (1 << 33) - 1
    cut = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    cut = keep(cut.select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().bitwiseAND(F.lit(low)).alias("_at")), name)
    counts = cut.groupBy("_part").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_part")
    starts = counts.select("_part", (F.sum("_n").over(before) - F.col("_n")).alias("_start"), F.sum("_n").over(before.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("n_rows"))
    return cut.join(F.broadcast(starts), "_part").withColumn("row", F.col("_start") + F.col("_at")).drop("_part", "_at", "_start")


def shard(docs: DataFrame, n_shards: int = 40, seed: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, row, shard, slot: the text itself never moves."""
    text = F.col("text")
    sized = id_and_text(docs, id_col, text_col).select("doc_id", (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).cast("long").alias("text_crc32"))
    placed = permuted_rows(row_numbers(sized, F.col("doc_id").asc_nulls_first(), F.col("size"), F.col("text_crc32"), name="shard"), seed)
    n = F.lit(n_shards).cast("long")
    return placed.select("doc_id", "size", "text_crc32", "row", F.pmod("place", n).cast("int").alias("shard"), _div(F.col("place"), n).alias("slot"))
