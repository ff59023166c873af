"""Totals from a table that tasks hold: whole and without a shuffle of the rows where it is small, else each its part by entity."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import Measure
from ..partials import totals_wanted, unilateral_totals
from ..scratch import once, written

#: What Spark can broadcast at all.
MOST_ROWS = 512_000_000
DEFAULT_BYTES = 1 << 30
#: A larger table isn't gathered by the driver and sent to every task; rows and table are dealt by entity, and each task looks up in its part.
BROADCAST_BYTES = 1 << 26


class LookupTableTooLarge(RuntimeError):
    """The table of totals doesn't fit where each task would have to hold it."""


def lookup_build(raw: DataFrame, *measures: Measure) -> DataFrame:
    return unilateral_totals(raw, *measures)


def footprint(totals: DataFrame) -> tuple[int, int]:
    """Rows of the table and about how many bytes they take as a hash relation: keys of any width, 8 bytes a total, 48 around."""
    numbers = 8 * (len(totals.columns) - 1)
    key = F.octet_length(F.col("entity").cast("string")) if dict(totals.dtypes)["entity"] == "string" else F.lit(8)
    got = totals.agg(F.count("*").alias("rows"), F.coalesce(F.sum(key + numbers + 48), F.lit(0)).cast("long").alias("bytes")).first()
    return got["rows"], got["bytes"]


def attach_lookup(raw: DataFrame, *measures: Measure, max_table_bytes: int = DEFAULT_BYTES, totals: DataFrame | None = None) -> DataFrame:
    """Raises LookupTableTooLarge if the table of totals is over the budget; it is measured, not guessed.

    The table is written once and measured and broadcast from there; so are raw rows that are themselves made by more than a scan.  Above ``BROADCAST_BYTES`` it isn't broadcast but dealt by entity.
    """
    if not totals_wanted(measures):
        return raw
    raw = once(raw, "raw_rows")
    table = written(lookup_build(raw, *measures), "totals") if totals is None else totals
    rows, size = footprint(table)
    if rows > MOST_ROWS or size > max_table_bytes:
        raise LookupTableTooLarge(f"{rows} entities take about {size} bytes; the budget is {max_table_bytes}")
    return raw.join(F.broadcast(table) if size <= BROADCAST_BYTES else table.hint("shuffle_hash"), "entity")
