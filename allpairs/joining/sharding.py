"""Totals from a table for the few giant entities, and in place for all others.

Entities of more than C elements are giants: their totals are looked up, so their rows can be dealt
over many tasks by a fingerprint of the element.  Others keep their rows together, at most C of
them, and are totalled there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..measures import Measure
from ..partials import totals_wanted, unilateral_totals
from ..scratch import once, written
from .lookup import DEFAULT_BYTES, MOST_ROWS, LookupTableTooLarge, footprint


def sharded_totals(raw: DataFrame, *measures: Measure, C: int = 1000) -> DataFrame:  # noqa: N803
    """Totals of entities with more than C elements."""
    from ..measures import jaccard

    return unilateral_totals(raw, *measures, jaccard()).filter(F.col("uni_ucard") > C)


def attach_sharding(raw: DataFrame, *measures: Measure, C: int = 1000, fingerprint_buckets: int = 64, route_giants: bool = True, max_table_bytes: int = DEFAULT_BYTES) -> DataFrame:  # noqa: N803
    wanted = totals_wanted(measures)
    if not wanted:
        return raw
    raw = once(raw, "raw_rows")
    giants = written(sharded_totals(raw, *measures, C=C), "giant_totals")
    rows, size = footprint(giants)
    if rows > MOST_ROWS or size > max_table_bytes:
        raise LookupTableTooLarge(f"{rows} entities of more than {C} elements take about {size} bytes; the budget is {max_table_bytes}")
    return routed_rows(raw, giants, measures, fingerprint_buckets, route_giants)


def routed_rows(raw: DataFrame, giants: DataFrame, measures: tuple[Measure, ...], fingerprint_buckets: int = 64, route_giants: bool = True) -> DataFrame:
    """Rows of giants with their totals from the table, all others with totals made in place; the table is broadcast."""
    wanted = totals_wanted(measures)
    table = giants.select("entity", *(F.col(f"uni_{n}").alias(f"_big_{n}") for n in wanted), F.lit(True).alias("_giant"))
    of = {name: m for m in measures for name in m.uni}
    if not route_giants:
        found = raw.join(F.broadcast(table), "entity").select(*raw.columns, *(F.col(f"_big_{n}").alias(f"uni_{n}") for n in wanted))
        rest = raw.join(F.broadcast(table.select("entity")), "entity", "left_anti")
        group = Window.partitionBy("entity")
        return found.unionByName(rest.select("*", *(of[n].total(n)(F.col("mult")).over(group).alias(f"uni_{n}") for n in wanted)))
    probed = raw.join(F.broadcast(table), "entity", "left")
    route = F.when(F.col("_giant"), F.pmod(F.xxhash64("element"), F.lit(fingerprint_buckets))).otherwise(F.lit(-1).cast("long"))
    group = Window.partitionBy("entity", "_route")
    routed = probed.withColumn("_route", route)
    return routed.select(*raw.columns, *(F.coalesce(F.col(f"_big_{n}"), of[n].total(n)(F.col("mult")).over(group)).alias(f"uni_{n}") for n in wanted))
