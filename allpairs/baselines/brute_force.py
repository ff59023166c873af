"""Every pair of entities compared over the union of their elements: the exact answer at any price."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..joining import attach_online
from ..measures import Measure
from ..partials import disjunctive_sums, shared_aggregates, unilateral_totals
from ..scratch import once
from ..similarity.blocks import fits, pair_sums_blocked
from ..similarity.score import value_of


def all_pairs(raw: DataFrame) -> DataFrame:
    ids = raw.select("entity").distinct()
    return ids.select(F.col("entity").alias("e1")).crossJoin(ids.select(F.col("entity").alias("e2"))).filter("e1 < e2")


def brute_force(raw: DataFrame, measure: Measure, t: float, inclusive: bool = True) -> DataFrame:
    """Blocks of entities meet in memory; for measures without such a form, all cells of all pairs are joined."""
    if fits(raw, measure):
        out = pair_sums_blocked(once(attach_online(raw, measure).filter("element is not null and mult is not null"), "joined_rows"), measure, t).withColumn("sim", value_of(measure))
        return out.filter(measure.passes(F.col("sim"), t, inclusive)).select("e1", "e2", "sim")
    pairs = all_pairs(raw)
    left = pairs.join(raw.select(F.col("entity").alias("e1"), "element", F.col("mult").alias("f1")), "e1")
    right = pairs.join(raw.select(F.col("entity").alias("e2"), "element", F.col("mult").alias("f2")), "e2")
    cells = left.join(right, ["e1", "e2", "element"], "full_outer")
    shared = cells.filter("f1 is not null and f2 is not null").groupBy("e1", "e2").agg(*shared_aggregates((measure,)))
    out = _with_totals(shared, raw, measure).withColumn("sim", value_of(measure))
    return out.filter(measure.passes(F.col("sim"), t, inclusive)).select("e1", "e2", "sim")


def _with_totals(pairs: DataFrame, raw: DataFrame, measure: Measure) -> DataFrame:
    if not measure.uni:
        return pairs
    totals = unilateral_totals(raw, measure)
    for side in "12":
        pairs = pairs.join(totals.select(F.col("entity").alias(f"e{side}"), *(F.col(f"uni_{n}").alias(f"uni_{n}_{side}") for n in measure.uni)), f"e{side}")
    return pairs


def ruzicka_disjunctive(raw: DataFrame, t: float, pairs: DataFrame | None = None) -> DataFrame:
    """Sum of least over sum of greatest, both over the union, with no rewriting."""
    ids = all_pairs(raw) if pairs is None else pairs
    low = disjunctive_sums(raw, ids, lambda a, b: F.least(a, b), name="low")
    high = disjunctive_sums(raw, ids, lambda a, b: F.greatest(a, b), name="high")
    return low.join(high, ["e1", "e2"]).filter("low > 0").withColumn("sim", F.col("low").cast("double") / F.col("high").cast("double")).filter(F.col("sim") >= t).select("e1", "e2", "sim")
