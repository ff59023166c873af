"""Sums over shared elements, the measure's value, and the threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import Measure
from ..partials import shared_aggregates


def summed_pairs(increments: DataFrame, measures: tuple[Measure, ...], carry: str = "key", totals: DataFrame | None = None) -> DataFrame:
    """One row a pair, with conj_ sums and both totals; partial sums are made before the shuffle.

    Totals travel in the grouping key (``key``), as any value of the group (``first``), or are joined again (``rejoin``).
    """
    uni = [c for c in increments.columns if c.startswith("uni_")]
    sums = shared_aggregates(measures)
    if carry == "key":
        return increments.groupBy("e1", "e2", *uni).agg(*sums)
    if carry == "first":
        return increments.groupBy("e1", "e2").agg(*sums, *(F.any_value(c).alias(c) for c in uni))
    if carry != "rejoin" or totals is None:
        raise ValueError("carry is key, first, or rejoin with totals")
    out = increments.groupBy("e1", "e2").agg(*sums)
    for side in ("1", "2"):
        named = totals.select(F.col("entity").alias(f"e{side}"), *(F.col(c).alias(f"{c}_{side}") for c in totals.columns if c != "entity"))
        out = out.join(named, f"e{side}")
    return out


def value_of(measure: Measure):
    conj = {n: F.col(f"conj_{measure.name}_{n}") for n in measure.conj}
    a, b = ({n: F.col(f"uni_{n}_{side}") for n in measure.uni} for side in "12")
    sim = measure.combine(conj, a, b)
    return F.round(sim, measure.digits) if measure.digits is not None else sim


def score_pairs(increments: DataFrame, measure: Measure, t: float | None, inclusive: bool = True, carry: str = "key", totals: DataFrame | None = None) -> DataFrame:
    """e1, e2, sim and what it was made of; t None gives all candidates."""
    scored = summed_pairs(increments, (measure,), carry, totals).withColumn("sim", value_of(measure))
    return scored if t is None else scored.filter(measure.passes(F.col("sim"), t, inclusive))
