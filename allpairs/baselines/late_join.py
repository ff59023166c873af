"""Shared sums first and totals joined to the pairs afterwards: the step that carrying totals avoids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import Measure
from ..partials import conjunctive_sums
from ..similarity.index import pair_increments
from ..similarity.possible import among, dealt_near
from ..similarity.score import value_of
from .brute_force import _with_totals


def late_join(raw: DataFrame, measure: Measure, t: float, inclusive: bool = True, near: DataFrame | None = None) -> DataFrame:
    """``near`` as in :func:`allpairs.join.similarity_join`."""
    raw = raw if near is None else among(raw, near)
    shared = conjunctive_sums(pair_increments(raw if near is None else dealt_near(raw, near)), measure)
    return _with_totals(shared, raw, measure).withColumn("sim", value_of(measure)).filter(measure.passes(F.col("sim"), t, inclusive)).select("e1", "e2", "sim")
