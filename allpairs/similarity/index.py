"""Pairs of entities inside each element's list."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..measures import Measure
from .possible import KEYS, OWN


def _sides(joined: DataFrame, *more: str) -> tuple[DataFrame, DataFrame]:
    """Two views of the same columns in the same order, so that both reuse one exchange."""
    uni = sorted(c for c in joined.columns if c.startswith("uni_"))
    base = joined.select("element", "entity", "mult", *uni, *near_columns(joined), *more)
    return base.alias("l"), base.alias("r")


def near_columns(joined: DataFrame) -> list[str]:
    """What :func:`allpairs.similarity.possible.dealt_near` has added, if anything."""
    return [c for c in (*KEYS, OWN) if c in joined.columns]


def met_near(joined: DataFrame, left: str = "l.{}", right: str = "r.{}") -> Column:
    """Only rows of one group meet; with two chunks under a key, pairs inside either belong to that chunk's own key."""
    out = F.lit(True)
    if OWN in joined.columns:
        for c in KEYS:
            out = out & (F.col(left.format(c)) == F.col(right.format(c)))
        out = out & ((F.col(left.format("near_p")) == F.col(left.format("near_q"))) | (F.col(left.format(OWN)) != F.col(right.format(OWN))))
    return out


def carried(joined: DataFrame) -> list[Column]:
    uni = sorted(c for c in joined.columns if c.startswith("uni_"))
    return [*(F.col(f"l.{c}").alias(f"{c}_1") for c in uni), *(F.col(f"r.{c}").alias(f"{c}_2") for c in uni)]


def totals_of(measure: Measure, left: str, right: str) -> tuple[dict, dict]:
    return {n: F.col(left.format(n)) for n in measure.uni}, {n: F.col(right.format(n)) for n in measure.uni}


def pair_increments(joined: DataFrame, measures: tuple[Measure, ...] = (), t: float | None = None, impl: str = "join", prune: bool | str = False, hint: str | None = "merge", with_element: bool = False) -> DataFrame:
    """e1, e2 (e1 < e2), f1, f2 and both entities' totals, a row for each shared element.

    ``join`` equi-joins the rows with themselves; its match buffer is on disk if it must be.
    ``list`` gathers each list in memory and pairs it there, for comparison.  ``prune`` leaves out pairs whose totals
    alone rule them out; ``prune='bands'`` never forms most of them (see :func:`_banded`).
    """
    if impl == "list":
        return _from_lists(joined)
    if prune == "bands" and len(measures) == 1 and t is not None and measures[0].least_ratio is not None and measures[0].least_ratio(t) < 1:
        return _banded(joined, measures[0], t, hint)
    left, right = _sides(joined)
    on = met_near(joined) & (F.col("l.element") == F.col("r.element")) & (F.col("l.entity") < F.col("r.entity"))
    if prune and t is not None:
        for m in measures:
            if m.bound is not None:
                a, b = totals_of(m, "l.uni_{}", "r.uni_{}")
                on = on & m.bound(a, b, t)
    pairs = left.join(right.hint(hint) if hint else right, on)
    element = [F.col("l.element").alias("element")] if with_element else []
    return pairs.select(F.col("l.entity").alias("e1"), F.col("r.entity").alias("e2"), F.col("l.mult").alias("f1"), F.col("r.mult").alias("f2"), *carried(joined), *element)


def _banded(joined: DataFrame, measure: Measure, t: float, hint: str | None) -> DataFrame:
    """The same for a measure whose totals may differ by a ratio at most: a list is cut into bands of totals that wide, and a row
    meets those of its own band and, as the smaller of the two, of the next.  Rows are shipped three times and not once, and of a
    list only near totals are compared, so this pays where lists are long and totals spread.
    """
    total = f"uni_{measure.uni[0]}"
    width = -math.log(measure.least_ratio(t)) * (1 + 1e-9)  # a little wider, so that rounding loses no pair at the border
    uni = sorted(c for c in joined.columns if c.startswith("uni_"))
    rows = joined.select("element", "entity", "mult", *uni, *near_columns(joined), F.floor(F.log(F.col(total).cast("double")) / width).alias("_band"))
    small = rows.withColumn("_band", F.explode(F.array(F.col("_band"), F.col("_band") + 1))).alias("l")
    large = rows.alias("r")
    order = F.struct(F.col(f"l.{total}"), F.col("l.entity")) < F.struct(F.col(f"r.{total}"), F.col("r.entity"))
    on = met_near(joined) & (F.col("l.element") == F.col("r.element")) & (F.col("l._band") == F.col("r._band")) & order & measure.bound(*totals_of(measure, "l.uni_{}", "r.uni_{}"), t)
    first = F.col("l.entity") < F.col("r.entity")

    def side(c: str, mine: bool) -> Column:
        return F.when(first == mine, F.col(f"l.{c}")).otherwise(F.col(f"r.{c}"))

    pairs = small.join(large.hint(hint) if hint else large, on)
    return pairs.select(side("entity", True).alias("e1"), side("entity", False).alias("e2"), side("mult", True).alias("f1"), side("mult", False).alias("f2"), *(side(c, True).alias(f"{c}_1") for c in uni), *(side(c, False).alias(f"{c}_2") for c in uni))


def _from_lists(joined: DataFrame) -> DataFrame:
    uni = sorted(c for c in joined.columns if c.startswith("uni_"))
    near = near_columns(joined)
    lists = joined.groupBy("element", *near[:-1]).agg(F.sort_array(F.collect_list(F.struct("entity", "mult", *uni, *near))).alias("all"))
    first = lists.select(F.posexplode("all").alias("at", "x"), "all")
    both = first.select("x", F.explode(F.slice("all", F.col("at") + 2, F.size("all"))).alias("y")).filter(met_near(joined, "x.{}", "y.{}"))
    return both.select(F.col("x.entity").alias("e1"), F.col("y.entity").alias("e2"), F.col("x.mult").alias("f1"), F.col("y.mult").alias("f2"), *(F.col(f"x.{c}").alias(f"{c}_1") for c in uni), *(F.col(f"y.{c}").alias(f"{c}_2") for c in uni))


def increments_between(left: DataFrame, right: DataFrame) -> DataFrame:
    """The same for two collections: e1 from the left, e2 from the right."""
    names = sorted(c for c in left.columns if c.startswith("uni_"))
    on = F.col("l.element") == F.col("r.element")
    met = left.alias("l").join(right.alias("r"), on)
    return met.select(F.col("l.entity").alias("e1"), F.col("r.entity").alias("e2"), F.col("l.mult").alias("f1"), F.col("r.mult").alias("f2"), *(F.col(f"l.{c}").alias(f"{c}_1") for c in names), *(F.col(f"r.{c}").alias(f"{c}_2") for c in names))
