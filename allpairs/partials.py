"""Totals, shared sums and sums over unions.

A per-element function g(x, y) of two multiplicities is unilateral if it needs one of them, conjunctive if it is 0
wherever one of them is, else disjunctive: it needs the union of both entities.  Sums of disjunctive functions
with g(0, 0) = 0 are rewritten: over the union they are both entities' own sums of g(x, 0) and g(0, y), and over
shared elements what g(x, y) exceeds those by.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .measures import Measure, UnsupportedMeasure

_PROBES = (1, 2, 3, 5, 8)


def unilateral_totals(raw: DataFrame, *measures: Measure) -> DataFrame:
    """entity and one ``uni_`` column for each total that any measure asks for; partial sums are made before the shuffle."""
    wanted = {name: m for m in measures for name in m.uni}
    if not wanted:
        return raw.select("entity").distinct()
    return raw.groupBy("entity").agg(*(m.total(name)(F.col("mult")).alias(f"uni_{name}") for name, m in sorted(wanted.items())))


def totals_wanted(measures) -> list[str]:
    return sorted({name for m in measures for name in m.uni})


def conjunctive_sums(increments: DataFrame, *measures: Measure) -> DataFrame:
    """Per pair, with whatever totals the increments carry in the key."""
    carried = [c for c in increments.columns if c.startswith("uni_")]
    return increments.groupBy("e1", "e2", *carried).agg(*shared_aggregates(measures))


def shared_aggregates(measures):
    made = {}
    for m in measures:
        for name, g in m.conj.items():
            made.setdefault(f"{m.name}.{name}", g)
    return [F.sum(g(F.col("f1"), F.col("f2"))).alias(f"conj_{key.replace('.', '_')}") for key, g in made.items()]


def measure_of(name: str, functions: dict[str, Callable], column_functions: dict[str, Callable], combine: Callable, digits: int | None = None) -> Measure:
    """A measure from plain per-element functions, each put by :func:`classify` where it belongs.

    ``functions`` are of two numbers, for telling what they need; ``column_functions`` the same on columns.
    ``combine`` gets shared sums and both entities' totals by these names.  A function of the left entity alone is a total;
    a disjunctive one is refused here: :func:`decompose_disjunctive` rewrites it.  ``digits`` rounds values before the threshold,
    for combiners that add fractions, whose sums may fall just short of it.
    """
    uni, conj = {}, {}
    for key, g in functions.items():
        needs = classify(g)
        if needs == {"uni"}:
            uni[key] = (lambda c: lambda f: c(f, F.lit(0)))(column_functions[key])
        elif needs == {"conj"}:
            conj[key] = column_functions[key]
        else:
            raise UnsupportedMeasure(f"{name}: {key} needs the union of both entities")
    return Measure(name, tuple(uni), conj, combine, digits=digits, totals=uni)


def classify(g: Callable[[float, float], float]) -> set[str]:
    """What a plain function of two multiplicities needs, told by probing it."""
    out = set()
    left = all(g(x, y) == g(x, 0) for x, y in product(_PROBES, _PROBES))
    right = all(g(x, y) == g(0, y) for x, y in product(_PROBES, _PROBES))
    if left or right:
        return {"uni"}
    if all(g(x, 0) == 0 and g(0, x) == 0 for x in _PROBES):
        out.add("conj")
    else:
        out.add("disj")
    return out


def decompose_disjunctive(name: str, g: Callable, aggregate: str = "sum", zero=lambda: F.lit(0)) -> Measure:
    """The measure sum over the union of g, from totals and shared sums; ``g`` works on columns.

    Other aggregates than sums don't split over the two entities and are refused.
    """
    if aggregate != "sum":
        raise UnsupportedMeasure(f"{name}: {aggregate} over a union doesn't split into totals and shared sums")
    return Measure(
        name,
        ("left", "right"),
        {"both": lambda f1, f2: g(f1, f2) - g(f1, zero()) - g(zero(), f2)},
        lambda c, a, b: (a["left"] + b["right"] + c["both"]).cast("double"),
        totals={"left": lambda f: g(f, zero()), "right": lambda f: g(zero(), f)},
    )


def disjunctive_sums(raw: DataFrame, pairs: DataFrame, g: Callable, aggregate: str = "sum", name: str = "value") -> DataFrame:
    """g over the union of each candidate pair's elements, evaluated directly: e1, e2 and the value.

    Every pair costs both entities' rows, so this is for few candidates and for checking.
    """
    if aggregate not in ("sum", "max", "min"):
        raise UnsupportedMeasure(aggregate)
    ids = pairs.select("e1", "e2").distinct()
    left = ids.join(raw.select(F.col("entity").alias("e1"), "element", F.col("mult").alias("f1")), "e1").select("e1", "e2", "element", "f1", F.lit(0).alias("f2"))
    right = ids.join(raw.select(F.col("entity").alias("e2"), "element", F.col("mult").alias("f2")), "e2").select("e1", "e2", "element", F.lit(0).alias("f1"), "f2")
    cells = left.unionByName(right).groupBy("e1", "e2", "element").agg(F.sum("f1").alias("f1"), F.sum("f2").alias("f2"))
    return cells.groupBy("e1", "e2").agg(getattr(F, aggregate)(g(F.col("f1"), F.col("f2"))).alias(name))
