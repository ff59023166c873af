"""Measures as unilateral totals, conjunctive sums and a combiner.

A measure names the totals that need one entity only, the sums over shared elements, and how both
give its value.  Disjunctive measures, which need the union, are listed with
:mod:`allpairs.partials`, which rewrites those that can be.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Guards a ceiling against products like 0.1 * 30, which exceed the whole number in binary.
SLACK = 1e-9

#: Totals of one entity: what each of its rows adds, and how that is put together if not by a sum.
TOTALS: dict[str, Callable[[Column], Column]] = {
    "card": lambda f: f,
    "ucard": lambda f: F.when(f.isNotNull(), 1).otherwise(0).cast("long"),
    "sumsq": lambda f: f * f,
    "maxf": lambda f: f,
}
MERGES = {"maxf": "max"}


class UnsupportedMeasure(ValueError):
    """A measure that totals and shared elements alone can't give."""


@dataclass(frozen=True)
class Measure:
    name: str
    uni: tuple[str, ...]
    conj: dict[str, Callable[[Column, Column], Column]]
    combine: Callable[[dict, dict, dict], Column]  # conjunctive sums, totals of either entity
    #: Can a pair with these totals reach t at all?
    bound: Callable[[dict, dict, float], Column] | None = None
    #: For entities as sets of n elements: how many of the rarest must be looked at, and which sizes can pair.
    prefix_len: Callable[[int, float], float] | None = None
    len_range: Callable[[int, float], tuple[float, float]] | None = None
    #: The least ratio of the first total of the smaller entity to that of the larger at which a pair can reach t.
    least_ratio: Callable[[float], float] | None = None
    sets: bool = False
    distance: bool = False
    symmetric: bool = True
    signed: bool = False
    digits: int | None = None
    #: Totals of the measure's own, by what each row adds; ``merges`` says max or min for those that aren't sums.
    totals: dict[str, Callable[[Column], Column]] = field(default_factory=dict)
    merges: dict[str, str] = field(default_factory=dict)
    #: For whole blocks: the kind of the shared sum (least, product, magnitude, one) and the value from it and both totals, on numpy arrays.
    plain: tuple[str, Callable] | None = None

    def each(self, name: str) -> Callable[[Column], Column]:
        """What one row adds to a total."""
        return self.totals.get(name) or TOTALS[name]

    def merge(self, name: str) -> str:
        return self.merges.get(name) or MERGES.get(name, "sum")

    def total(self, name: str) -> Callable[[Column], Column]:
        """The total as an aggregate over an entity's rows."""
        return lambda f: getattr(F, self.merge(name))(self.each(name)(f))

    def passes(self, sim: Column, t: float, inclusive: bool = True) -> Column:
        if self.distance:
            return sim <= t if inclusive else sim < t
        return sim >= t if inclusive else sim > t


def _d(x: Column) -> Column:
    return x.cast("double")


def _least(f, g):
    return F.least(f, g)


def _one(f, g):
    return F.lit(1).cast("long")


def _product(f, g):
    return f * g


def _ratio_bound(name: str, of: Callable[[Column, Column], Column]):
    return lambda a, b, t: of(_d(F.least(a[name], b[name])), _d(F.greatest(a[name], b[name]))) >= t - SLACK


def _up(x):
    return math.ceil(x - SLACK) if isinstance(x, (int, float)) else F.ceil(x - SLACK)


def _over_union(s, a, b):
    return s / (a + b - s)


def _over_mean(s, a, b):
    return 2 * s / (a + b)


def _over_root(s, a, b):
    return s / (a * b) ** 0.5


def _over_product(s, a, b):
    return s / (a * b)


# prefix and size windows for entities as sets
_JACCARD = {"prefix_len": lambda n, t: n - _up(n * t) + 1, "len_range": lambda n, t: (n * t, n / t), "least_ratio": lambda t: t}
_DICE = {"prefix_len": lambda n, t: n - _up(n * (t / (2 - t))) + 1, "len_range": lambda n, t: (n * (t / (2 - t)), n * ((2 - t) / t)), "least_ratio": lambda t: t / (2 - t)}
_COSINE = {"prefix_len": lambda n, t: n - _up(n * (t * t)) + 1, "len_range": lambda n, t: (n * (t * t), n / (t * t)), "least_ratio": lambda t: t * t}


def jaccard() -> Measure:
    return Measure("jaccard", ("ucard",), {"o": _one}, lambda c, a, b: _d(c["o"]) / _d(a["ucard"] + b["ucard"] - c["o"]), _ratio_bound("ucard", lambda x, y: x / y), **_JACCARD, sets=True, plain=("one", _over_union))


def ruzicka() -> Measure:
    return Measure("ruzicka", ("card",), {"o": _least}, lambda c, a, b: _d(c["o"]) / _d(a["card"] + b["card"] - c["o"]), _ratio_bound("card", lambda x, y: x / y), **_JACCARD, plain=("least", _over_union))


def dice(kind: str = "set") -> Measure:
    total, shared = ("ucard", _one) if kind == "set" else ("card", _least)
    return Measure(f"dice_{kind}", (total,), {"o": shared}, lambda c, a, b: 2 * _d(c["o"]) / _d(a[total] + b[total]), _ratio_bound(total, lambda x, y: 2 * x / (x + y)), **_DICE, sets=kind == "set", plain=("one" if kind == "set" else "least", _over_mean))


def cosine(kind: str = "set", norm: str = "l2", signed: bool = False) -> Measure:
    """``signed`` multiplies signed values; else magnitudes.  ``norm='l1'`` divides by the two sums of magnitudes."""
    if kind in ("set", "multiset"):
        total, shared = ("ucard", _one) if kind == "set" else ("card", _least)
        return Measure(f"cosine_{kind}", (total,), {"o": shared}, lambda c, a, b: _d(c["o"]) / F.sqrt(_d(a[total]) * _d(b[total])), _ratio_bound(total, lambda x, y: F.sqrt(x / y)), **_COSINE, sets=kind == "set", plain=("one" if kind == "set" else "least", _over_root))
    kind = "product" if signed else "magnitude"
    product = _product if signed else lambda f, g: F.abs(f) * F.abs(g)
    if norm == "l1":
        return Measure("cosine_vector_l1", ("l1",), {"dot": product}, lambda c, a, b: _d(c["dot"]) / (_d(a["l1"]) * _d(b["l1"])), signed=True, digits=9, totals={"l1": lambda f: F.abs(f)}, plain=(kind, _over_product))
    return Measure("cosine_vector", ("sumsq",), {"dot": product}, lambda c, a, b: _d(c["dot"]) / F.sqrt(_d(a["sumsq"]) * _d(b["sumsq"])), signed=True, digits=9, plain=(kind, _over_root))


def overlap() -> Measure:
    return Measure("overlap", (), {"o": _least}, lambda c, a, b: _d(c["o"]))


def inner_product() -> Measure:
    return Measure("inner_product", (), {"dot": _product}, lambda c, a, b: _d(c["dot"]), digits=9)


def union_size() -> Measure:
    """Rewritten with totals: what both hold less what they share."""
    return Measure("union_size", ("card",), {"o": _least}, lambda c, a, b: _d(a["card"] + b["card"] - c["o"]))


def symmetric_difference() -> Measure:
    return Measure("symmetric_difference", ("card",), {"o": _least}, lambda c, a, b: _d(a["card"] + b["card"] - 2 * c["o"]), distance=True)


def overlap_coefficient() -> Measure:
    return Measure("overlap_coefficient", ("card",), {"o": _least}, lambda c, a, b: _d(c["o"]) / _d(F.least(a["card"], b["card"])))


def containment() -> Measure:
    """The larger of the two directions passes; :func:`allpairs.join.similarity_join` also gives both as columns of sums and totals."""
    return Measure("containment", ("card",), {"o": _least}, lambda c, a, b: F.greatest(_d(c["o"]) / _d(a["card"]), _d(c["o"]) / _d(b["card"])))


def tversky(alpha: float = 0.5, beta: float = 0.5) -> Measure:
    return Measure("tversky", ("card",), {"o": _least}, lambda c, a, b: _d(c["o"]) / (_d(c["o"]) + alpha * _d(a["card"] - c["o"]) + beta * _d(b["card"] - c["o"])), symmetric=alpha == beta, digits=9)


def tanimoto() -> Measure:
    return Measure("tanimoto", ("sumsq",), {"dot": _product}, lambda c, a, b: _d(c["dot"]) / _d(a["sumsq"] + b["sumsq"] - c["dot"]), digits=9)


def squared_l2() -> Measure:
    return Measure("squared_l2", ("sumsq",), {"dot": _product}, lambda c, a, b: _d(a["sumsq"] + b["sumsq"] - 2 * c["dot"]), distance=True, signed=True, digits=9)


def bray_curtis() -> Measure:
    return Measure("bray_curtis", ("card",), {"o": _least}, lambda c, a, b: 1 - 2 * _d(c["o"]) / _d(a["card"] + b["card"]), distance=True)


def weighted_jaccard(weight: str = "idf", scale: int = 1_000_000) -> Measure:
    """Sum of the weights of shared elements over that of all: Ruzicka of rows whose multiplicity is the weight.

    :func:`allpairs.preprocess.idf_weighted` gives such rows, in whole ``scale``-ths, so sums are exact in any order.
    """
    return Measure(f"weighted_jaccard_{weight}", ("card",), {"o": _least}, lambda c, a, b: _d(c["o"]) / _d(a["card"] + b["card"] - c["o"]), _ratio_bound("card", lambda x, y: x / y), **_JACCARD)


_MADE: dict[str, Callable[[], Measure]] = {
    "jaccard": jaccard,
    "ruzicka": ruzicka,
    "dice_set": lambda: dice("set"),
    "dice_multiset": lambda: dice("multiset"),
    "cosine_set": lambda: cosine("set"),
    "cosine_multiset": lambda: cosine("multiset"),
    "cosine_vector": lambda: cosine("vector"),
    "overlap": overlap,
    "inner_product": inner_product,
    "union_size": union_size,
    "symmetric_difference": symmetric_difference,
    "overlap_coefficient": overlap_coefficient,
    "containment": containment,
    "tversky": tversky,
    "tanimoto": tanimoto,
    "squared_l2": squared_l2,
    "bray_curtis": bray_curtis,
    "weighted_jaccard_idf": weighted_jaccard,
}


def register_measure(measure: Measure) -> Measure:
    """Make a measure of one's own known by name."""
    if not measure.conj and not measure.uni:
        raise UnsupportedMeasure(f"{measure.name} has neither totals nor shared sums")
    _MADE[measure.name] = lambda: measure
    return measure


def by_name(name: str) -> Measure:
    if name not in _MADE:
        raise UnsupportedMeasure(f"no measure is called {name}; known: {', '.join(sorted(_MADE))}")
    return _MADE[name]()
