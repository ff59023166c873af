"""All pairs of similar entities: totals first, then the inverted index."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import planner
from .joining import LookupTableTooLarge, attach_lookup, attach_online, attach_sharding
from .measures import Measure, by_name
from .model import normalize_raw
from .partials import unilateral_totals
from .preprocess import drop_small_entities, drop_stop_words
from .scratch import once
from .similarity.blocks import pair_sums_blocked
from .similarity.chunked import LIST_ROWS, pair_increments_chunked
from .similarity.index import increments_between, pair_increments
from .similarity.possible import among, dealt_near
from .similarity.score import score_pairs, summed_pairs, value_of


def _measure(measure: Measure | str) -> Measure:
    return by_name(measure) if isinstance(measure, str) else measure


def attach(raw: DataFrame, *measures: Measure, joining: str = "online_aggregation", C: int = 1000, impl: str = "window", salt: int = 16, max_table_bytes: int = 1 << 30, on_overflow: str | None = None, route_giants: bool = True) -> DataFrame:  # noqa: N803
    """JOINED rows by the named way; ``auto`` chooses from counted sizes."""
    if joining == "auto":
        joining = planner.choose_joining(planner.statistics(raw), max_table_bytes)
    if joining == "online_aggregation":
        return attach_online(raw, *measures, impl=impl, salt=salt)
    if joining == "sharding":
        return attach_sharding(raw, *measures, C=C, route_giants=route_giants, max_table_bytes=max_table_bytes)
    if joining != "lookup":
        raise ValueError(f"no joining is called {joining}")
    try:
        return attach_lookup(raw, *measures, max_table_bytes=max_table_bytes)
    except LookupTableTooLarge:
        if on_overflow is None:
            raise
        return attach(raw, *measures, joining=on_overflow, C=C, impl=impl, max_table_bytes=max_table_bytes)


def similarity_join(
    raw: DataFrame,
    measure: Measure | str = "ruzicka",
    t: float = 0.5,
    *,
    measures: list[Measure | str] | None = None,
    joining: str = "online_aggregation",
    similarity: str = "index",
    C: int = 1000,  # noqa: N803
    impl: str = "window",
    q: int | None = None,
    stopword_scope: str = "before_totals",
    stopword_impl: str = "count",
    T: int | None = None,  # noqa: N803
    max_list_rows: int = LIST_ROWS,
    freq_limit: int | None = None,
    chunk_pairs: str = "unordered",
    min_elements: int | None = None,
    inclusive: bool = True,
    prune: bool | str = False,
    carry: str = "key",
    hint: str | None = "merge",
    salt: int = 16,
    max_table_bytes: int = 1 << 30,
    on_overflow: str | None = None,
    route_giants: bool = True,
    symmetric_output: bool = False,
    unique: bool = False,
    guards: bool | None = None,
    most_increments: int | None = None,
    near: DataFrame | None = None,
) -> DataFrame:
    """Every pair e1 < e2 that shares an element and passes t, exactly.

    With ``measures`` several are computed in one run: a pair is given if the first passes t, with one ``sim_<name>`` each.
    ``similarity='auto'`` counts the input first and takes chunks and bounds from that; it also refuses, as ``guards`` does
    for any other, inputs that an index doesn't help and, with ``most_increments``, those that would emit more.
    ``similarity='blocks'`` is for those: every pair of entities is summed in memory, block by block.
    ``near`` is what :func:`allpairs.similarity.possible.groups` gives for this measure and threshold, or a lower one: others' rows
    are left out, and lists are those of a group.
    """
    m = _measure(measures[0] if measures else measure)
    others = [_measure(x) for x in measures[1:]] if measures else []
    everyone = (m, *others)
    if not m.distance and t <= 0:
        raise ValueError("the threshold is above 0: pairs that share nothing are never candidates")
    cells = normalize_raw(raw, unique, any(x.signed for x in everyone))
    if near is not None:
        cells = among(cells, near)
    if min_elements is not None:
        cells = drop_small_entities(cells, min_elements)
    if q is not None and stopword_scope == "before_totals":
        cells = drop_stop_words(cells, q, stopword_impl)
    if similarity == "auto" or guards or most_increments is not None:
        cells = once(cells, "cells")
        stats = planner.statistics(cells)
        if guards or guards is None and similarity == "auto":
            planner.check_applicability(stats)
        if most_increments is not None:
            planner.check_increments(stats, most_increments)
        if similarity == "auto":
            plan = planner.choose_similarity(stats, not others and m.bound is not None, max_list_rows)
            similarity, prune = plan.similarity, plan.prune
        if joining == "auto":
            joining = planner.choose_joining(stats, max_table_bytes)
    joined = attach(cells, *everyone, joining=joining, C=C, impl=impl, salt=salt, max_table_bytes=max_table_bytes, on_overflow=on_overflow, route_giants=route_giants)
    if q is not None and stopword_scope == "index_only":
        joined = drop_stop_words(joined, q, "count")
    if near is not None:
        joined = dealt_near(joined, near)
    if similarity == "blocks":
        if others or q is not None and stopword_scope == "index_only":
            raise ValueError("whole blocks are for one measure, whose totals are of the rows that meet")
        out = pair_sums_blocked(once(joined, "joined_rows"), m, t, prune=bool(prune)).withColumn("sim", value_of(m))
        out = out.filter(m.passes(F.col("sim"), t, inclusive))
        return out.unionByName(_swapped(out)) if symmetric_output else out
    if similarity == "chunked":
        joined = once(joined, "joined_rows") if near is None else joined
        bounds = ((m,), t) if prune and not others else ((), None)
        increments = pair_increments_chunked(joined, T, max_list_rows, freq_limit, chunk_pairs, *bounds)
    elif similarity in ("index", "aqe"):
        increments = pair_increments(joined, everyone if not others else (m,), t, prune=prune, hint=None if similarity == "aqe" else hint)
    elif similarity == "list":
        if prune:
            raise ValueError("lists that are gathered in memory are not pruned; take index or chunked")
        increments = pair_increments(joined, impl="list")
    else:
        raise ValueError(f"no similarity phase is called {similarity}")
    totals = unilateral_totals(cells, *everyone) if carry == "rejoin" else None
    if not others:
        out = score_pairs(increments, m, t, inclusive, carry, totals)
    else:
        scored = summed_pairs(increments, everyone, carry, totals).withColumns({f"sim_{x.name}": value_of(x) for x in everyone})
        out = scored.filter(m.passes(F.col(f"sim_{m.name}"), t, inclusive)).withColumn("sim", F.col(f"sim_{m.name}"))
    return out.unionByName(_swapped(out)) if symmetric_output else out


def _swapped(pairs: DataFrame) -> DataFrame:
    other = {"e1": "e2", "e2": "e1"} | {c: c[:-1] + ("2" if c.endswith("1") else "1") for c in pairs.columns if c.startswith("uni_")}
    return pairs.select(*(F.col(other.get(c, c)).alias(c) for c in pairs.columns))


def similarity_join_rs(left: DataFrame, right: DataFrame, measure: Measure | str = "ruzicka", t: float = 0.5, inclusive: bool = True, unique: bool = False) -> DataFrame:
    """Similar pairs across two collections: e1 is of the left, e2 of the right."""
    m = _measure(measure)
    sides = [attach_online(normalize_raw(x, unique, m.signed), m) for x in (left, right)]
    return score_pairs(increments_between(*sides), m, t, inclusive)


def top_k(pairs: DataFrame, k: int, per_entity: bool = True) -> DataFrame:
    """The k most similar pairs of all, or of each entity (as ``entity`` and ``other``); ties go to smaller ids."""
    if not per_entity:
        return pairs.orderBy(F.desc("sim"), "e1", "e2").limit(k)
    both = pairs.select(F.col("e1").alias("entity"), F.col("e2").alias("other"), "sim").unionByName(pairs.select(F.col("e2").alias("entity"), F.col("e1").alias("other"), "sim"))
    order = Window.partitionBy("entity").orderBy(F.desc("sim"), "other")
    return both.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)
