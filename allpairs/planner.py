"""Counts of the input, and what follows from them before anything large is run."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .preprocess import element_frequency, entity_sizes


class NotApplicable(ValueError):
    """Data for which an inverted index is no help: few elements, each in nearly every entity."""


@dataclass(frozen=True)
class Statistics:
    rows: int
    entities: int
    elements: int
    largest_entity: int
    highest_freq: int
    increments: int


def statistics(raw: DataFrame) -> Statistics:
    sizes = entity_sizes(raw).agg(F.count("*").alias("entities"), F.coalesce(F.max("ucard"), F.lit(0)).alias("largest"), F.coalesce(F.sum("ucard"), F.lit(0)).alias("rows")).first()
    f = F.col("freq")
    lists = element_frequency(raw).agg(F.count("*").alias("elements"), F.coalesce(F.max(f), F.lit(0)).alias("highest"), F.coalesce(F.sum((f * (f - 1) / 2).cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("increments")).first()
    return Statistics(sizes["rows"], sizes["entities"], lists["elements"], sizes["largest"], lists["highest"], int(lists["increments"]))


def choose_joining(stats: Statistics, max_table_bytes: int = 1 << 30, secondary_sort: bool = True, giant: int = 50_000_000) -> str:
    """The table of totals if it fits, else one pass over sorted groups; giants apart where groups can't be sorted or are huge."""
    if stats.entities * 64 <= max_table_bytes and stats.entities <= 1_000_000:
        return "lookup"
    if not secondary_sort or stats.largest_entity > giant:
        return "sharding"
    return "online_aggregation"


@dataclass(frozen=True)
class SimilarityPlan:
    """How lists are paired: ``index`` in one task each, ``chunked`` where the longest is too long for that."""

    similarity: str
    prune: bool
    max_list_rows: int


def choose_similarity(stats: Statistics, can_prune: bool, max_list_rows: int = 4096) -> SimilarityPlan:
    """Chunks if the longest list has more rows than one task should pair with each other; bounds wherever the measure has any."""
    return SimilarityPlan("chunked" if stats.highest_freq > max_list_rows else "index", can_prune, max_list_rows)


def check_applicability(stats: Statistics, most_share: float = 0.9, least_elements: int = 64) -> None:
    if stats.entities > 1 and stats.elements < least_elements and stats.highest_freq >= most_share * stats.entities:
        raise NotApplicable(f"{stats.elements} elements, one of them in {stats.highest_freq} of {stats.entities} entities: nearly every pair is a candidate")


def check_increments(stats: Statistics, most: int) -> None:
    """Refuse a join whose index would emit more pairs than can be afforded; drop stop words or prune instead."""
    if stats.increments > most:
        raise NotApplicable(f"the index would emit {stats.increments} pairs, more than {most}")
