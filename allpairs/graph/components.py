"""Connected components of an edge list by alternating star contractions.

Each round costs four shuffles of the edges that are left, needs a logarithmic number of rounds, and
never gathers a component: a round only sends edges towards smaller ids.  ``keep`` cuts the lineage
between rounds (a written table or ``checkpoint``).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..scratch import written


def _large_star(edges: DataFrame) -> DataFrame:
    """Every node sends its larger neighbours to the least node it sees."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Every node sends its smaller neighbours, and itself, to the least of them; edges have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    others = edges.join(least, "u").filter("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return others.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, keep: Callable[[DataFrame], DataFrame], a: str = "e1", b: str = "e2", most_rounds: int = 60) -> DataFrame:
    """node and component (its least node) for every node that has an edge."""
    oriented = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).filter("u <> v").distinct()
    current, before = keep(oriented), None
    for _ in range(most_rounds):
        current = keep(_small_star(_large_star(current)))
        state = current.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"no fixed point after {most_rounds} rounds")
    return current.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(current.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def communities(pairs: DataFrame, keep: Callable[[DataFrame], DataFrame] | None = None, min_size: int = 2) -> DataFrame:
    """entity, community (its least entity) and size, for the connected groups of similar pairs."""
    found = components(pairs, keep or (lambda df: written(df, "stars"))).select(F.col("node").alias("entity"), F.col("component").alias("community"))
    sizes = found.groupBy("community").agg(F.count("*").alias("size")).filter(F.col("size") >= min_size)
    return found.join(sizes, "community").select("entity", "community", "size")
