"""Approximate join by banded minimum hashes, verified exactly: no wrong pairs, but some are missed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import Measure
from ..model import as_sets
from ..similarity.index import met_near, near_columns, pair_increments
from ..similarity.possible import among, dealt_near
from ..similarity.score import score_pairs
from ..joining import attach_online


def signatures(raw: DataFrame, bands: int, rows: int, seed: int = 0) -> DataFrame:
    hashes = [F.min(F.xxhash64(F.lit(seed * 100_003 + k), "element")).alias(f"h{k}") for k in range(bands * rows)]
    return raw.groupBy("entity").agg(*hashes)


def candidates(raw: DataFrame, bands: int = 16, rows: int = 4, seed: int = 0, near: DataFrame | None = None) -> DataFrame:
    """Pairs that agree in a band; with ``near`` only those of one group."""
    signed = signatures(raw, bands, rows, seed)
    keys = F.array(*(F.struct(F.lit(b).alias("band"), F.xxhash64(*(f"h{b * rows + r}" for r in range(rows))).alias("value")) for b in range(bands)))
    dealt = signed.select("entity", keys.alias("k"))
    dealt = dealt if near is None else dealt_near(dealt, near)
    dealt = dealt.select("entity", F.explode("k").alias("k"), *near_columns(dealt)).select("entity", "k.band", "k.value", *near_columns(dealt))
    left, right = dealt.alias("l"), dealt.alias("r")
    on = met_near(dealt) & (F.col("l.band") == F.col("r.band")) & (F.col("l.value") == F.col("r.value")) & (F.col("l.entity") < F.col("r.entity"))
    return left.join(right, on).select(F.col("l.entity").alias("e1"), F.col("r.entity").alias("e2")).distinct()


def minhash_lsh(raw: DataFrame, measure: Measure, t: float, bands: int = 16, rows: int = 4, seed: int = 0, near: DataFrame | None = None) -> DataFrame:
    """Candidates that pass t by the exact measure; ``near`` as in :func:`allpairs.join.similarity_join`, and then sums are made where lists are."""
    raw = raw if near is None else among(raw, near)
    pairs = candidates(raw, bands, rows, seed, near)
    cells = as_sets(raw) if measure.sets else raw
    joined = attach_online(cells, measure)
    if near is not None:
        return score_pairs(pair_increments(dealt_near(joined, near)), measure, t).join(pairs, ["e1", "e2"], "left_semi").select("e1", "e2", "sim")
    uni = [c for c in joined.columns if c.startswith("uni_")]
    left = pairs.join(joined.select(F.col("entity").alias("e1"), "element", F.col("mult").alias("f1"), *(F.col(c).alias(f"{c}_1") for c in uni)), "e1")
    met = left.join(joined.select(F.col("entity").alias("e2"), "element", F.col("mult").alias("f2"), *(F.col(c).alias(f"{c}_2") for c in uni)), ["e2", "element"])
    return score_pairs(met, measure, t).select("e1", "e2", "sim")


def recall_precision(found: DataFrame, exact: DataFrame) -> DataFrame:
    f, e = found.select("e1", "e2", F.lit(1).alias("f")), exact.select("e1", "e2", F.lit(1).alias("e"))
    both = f.join(e, ["e1", "e2"], "full_outer")
    hits = F.sum(F.when(F.col("f").isNotNull() & F.col("e").isNotNull(), 1).otherwise(0)).cast("double")
    return both.agg((hits / F.count("e")).alias("recall"), (hits / F.count("f")).alias("precision"))
