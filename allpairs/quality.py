"""How good the pairs are, judged by something the join didn't see."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def coverage(pairs: DataFrame) -> DataFrame:
    """Entities in any similar pair."""
    ids = pairs.select(F.col("e1").alias("entity")).union(pairs.select(F.col("e2").alias("entity"))).distinct()
    return ids.agg(F.count("*").alias("covered"))


def false_positive_rate(pairs: DataFrame, evidence: DataFrame, sample_of: int | None = None, seed: int = 0) -> DataFrame:
    """Pairs whose two entities differ in ``evidence`` (entity, value), among all or a sample of 1 in ``sample_of``, chosen by an md5 of the pair."""
    if sample_of is not None:
        digest = F.md5(F.concat_ws(":", F.col("e1").cast("string"), F.col("e2").cast("string"), F.lit(str(seed))))
        pairs = pairs.filter(F.substring(digest, 1, 4) < f"{65536 // sample_of:04x}")
    one = evidence.select(F.col("entity").alias("e1"), F.col("value").alias("v1"))
    two = evidence.select(F.col("entity").alias("e2"), F.col("value").alias("v2"))
    judged = pairs.join(one, "e1").join(two, "e2")
    wrong = F.coalesce(F.sum((F.col("v1") != F.col("v2")).cast("long")), F.lit(0))
    return judged.agg(F.count("*").alias("pairs"), wrong.alias("differ"), F.round(wrong / F.greatest(F.count("*"), F.lit(1)), 9).alias("rate"))


def quality_sweep(pairs: DataFrame, evidence: DataFrame, thresholds: list[float]) -> DataFrame:
    """For each threshold: pairs, covered entities, pairs that differ in the evidence; pairs come from the lowest."""
    steps = F.array(*(F.lit(float(t)) for t in thresholds))
    rows = pairs.withColumn("t", F.explode(F.filter(steps, lambda t: F.col("sim") >= t)))
    one = evidence.select(F.col("entity").alias("e1"), F.col("value").alias("v1"))
    two = evidence.select(F.col("entity").alias("e2"), F.col("value").alias("v2"))
    judged = rows.join(one, "e1").join(two, "e2")
    counts = judged.groupBy("t").agg(F.count("*").alias("pairs"), F.sum((F.col("v1") != F.col("v2")).cast("long")).alias("differ"))
    ends = rows.select("t", F.col("e1").alias("entity")).union(rows.select("t", F.col("e2").alias("entity"))).distinct().groupBy("t").agg(F.count("*").alias("covered"))
    return counts.join(ends, "t").select("t", "pairs", "covered", "differ")


def profile_ratio(raw: DataFrame) -> DataFrame:
    """Elements for each entity, as a whole."""
    return raw.agg(F.round(F.count_distinct("element") / F.count_distinct("entity"), 9).alias("ratio"))


def community_report(clusters: DataFrame, raw: DataFrame, largest: int = 7) -> DataFrame:
    """The largest groups: how many entities, rows and copies each has; ties go to smaller ids."""
    sums = clusters.join(raw, "entity").groupBy("community").agg(F.count_distinct("entity").alias("entities"), F.count("*").alias("rows"), F.sum("mult").cast("long").alias("copies"))
    order = Window.orderBy(F.desc("entities"), "community")
    top = sums.orderBy(F.desc("entities"), "community").limit(largest)
    return top.withColumn("place", F.row_number().over(order))
