"""What is done to raw rows before the join: frequencies, stop words, small entities, profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def idf_weighted(raw: DataFrame, scale: int = 1_000_000) -> DataFrame:
    """Each element of an entity once, with ln(entities / entities that have it) as its multiplicity, in whole ``scale``-ths.

    Rows are those of :func:`allpairs.model.normalize_raw`; frequencies are partly summed before they move.
    """
    entities = raw.select("entity").distinct().count()
    weight = F.round(F.log(F.lit(entities) / F.col("freq")) * scale).cast("long")
    weights = element_frequency(raw).select("element", weight.alias("mult"))
    return raw.select("entity", "element").join(weights.filter("mult > 0"), "element").select("entity", "element", "mult")


def element_frequency(raw: DataFrame) -> DataFrame:
    """element and freq, the number of entities that have it."""
    return raw.groupBy("element").agg(F.count("*").alias("freq"))


def entity_sizes(raw: DataFrame) -> DataFrame:
    return raw.groupBy("entity").agg(F.count("*").alias("ucard"), F.sum("mult").alias("card"))


def drop_stop_words(raw: DataFrame, q: int, impl: str = "count") -> DataFrame:
    """Without elements of more than q entities.

    ``count`` counts each element and drops its rows by an anti join.  ``bounded`` never holds more
    than q + 1 rows of an element: ranks are cut off at q + 1 before the shuffle and after it.
    """
    if impl == "count":
        return raw.join(element_frequency(raw).filter(F.col("freq") > q).select("element"), "element", "left_anti").select(*raw.columns)
    rank = F.row_number().over(Window.partitionBy("element").orderBy("entity"))
    first = raw.withColumn("_rank", rank).filter(F.col("_rank") <= q + 1)
    return first.withColumn("_most", F.max("_rank").over(Window.partitionBy("element"))).filter(F.col("_most") <= q).select(*raw.columns)


def drop_small_entities(raw: DataFrame, least: int, by: str = "ucard") -> DataFrame:
    """Without entities of fewer elements (``ucard``) or a smaller sum (``card``)."""
    large = entity_sizes(raw).filter(F.col(by) >= least).select("entity")
    return raw.join(large, "entity", "left_semi").select(*raw.columns)


def size_histogram(raw: DataFrame) -> DataFrame:
    """Entities by size in powers of two: bin b holds sizes 2**b to 2**(b+1) - 1."""
    return _by_power(entity_sizes(raw).select(F.col("ucard").alias("n")))


def frequency_histogram(raw: DataFrame) -> DataFrame:
    """Elements by the number of entities that have them, in powers of two."""
    return _by_power(element_frequency(raw).select(F.col("freq").alias("n")))


def _by_power(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy((F.length(F.conv(F.col("n").cast("string"), 10, 2)) - 1).cast("long").alias("bin")).agg(F.count("*").alias("count"))


def shuffle_alphabet(raw: DataFrame, seed: int = 0) -> DataFrame:
    """The same entities over a relabelled alphabet; no measure may change."""
    return raw.withColumn("element", F.sha2(F.concat_ws(":", F.lit(str(seed)), F.col("element").cast("string")), 256))
