"""The data model: one row for each (entity, element) cell that isn't zero.

RAW is ``entity, element, mult``.  A set has mult 1 everywhere, a multiset natural numbers, a
non-negative vector any positive numbers.  Entities are never gathered into one record, however
large they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RAW = ("entity", "element", "mult")
PAIRS = ("e1", "e2", "sim")


class InvalidRaw(ValueError):
    """A frame that isn't in RAW form."""


def validate_raw(raw: DataFrame) -> DataFrame:
    missing = [c for c in RAW if c not in raw.columns]
    if missing:
        raise InvalidRaw(f"columns are missing: {', '.join(missing)}")
    kind = dict(raw.dtypes)["mult"]
    if not kind.startswith(("int", "bigint", "smallint", "tinyint", "float", "double", "decimal")):
        raise InvalidRaw(f"mult is {kind}, not a number")
    return raw.select(*RAW)


def raw_from(df: DataFrame, entity: Column | str, element: Column | str, mult: Column | str | None = None) -> DataFrame:
    """RAW rows by mapping two expressions of any table; ``mult`` is an aggregate, by default how many rows there are."""
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    total = F.count(F.lit(1)) if mult is None else as_col(mult)
    keyed = df.withColumn("_entity", as_col(entity)).withColumn("_element", as_col(element)).filter("_entity is not null and _element is not null")
    return keyed.groupBy(F.col("_entity").alias("entity"), F.col("_element").alias("element")).agg(total.alias("mult"))


def positive(raw: DataFrame, signed: bool = False) -> DataFrame:
    """Cells that count: no nulls, and above zero (other than zero for signed vectors)."""
    some = F.col("mult") != 0 if signed else F.col("mult") > 0
    return raw.filter(F.col("entity").isNotNull() & F.col("element").isNotNull() & some)


def normalize_raw(raw: DataFrame, unique: bool = False, signed: bool = False) -> DataFrame:
    """Valid rows, each cell once; ``unique`` says that cells don't repeat, which saves a shuffle."""
    cells = positive(validate_raw(raw), signed)
    if unique:
        return cells
    return positive(cells.groupBy("entity", "element").agg(F.sum("mult").alias("mult")), signed)


def as_sets(raw: DataFrame) -> DataFrame:
    return raw.withColumn("mult", F.lit(1).cast("long"))


def expand_to_set(raw: DataFrame) -> DataFrame:
    """Each of a cell's copies as an element of its own: (element, 1), (element, 2), ..."""
    copies = raw.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("mult").cast("long"))))
    return copies.select("entity", F.struct(F.col("element").alias("of"), "copy").alias("element"), F.lit(1).cast("long").alias("mult"))


def to_long(df: DataFrame, entity: str, vector: str, signed: bool = True) -> DataFrame:
    """RAW rows of an array column (positions are elements) or a map column (keys are)."""
    if dict(df.dtypes)[vector].startswith("map"):
        cells = df.select(F.col(entity).alias("entity"), F.explode(vector).alias("element", "mult"))
    else:
        cells = df.select(F.col(entity).alias("entity"), F.posexplode(vector).alias("element", "mult"))
    if dict(cells.dtypes)["mult"] == "float":
        cells = cells.withColumn("mult", F.col("mult").cast("double"))
    return positive(cells, signed)


def to_wide(raw: DataFrame) -> DataFrame:
    """entity and ``cells``, a map in element order; for looking at small entities, not for joins."""
    return raw.groupBy("entity").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("element", "mult")))).alias("cells"))
