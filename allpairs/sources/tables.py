"""Tables in and out, with explicit columns and schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, where: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{where}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_slice(spark: SparkSession, path: str, predicate: str) -> DataFrame:
    """Only the partitions that the predicate on partition columns leaves."""
    return spark.read.parquet(path).where(predicate)


def round_trip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """Written and read back in another format, with the schema given rather than guessed."""
    if fmt == "text":
        df.select(F.to_json(F.struct(*df.columns)).alias("value")).write.mode("overwrite").text(path)
        lines = df.sparkSession.read.text(path)
        return lines.select(F.from_json("value", df.schema).alias("r")).select("r.*")
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.mode("overwrite").options(**options).format(fmt).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(fmt).load(path)


def register_views(spark: SparkSession, where: str) -> list[str]:
    for name in TABLES:
        read_table(spark, where, name).createOrReplaceTempView(name)
    return list(TABLES)


def write_joined(joined: DataFrame, table: str, buckets: int = 64, path: str | None = None) -> DataFrame:
    """Joined rows bucketed on the element, so that later index runs need no shuffle; at ``path`` if one is given."""
    where = {"path": path} if path else {}
    joined.write.mode("overwrite").options(**where).bucketBy(buckets, "element").sortBy("element").saveAsTable(table)
    return joined.sparkSession.table(table)


def write_pairs(pairs: DataFrame, path: str) -> DataFrame:
    """Pairs partitioned by tenths of similarity; a threshold reads only the bands it needs."""
    pairs.withColumn("band", F.least(F.floor(F.col("sim") * 10), F.lit(9)).cast("int")).write.mode("overwrite").partitionBy("band").parquet(path)
    return pairs.sparkSession.read.parquet(path)
