"""The experiments' entities and elements, taken from the given tables, in Spark and in DuckDB's SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.text import ngrams, words
from .model import raw_from, to_long
from .sources.tables import read_table



def _tokens(df: DataFrame, entity: str, text: str) -> DataFrame:
    return df.select(F.col(entity).alias("entity"), words(F.col(text)).alias("tokens"))


def _counted(cells: DataFrame) -> DataFrame:
    return cells.groupBy("entity", "element").agg(F.count("*").alias("mult"))


def doc_words(spark: SparkSession, where: str) -> DataFrame:
    return _counted(_tokens(read_table(spark, where, "documents", ["doc_id", "text"]), "doc_id", "text").select("entity", F.explode("tokens").alias("element")))


def _grams(df: DataFrame) -> DataFrame:
    return _counted(df.select("entity", F.explode(ngrams(F.col("tokens"), 3)).alias("element")))


def doc_shingles(spark: SparkSession, where: str, dealt: bool = False) -> DataFrame:
    """``dealt`` moves the texts to their entity's task first; shingles, of which there are many more bytes, are then counted where they are made."""
    docs = read_table(spark, where, "documents", ["doc_id", "text"])
    return _grams(_tokens(docs.repartition("doc_id") if dealt else docs, "doc_id", "text"))


def benchmark_shingles(spark: SparkSession, where: str) -> DataFrame:
    return _grams(_tokens(read_table(spark, where, "benchmark", ["item_id", "text"]), "item_id", "text"))


def order_parts(spark: SparkSession, where: str) -> DataFrame:
    return raw_from(read_table(spark, where, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey")


def cust_parts(spark: SparkSession, where: str) -> DataFrame:
    items = read_table(spark, where, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    orders = read_table(spark, where, "orders", ["o_orderkey", "o_custkey"])
    met = items.join(orders, items["l_orderkey"] == orders["o_orderkey"])
    return raw_from(met, "o_custkey", "l_partkey", F.sum("l_quantity").cast("long"))


def supp_parts(spark: SparkSession, where: str) -> DataFrame:
    return raw_from(read_table(spark, where, "lineitem", ["l_suppkey", "l_partkey", "l_quantity"]), "l_suppkey", "l_partkey", F.sum("l_quantity").cast("long"))


def user_props(spark: SparkSession, where: str) -> DataFrame:
    return raw_from(read_table(spark, where, "events", ["user_id", "props"]), "user_id", F.get_json_object("props", "$.k"))


def user_types(spark: SparkSession, where: str) -> DataFrame:
    return raw_from(read_table(spark, where, "events", ["user_id", "event_type"]), "user_id", "event_type")


def embeddings(spark: SparkSession, where: str) -> DataFrame:
    return to_long(read_table(spark, where, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding")


def conv_words(spark: SparkSession, where: str) -> DataFrame:
    return _counted(_tokens(read_table(spark, where, "conversations", ["conv_id", "text"]), "conv_id", "text").select("entity", F.explode("tokens").alias("element")))


def page_words(spark: SparkSession, where: str) -> DataFrame:
    return _counted(_tokens(read_table(spark, where, "pages", ["page_id", "html"]), "page_id", "html").select("entity", F.explode("tokens").alias("element")))


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (doc_words, doc_shingles, benchmark_shingles, order_parts, cust_parts, supp_parts, user_props, user_types, embeddings, conv_words, page_words)
}


def _word_sql(table: str, entity: str, text: str) -> str:
    return f"SELECT entity, element, count(*)::BIGINT AS mult FROM (SELECT {entity} AS entity, unnest([lower(x) for x in regexp_extract_all({text}, '[A-Za-z0-9]+')]) AS element FROM {table}) GROUP BY ALL"


def _gram_sql(table: str, entity: str) -> str:
    grams = "[t[i] || ' ' || t[i + 1] || ' ' || t[i + 2] for i in range(1, len(t) - 1)]"
    tokens = f"SELECT {entity} AS entity, [lower(x) for x in regexp_extract_all(text, '[A-Za-z0-9]+')] AS t FROM {table}"
    return f"SELECT entity, element, count(*)::BIGINT AS mult FROM (SELECT entity, unnest({grams}) AS element FROM ({tokens})) GROUP BY ALL"


#: The same raw rows for DuckDB.
RAW_SQL = {
    "doc_words": _word_sql("documents", "doc_id", "text"),
    "doc_shingles": _gram_sql("documents", "doc_id"),
    "benchmark_shingles": _gram_sql("benchmark", "item_id"),
    "order_parts": "SELECT l_orderkey AS entity, l_partkey AS element, count(*)::BIGINT AS mult FROM lineitem GROUP BY ALL",
    "cust_parts": "SELECT o_custkey AS entity, l_partkey AS element, sum(l_quantity)::BIGINT AS mult FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL",
    "supp_parts": "SELECT l_suppkey AS entity, l_partkey AS element, sum(l_quantity)::BIGINT AS mult FROM lineitem GROUP BY ALL",
    "user_props": "SELECT user_id AS entity, json_extract_string(props, '$.k') AS element, count(*)::BIGINT AS mult FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY ALL",
    "user_types": "SELECT user_id AS entity, event_type AS element, count(*)::BIGINT AS mult FROM events GROUP BY ALL",
    "embeddings": "SELECT vec_id AS entity, (unnest(range(len(embedding))))::INTEGER AS element, unnest(embedding)::DOUBLE AS mult FROM embeddings",
    "conv_words": _word_sql("conversations", "conv_id", "text"),
    "page_words": _word_sql("pages", "page_id", "html"),
}
