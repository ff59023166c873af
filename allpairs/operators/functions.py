"""Scalar functions, arrays, maps, structs, JSON, hashes; user functions of each kind."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .. import oracles
from ..functions.text import character_shingles, lines, url_host, url_path, without_tags
from ..join import attach
from ..measures import Measure, ruzicka
from ..similarity.index import pair_increments
from ..similarity.score import score_pairs
from ..sources.tables import read_table
from ..workers import ship
from ..workloads import WORKLOADS

OPERATORS: dict[str, tuple] = {}


def op(name: str, make, sql: str | None = None) -> None:
    OPERATORS[f"op_{name}"] = (make, sql)


def _t(s, d, name):
    return read_table(s, d, name)


op("fn_strings", lambda s, d: _t(s, d, "part").select("p_partkey", F.lower("p_name").alias("lo"), F.upper("p_brand").alias("up"), F.substring("p_name", 2, 5).alias("sub"), F.concat_ws("-", "p_brand", "p_type").alias("cat"), F.length("p_name").alias("len"), F.reverse("p_brand").alias("rev"), F.lpad(F.col("p_size").cast("string"), 5, "0").alias("pad"), F.instr("p_name", "a").alias("pos"), F.translate("p_brand", "Bb", "Xx").alias("tr"), F.regexp_replace("p_type", "[aeiou]", "").alias("rx")), "SELECT p_partkey, lower(p_name) AS lo, upper(p_brand) AS up, substr(p_name, 2, 5) AS sub, concat_ws('-', p_brand, p_type) AS cat, length(p_name)::INTEGER AS len, reverse(p_brand) AS rev, lpad(p_size::VARCHAR, 5, '0') AS pad, instr(p_name, 'a')::INTEGER AS pos, translate(p_brand, 'Bb', 'Xx') AS tr, regexp_replace(p_type, '[aeiou]', '', 'g') AS rx FROM part")
op("fn_levenshtein", lambda s, d: _t(s, d, "nation").select("n_nationkey", F.levenshtein("n_name", F.lit("NATION_1")).alias("d")), "SELECT n_nationkey, levenshtein(n_name, 'NATION_1')::INTEGER AS d FROM nation")
op("fn_soundex", lambda s, d: _t(s, d, "nation").select("n_nationkey", F.soundex("n_name").alias("code"), F.format_string("%s:%05d", "n_name", "n_nationkey").alias("f")))
op("fn_lines", lambda s, d: _t(s, d, "documents").select("doc_id", F.explode(lines(F.col("text"))).alias("line")).groupBy("doc_id").agg(F.count("*").alias("n")), "SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents) WHERE trim(l) <> '' GROUP BY doc_id")
op("fn_character_shingles", lambda s, d: _t(s, d, "nation").select("n_nationkey", F.explode(character_shingles(F.col("n_name"), 3)).alias("g")), "SELECT n_nationkey, unnest([substr(n_name, i, 3) for i in range(1, length(n_name) - 1)]) AS g FROM nation")
op("fn_url", lambda s, d: _t(s, d, "pages").select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
op("fn_without_tags", lambda s, d: _t(s, d, "pages").select("page_id", F.md5(without_tags(F.col("html"))).alias("h")), "SELECT page_id, md5(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS h FROM pages")
op("fn_dates", lambda s, d: _t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("dow"), F.date_trunc("month", "o_orderdate").alias("mo"), F.datediff(F.lit("2000-01-01"), "o_orderdate").alias("days"), F.unix_timestamp("o_orderdate").alias("sec"), F.date_format(F.add_months("o_orderdate", 1), "yyyy-MM-dd").alias("next")), "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, (dayofweek(o_orderdate) + 1)::INTEGER AS dow, date_trunc('month', o_orderdate)::TIMESTAMP AS mo, date_diff('day', o_orderdate, TIMESTAMP '2000-01-01')::INTEGER AS days, epoch(o_orderdate)::BIGINT AS sec, strftime(o_orderdate + INTERVAL 1 MONTH, '%Y-%m-%d') AS next FROM orders")
op("fn_math", lambda s, d: _t(s, d, "lineitem").select("l_orderkey", "l_partkey", F.least("l_quantity", F.lit(10.0)).alias("lo"), F.greatest("l_quantity", F.lit(10.0)).alias("hi"), F.round(F.sqrt("l_quantity"), 6).alias("sq"), F.abs(F.col("l_quantity") - 25).alias("ab"), F.ceil("l_extendedprice").alias("ce"), F.floor("l_extendedprice").alias("fl"), F.pmod(F.col("l_orderkey"), F.lit(7)).alias("pm"), F.round(F.log2("l_quantity"), 6).alias("l2"), F.signum(F.col("l_quantity") - 25).alias("sg")), "SELECT l_orderkey, l_partkey, least(l_quantity, 10.0::DOUBLE) AS lo, greatest(l_quantity, 10.0::DOUBLE) AS hi, round(sqrt(l_quantity), 6) AS sq, abs(l_quantity - 25) AS ab, ceil(l_extendedprice)::BIGINT AS ce, floor(l_extendedprice)::BIGINT AS fl, l_orderkey % 7 AS pm, round(log2(l_quantity), 6) AS l2, sign(l_quantity - 25)::DOUBLE AS sg FROM lineitem")
op("fn_arrays", lambda s, d: _t(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")), 5).alias("sum"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.round(F.element_at(F.sort_array("embedding"), -1).cast("double"), 6).alias("top"), F.size(F.slice("embedding", 3, 4)).alias("sl")), "SELECT vec_id, len(embedding)::INTEGER AS n, round(list_sum([x::DOUBLE for x in embedding]), 5) AS sum, len([x for x in embedding if x > 0])::INTEGER AS pos, round(list_max(embedding)::DOUBLE, 6) AS top, 4 AS sl FROM embeddings")


def _baskets(s, d):
    return read_table(s, d, "lineitem", ["l_orderkey", "l_partkey"]).groupBy("l_orderkey").agg(F.sort_array(F.collect_set("l_partkey")).alias("parts"))


op("fn_array_sets", lambda s, d: _baskets(s, d).select("l_orderkey", F.size(F.array_intersect("parts", F.sequence(F.lit(1).cast("long"), F.lit(500).cast("long")))).alias("low"), F.size(F.array_union("parts", F.array(F.lit(1).cast("long")))).alias("uni"), F.size(F.array_except("parts", F.array(F.lit(1).cast("long")))).alias("exc"), F.arrays_overlap("parts", F.array(F.lit(1).cast("long"), F.lit(2).cast("long"))).alias("ov")), "SELECT l_orderkey, count(DISTINCT CASE WHEN l_partkey BETWEEN 1 AND 500 THEN l_partkey END)::INTEGER AS low, (count(DISTINCT l_partkey) + CASE WHEN bool_or(l_partkey = 1) THEN 0 ELSE 1 END)::INTEGER AS uni, count(DISTINCT CASE WHEN l_partkey <> 1 THEN l_partkey END)::INTEGER AS exc, bool_or(l_partkey IN (1, 2)) AS ov FROM lineitem GROUP BY l_orderkey")
op("fn_maps", lambda s, d: WORKLOADS["user_types"](s, d).groupBy("entity").agg(F.map_from_entries(F.collect_list(F.struct("element", "mult"))).alias("m")).select("entity", F.size(F.map_keys("m")).alias("n"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.element_at("m", "click").alias("clicks"), F.size(F.map_filter("m", lambda k, v: v > 10)).alias("many")), "SELECT user_id AS entity, count(DISTINCT event_type)::INTEGER AS n, count(*) AS total, nullif(count(*) FILTER (WHERE event_type = 'click'), 0) AS clicks, (SELECT count(*) FROM (SELECT event_type FROM events b WHERE b.user_id = a.user_id GROUP BY event_type HAVING count(*) > 10))::INTEGER AS many FROM events a GROUP BY user_id")
op("fn_structs", lambda s, d: _t(s, d, "nation").select(F.struct("n_nationkey", F.col("n_name").alias("name")).alias("r")).select(F.col("r.name").alias("name"), F.col("r").getField("n_nationkey").alias("key")), "SELECT n_name AS name, n_nationkey AS key FROM nation")
op("fn_json", lambda s, d: _t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"), F.from_json("props", "k long")["k"].alias("n"), F.to_json(F.struct("event_id")).alias("j")), "SELECT event_id, json_extract_string(props, '$.k') AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS n, '{\"event_id\":' || event_id || '}' AS j FROM events")
op("fn_variant", lambda s, d: _t(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
op("fn_hashes", lambda s, d: _t(s, d, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s")), "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
op("fn_hashes_native", lambda s, d: _t(s, d, "documents").select("doc_id", F.xxhash64("text").alias("x"), F.hash("text").alias("h"), F.crc32("text").alias("c")))
op("fn_nulls", lambda s, d: _t(s, d, "documents").join(_t(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("t"), F.nullif(F.col("quality"), F.lit(0)).alias("q"), F.round(F.try_divide(F.col("quality"), F.col("toxic")), 6).alias("d")), "SELECT d.doc_id, coalesce(toxic, -1) AS t, nullif(quality, 0) AS q, CASE WHEN toxic = 0 THEN NULL ELSE round(quality::DOUBLE / toxic, 6) END AS d FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id")
op("fn_decimal", lambda s, d: _t(s, d, "lineitem").groupBy("l_suppkey").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("string").alias("money")), "SELECT l_suppkey, sum(l_extendedprice::DECIMAL(18,2))::VARCHAR AS money FROM lineitem GROUP BY l_suppkey")

_PAIRS = oracles.pairs("user_props", "ruzicka", 0.3)


def _own_measure(s, d):
    """A shared sum and a combiner of one's own, as columns."""
    own = Measure("own", ("card",), {"o": lambda a, b: F.least(a, b)}, lambda c, a, b: c["o"].cast("double") / (a["card"] + b["card"] - c["o"]).cast("double"))
    return score_pairs(pair_increments(attach(WORKLOADS["user_props"](s, d), own)), own, 0.3).select("e1", "e2", F.round("sim", 9).alias("sim"))


def _arrow_measure(s, d):
    """The same with the per-element function in Python, batch by batch."""
    ship(s)
    @F.pandas_udf(LongType())
    def lesser(a: pd.Series, b: pd.Series) -> pd.Series:
        return a.where(a < b, b)

    own = Measure("own", ("card",), {"o": lesser}, lambda c, a, b: c["o"].cast("double") / (a["card"] + b["card"] - c["o"]).cast("double"))
    return score_pairs(pair_increments(attach(WORKLOADS["user_props"](s, d), own)), own, 0.3).select("e1", "e2", F.round("sim", 9).alias("sim"))


def _grouped_aggregate(s, d):
    ship(s)
    @F.pandas_udf(LongType())
    def total(x: pd.Series) -> int:
        return int(x.sum())

    return WORKLOADS["user_props"](s, d).groupBy("entity").agg(total("mult").alias("uni_card"))


def _table_function(s, d):
    """Pairs inside a list by a table function that is fed the list's sorted entities."""
    ship(s)

    @F.udtf(returnType="e1 bigint, e2 bigint")
    class PairsOf:
        def eval(self, ids):
            for k, a in enumerate(ids):
                for b in ids[k + 1 :]:
                    yield a, b

    s.udtf.register("pairs_of", PairsOf)
    lists = WORKLOADS["supp_parts"](s, d).groupBy("element").agg(F.sort_array(F.collect_list("entity")).alias("ids"))
    lists.createOrReplaceTempView("allpairs_lists")
    return s.sql("SELECT e1, e2, count(*) AS shared FROM allpairs_lists, LATERAL pairs_of(ids) GROUP BY e1, e2")


op("udf_measure_columns", _own_measure, _PAIRS)
op("udf_measure_arrow", _arrow_measure, _PAIRS)
op("udf_aggregate", _grouped_aggregate, oracles.totals("user_props", "card"))
op("udtf_pairs", _table_function, "WITH r AS (SELECT DISTINCT l_suppkey AS e, l_partkey AS p FROM lineitem) SELECT a.e AS e1, b.e AS e2, count(*) AS shared FROM r a JOIN r b ON a.p = b.p AND a.e < b.e GROUP BY ALL")
