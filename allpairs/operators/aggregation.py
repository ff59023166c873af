"""Aggregation: plain, distinct, filtered, grouping sets, pivots, statistics."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources.tables import read_table

OPERATORS: dict[str, tuple] = {}


def op(name: str, make, sql: str | None = None) -> None:
    OPERATORS[f"op_{name}"] = (make, sql)


def _t(s, d, name):
    return read_table(s, d, name)


op("agg_partial_final", lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last")), "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty, min(l_shipdate) AS first, max(l_shipdate) AS last FROM lineitem GROUP BY ALL")
op("agg_collect", lambda s, d: _t(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(DISTINCT n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
op("agg_count_distinct", lambda s, d: _t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey")
op("agg_approx_distinct", lambda s, d: _t(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts")))
op("agg_percentiles", lambda s, d: _t(s, d, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90")), "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS median, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY o_orderstatus")
op("agg_percentile_approx", lambda s, d: _t(s, d, "orders").agg(F.percentile_approx("o_totalprice", 0.5, 1000).alias("median")))
op("agg_filtered", lambda s, d: _t(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(0)).alias("purchases")), "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
_CUBE = "SELECT n_regionkey, c_mktsegment, count(*) AS n, grouping_id(n_regionkey, c_mktsegment)::BIGINT AS g FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY {} (n_regionkey, c_mktsegment)"


def _cn(s, d):
    return _t(s, d, "customer").join(_t(s, d, "nation"), F.expr("c_nationkey = n_nationkey"))


op("agg_cube", lambda s, d: _cn(s, d).cube("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().alias("g")), _CUBE.format("CUBE"))
op("agg_rollup", lambda s, d: _cn(s, d).rollup("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().alias("g")), _CUBE.format("ROLLUP"))
op("agg_grouping_sets", lambda s, d: _cn(s, d).groupingSets([["n_regionkey"], ["c_mktsegment"]], "n_regionkey", "c_mktsegment").agg(F.count("*").alias("n")), "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment))")
op("agg_pivot", lambda s, d: _t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0), "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
op("agg_unpivot", lambda s, d: _t(s, d, "labels").select("doc_id", "quality", "toxic").unpivot("doc_id", ["quality", "toxic"], "label", "value"), "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
op("agg_max_by", lambda s, d: _t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey")
op("agg_bool", lambda s, d: _t(s, d, "lineitem").groupBy("l_orderkey").agg(F.bool_and(F.col("l_quantity") > 5).alias("every"), F.bool_or(F.col("l_quantity") > 45).alias("some")), "SELECT l_orderkey, bool_and(l_quantity > 5) AS every, bool_or(l_quantity > 45) AS some FROM lineitem GROUP BY l_orderkey")
op("agg_statistics", lambda s, d: _t(s, d, "lineitem").agg(*(F.round(f, 4).alias(n) for n, f in (("sd", F.stddev("l_quantity")), ("va", F.var_pop("l_quantity")), ("co", F.corr("l_quantity", "l_extendedprice")), ("cv", F.covar_pop("l_quantity", "l_discount"))))), "SELECT round(stddev(l_quantity), 4) AS sd, round(var_pop(l_quantity), 4) AS va, round(corr(l_quantity, l_extendedprice), 4) AS co, round(covar_pop(l_quantity, l_discount), 4) AS cv FROM lineitem")
op("agg_shape", lambda s, d: _t(s, d, "lineitem").agg(F.round(F.skewness("l_quantity"), 4).alias("skew"), F.round(F.kurtosis("l_quantity"), 4).alias("kurt")), "WITH m AS (SELECT avg(l_quantity) AS a FROM lineitem), c AS (SELECT l_quantity - a AS x FROM lineitem, m) SELECT round(avg(x * x * x) / pow(avg(x * x), 1.5), 4) AS skew, round(avg(x * x * x * x) / pow(avg(x * x), 2) - 3, 4) AS kurt FROM c")
op("agg_log_bins", lambda s, d: _t(s, d, "documents").groupBy(F.floor(F.log2(F.col("n_chars") + 1)).alias("bin")).agg(F.count("*").alias("n")), "SELECT floor(log2(n_chars + 1))::BIGINT AS bin, count(*) AS n FROM documents GROUP BY 1")
op("agg_having", lambda s, d: _t(s, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).filter("n > 6"), "SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY l_orderkey HAVING count(*) > 6")
# of equally frequent segments the first; any name of a nation is the nation's
op("agg_mode_any", lambda s, d: _cn(s, d).groupBy("c_nationkey").agg(F.mode("c_mktsegment", deterministic=True).alias("usual"), F.any_value("n_name").alias("nation"), F.count("*").alias("n")), "WITH k AS (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL) SELECT c_nationkey, arg_min(c_mktsegment, (-k.n, c_mktsegment)) AS usual, any_value(n_name) AS nation, sum(k.n)::BIGINT AS n FROM k JOIN nation ON c_nationkey = n_nationkey GROUP BY c_nationkey")
