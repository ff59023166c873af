"""Scans, projections, filters, joins, set operations, sorting."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..measures import ruzicka
from ..join import attach, similarity_join
from ..scratch import folder as scratch
from ..sources.tables import read_slice, read_table, register_views, round_trip, write_joined, write_pairs
from ..workloads import RAW_SQL, WORKLOADS
from .. import oracles

OPERATORS: dict[str, tuple] = {}


def op(name: str, sql: str | None = None):
    def put(f):
        OPERATORS[f"op_{name}"] = (f, sql)
        return f

    return put


def _t(s: SparkSession, d: str, name: str) -> DataFrame:
    return read_table(s, d, name)


op("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")(lambda s, d: read_table(s, d, "lineitem", ["l_orderkey", "l_quantity"]).filter("l_quantity > 45"))


@op("scan_partitions", "SELECT l_orderkey, l_partkey FROM lineitem WHERE year(l_shipdate) = 1995")
def _partitions(s, d):
    path = scratch(s, "by_year")
    read_table(s, d, "lineitem", ["l_orderkey", "l_partkey", "l_shipdate"]).withColumn("year", F.year("l_shipdate")).drop("l_shipdate").write.mode("overwrite").partitionBy("year").parquet(path)
    return read_slice(s, path, "year = 1995").select("l_orderkey", "l_partkey")


for _fmt in ("csv", "json", "orc", "text"):
    op(f"round_trip_{_fmt}", "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders")(lambda s, d, f=_fmt: round_trip(read_table(s, d, "orders", ["o_orderkey", "o_custkey", "o_orderstatus"]), f, scratch(s, f"orders_{f}")))


@op("raw_source", RAW_SQL["user_types"])
def _raw_source(s, d):
    from ..sources.raw_source import register
    from ..workers import ship

    ship(s)
    register(s)
    path = scratch(s, f"raw_lines_{uuid.uuid4().hex}").removeprefix("file://")
    rows = WORKLOADS["user_types"](s, d)
    rows.select(F.concat_ws("\t", "entity", "element", "mult").alias("value")).coalesce(2).write.mode("overwrite").text(path)
    return s.read.format("allpairs_raw").load(path)


@op("joined_bucketed", oracles.joined("user_props", "card"))
def _bucketed(s, d):
    return write_joined(attach(WORKLOADS["user_props"](s, d), ruzicka()), "allpairs_joined_user_props", 8, scratch(s, f"joined_{uuid.uuid4().hex}")).select("entity", "element", "mult", "uni_card")


@op("pairs_banded", oracles.pairs("doc_shingles", "ruzicka", 0.8))
def _banded(s, d):
    found = similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.5, unique=True).select("e1", "e2", F.round("sim", 9).alias("sim"))
    return write_pairs(found, scratch(s, "pairs")).filter("band >= 8 and sim >= 0.8").select("e1", "e2", "sim")


@op("sql_views", "SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY c_mktsegment")
def _views(s, d):
    register_views(s, d)
    return s.sql("SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY c_mktsegment")


@op("sql_join", oracles.pairs("doc_shingles", "ruzicka", 0.5))
def _sql_join(s, d):
    from ..functions.sql_measures import join_sql, register
    from ..measures import by_name
    from ..similarity.possible import possible

    register(s)
    possible(WORKLOADS["doc_shingles"](s, d, dealt=True), by_name("ruzicka"), 0.5).createOrReplaceTempView("allpairs_raw_rows")
    return join_sql(s, "allpairs_raw_rows", "sim_ruzicka", 0.5).select("e1", "e2", F.round("sim", 9).alias("sim"))


# money in whole ten-thousandths, so that no library's rounding of halves shows
op("computed_columns", "SELECT l_orderkey, CAST(round(l_extendedprice * 100) AS BIGINT) * (100 - CAST(round(l_discount * 100) AS BIGINT)) AS revenue_e4, CAST(l_quantity AS BIGINT) AS qty FROM lineitem")(
    lambda s, d: _t(s, d, "lineitem").select("l_orderkey", (F.round(F.col("l_extendedprice") * 100).cast("long") * (100 - F.round(F.col("l_discount") * 100).cast("long"))).alias("revenue_e4"), F.col("l_quantity").cast("long").alias("qty"))
)
op("predicates", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%-%' AND regexp_matches(o_orderpriority, '^[1-3]') AND o_custkey IS NOT NULL")(
    lambda s, d: _t(s, d, "orders").filter(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").like("%-%") & F.col("o_orderpriority").rlike("^[1-3]") & F.col("o_custkey").isNotNull()).select("o_orderkey")
)
op("null_safe_equality", "SELECT count(*) AS n FROM labels a JOIN labels b ON a.doc_id = b.doc_id AND a.toxic IS NOT DISTINCT FROM b.toxic")(
    lambda s, d: (lambda a, b: a.join(b, (a["doc_id"] == b["d"]) & a["toxic"].eqNullSafe(b["t"])).agg(F.count("*").alias("n")))(_t(s, d, "labels"), _t(s, d, "labels").select(F.col("doc_id").alias("d"), F.col("toxic").alias("t")))
)
op("case_routing", "SELECT s_suppkey, CASE WHEN s_acctbal < 0 THEN 'debt' WHEN s_acctbal < 5000 THEN 'low' ELSE 'high' END AS route FROM supplier")(
    lambda s, d: _t(s, d, "supplier").select("s_suppkey", F.when(F.col("s_acctbal") < 0, "debt").when(F.col("s_acctbal") < 5000, "low").otherwise("high").alias("route"))
)
# a sample that any engine draws alike: an eighth, by the first digits of a digest
op("hash_sample", "SELECT doc_id FROM documents WHERE substr(md5(doc_id || ':7'), 1, 4) < '2000'")(lambda s, d: _t(s, d, "documents").filter(F.substring(F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(":7"))), 1, 4) < "2000").select("doc_id"))
op("rename_drop_expand", "SELECT n_nationkey AS nation, n_name AS name FROM nation")(lambda s, d: _t(s, d, "nation").withColumnsRenamed({"n_nationkey": "nation", "n_name": "name"}).drop("n_regionkey").select(F.struct("*").alias("r")).select("r.*"))


def _orders_customers(s, d):
    return read_table(s, d, "orders", ["o_orderkey", "o_custkey"]), read_table(s, d, "customer", ["c_custkey", "c_nationkey"])


_INNER = "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey"
for _hint in ("broadcast", "shuffle_hash", "merge"):

    @op(f"join_{_hint}", _INNER)
    def _joined(s, d, hint=_hint):
        o, c = _orders_customers(s, d)
        return o.join(c.hint(hint), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_nationkey")


for _how, _sqlhow in (("left", "LEFT"), ("right", "RIGHT"), ("full_outer", "FULL")):

    @op(f"join_{_how}", f"SELECT c_custkey, o_orderkey FROM orders {_sqlhow} JOIN customer ON o_custkey = c_custkey")
    def _outer(s, d, how=_how):
        o, c = _orders_customers(s, d)
        return o.join(c, o["o_custkey"] == c["c_custkey"], how).select("c_custkey", "o_orderkey")


op("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: (lambda o, c: c.join(o, c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey"))(*_orders_customers(s, d)))
op("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda s, d: (lambda o, c: c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey"))(*_orders_customers(s, d)))
op("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")(lambda s, d: _t(s, d, "region").select("r_name").crossJoin(_t(s, d, "nation").select("n_name")))
op("join_theta_self", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(
    lambda s, d: (lambda n: n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b")))(_t(s, d, "nation"))
)


@op("join_range", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) <= 100")
def _range(s, d, width=100.0):
    """Buckets as wide as the range make it an equi-join with the neighbouring buckets."""
    rows = read_table(s, d, "supplier", ["s_suppkey", "s_acctbal"]).withColumn("bucket", F.floor(F.col("s_acctbal") / width))
    near = rows.withColumn("bucket", F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)))
    return rows.alias("a").join(near.alias("b"), F.expr(f"a.bucket = b.bucket and a.s_suppkey < b.s_suppkey and abs(a.s_acctbal - b.s_acctbal) <= {width}")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@op("join_interval", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts BETWEEN p.ts - INTERVAL 6 HOUR AND p.ts")
def _interval(s, d):
    e = read_table(s, d, "events", ["event_id", "user_id", "event_type", "ts"])
    on = F.expr("p.user_id = c.user_id and c.ts between p.ts - interval 6 hours and p.ts")
    return e.filter("event_type = 'purchase'").alias("p").join(e.filter("event_type = 'click'").alias("c"), on).select(F.col("p.event_id").alias("purchase"), F.col("c.event_id").alias("click"))


@op("join_as_of", "SELECT p.event_id AS purchase, (SELECT c.event_id FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND (c.ts, c.event_id) < (p.ts, p.event_id) ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS click FROM events p WHERE p.event_type = 'purchase'")
def _as_of(s, d):
    """One sorted pass over both sides: the last click before each purchase is carried forward."""
    from pyspark.sql import Window

    e = read_table(s, d, "events", ["event_id", "user_id", "event_type", "ts"]).filter("event_type in ('purchase', 'click')")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("click", last).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "click")


@op("join_salted", _INNER)
def _salted(s, d, salts=8):
    o, c = _orders_customers(s, d)
    o = o.withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(salts)))
    c = c.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return o.join(c, (o["o_custkey"] == c["c_custkey"]) & (o["salt"] == c["salt"])).select("o_orderkey", "c_nationkey")


@op("join_star", "SELECT r_name, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _star(s, d):
    t = {n: _t(s, d, n) for n in ("lineitem", "orders", "customer", "nation", "region")}
    met = t["lineitem"].join(t["orders"], F.expr("l_orderkey = o_orderkey")).join(t["customer"], F.expr("o_custkey = c_custkey")).join(t["nation"], F.expr("c_nationkey = n_nationkey")).join(t["region"], F.expr("n_regionkey = r_regionkey"))
    return met.groupBy("r_name").agg(F.round(F.sum("l_extendedprice"), 2).alias("price"))


_NAT, _SUP = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _keys(s, d):
    return read_table(s, d, "customer").select(F.col("c_nationkey").alias("k")), read_table(s, d, "supplier").select(F.col("s_nationkey").alias("k"))


for _name, _make, _sql in (
    ("union_all", lambda a, b: a.union(b), "UNION ALL"),
    ("intersect", lambda a, b: a.intersect(b), "INTERSECT"),
    ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"),
    ("subtract", lambda a, b: a.subtract(b), "EXCEPT"),
    ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
):
    op(f"set_{_name}", f"{_NAT} {_sql} {_SUP}")(lambda s, d, make=_make: make(*_keys(s, d)))
op("set_union_by_name", f"SELECT k, NULL::BIGINT AS more FROM ({_NAT}) UNION ALL SELECT k, 1 AS more FROM ({_SUP})")(lambda s, d: (lambda a, b: a.unionByName(b.withColumn("more", F.lit(1).cast("long")), allowMissingColumns=True))(*_keys(s, d)))
op("set_distinct", "SELECT DISTINCT o_custkey, o_orderstatus FROM orders")(lambda s, d: _t(s, d, "orders").select("o_custkey", "o_orderstatus").distinct())
op("set_drop_duplicates", "SELECT DISTINCT l_suppkey, l_partkey FROM lineitem")(lambda s, d: read_table(s, d, "lineitem", ["l_suppkey", "l_partkey", "l_quantity"]).dropDuplicates(["l_suppkey", "l_partkey"]).select("l_suppkey", "l_partkey"))
op("sort_top", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")(lambda s, d: read_table(s, d, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25))
op("sort_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 40")(lambda s, d: read_table(s, d, "orders", ["o_orderkey"]).orderBy("o_orderkey").offset(40).limit(10))


@op("sort_within_partitions", "SELECT o_custkey, min(o_orderkey) AS first FROM orders GROUP BY o_custkey")
def _sorted_parts(s, d):
    """The first row of each run of equal keys: right only if every partition is sorted and holds whole keys."""
    from ..workers import ship

    ship(s)

    def firsts(frames):
        last = None
        for pdf in frames:
            new = pdf["o_custkey"] != pdf["o_custkey"].shift(fill_value=-1 if last is None else last)
            if len(pdf):
                last = pdf["o_custkey"].iloc[-1]
            yield pdf[new].rename(columns={"o_orderkey": "first"})

    parts = read_table(s, d, "orders", ["o_custkey", "o_orderkey"]).repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")
    return parts.mapInPandas(firsts, "o_custkey long, first long")


op("sort_global", "SELECT s_suppkey, s_acctbal FROM supplier")(lambda s, d: read_table(s, d, "supplier", ["s_suppkey", "s_acctbal"]).orderBy("s_acctbal", "s_suppkey"))
