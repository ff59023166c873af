"""Windows: partition totals, ranks, offsets, frames, sessions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources.tables import read_table

OPERATORS: dict[str, tuple] = {}


def op(name: str, make, sql: str | None = None) -> None:
    OPERATORS[f"op_window_{name}"] = (make, sql)


def _e(s, d):
    return read_table(s, d, "events", ["event_id", "user_id", "event_type", "ts", "value"])


def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


def _all():
    return _user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)


def _seconds():
    """Whole seconds, to the nearest and halves to the even one, as the statements' casts of fractions give them."""
    return F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(1e6)).cast("long")


_SQL = "(PARTITION BY user_id ORDER BY ts, event_id)"
op("partition_sum", lambda s, d: _e(s, d).select("event_id", F.count("*").over(Window.partitionBy("user_id")).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id) AS n FROM events")
op("ranks", lambda s, d: read_table(s, d, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"]).select("l_orderkey", "l_partkey", F.rank().over(Window.partitionBy("l_orderkey").orderBy("l_quantity")).alias("r"), F.dense_rank().over(Window.partitionBy("l_orderkey").orderBy("l_quantity")).alias("dr")), "SELECT l_orderkey, l_partkey, (rank() OVER w)::INTEGER AS r, (dense_rank() OVER w)::INTEGER AS dr FROM lineitem WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_quantity)")
op("shares", lambda s, d: _e(s, d).select("event_id", F.row_number().over(_user()).alias("rn"), F.round(F.percent_rank().over(_user()), 9).alias("pr"), F.round(F.cume_dist().over(_user()), 9).alias("cd"), F.ntile(4).over(_user()).alias("q")), f"SELECT event_id, (row_number() OVER w)::INTEGER AS rn, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, (ntile(4) OVER w)::INTEGER AS q FROM events WINDOW w AS {_SQL}")
op("lag_lead", lambda s, d: _e(s, d).select("event_id", F.lag("event_id").over(_user()).alias("before"), F.lead("event_id", 2).over(_user()).alias("after")), f"SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after FROM events WINDOW w AS {_SQL}")
op("first_last", lambda s, d: _e(s, d).select("event_id", F.first("event_id").over(_all()).alias("first"), F.last("event_id").over(_all()).alias("last"), F.nth_value("event_id", 2).over(_all()).alias("second")), f"SELECT event_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS {_SQL[:-1]} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
op("rows_frame", lambda s, d: _e(s, d).select("event_id", F.count("*").over(_user().rowsBetween(-3, 0)).alias("n"), F.max("event_id").over(_user().rowsBetween(-3, -1)).alias("m")), f"SELECT event_id, count(*) OVER {_SQL[:-1]} ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS n, max(event_id) OVER {_SQL[:-1]} ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING) AS m FROM events")
op("range_frame", lambda s, d: _e(s, d).withColumn("sec", _seconds()).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
op("running_total", lambda s, d: _e(s, d).select("event_id", F.sum(F.lit(1)).over(_user()).alias("n")), f"SELECT event_id, (sum(1) OVER {_SQL})::BIGINT AS n FROM events")
op("top_k", lambda s, d: _e(s, d).withColumn("rn", F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))).filter("rn <= 3").select("user_id", "event_id", "rn"), "SELECT user_id, event_id, rn FROM (SELECT user_id, event_id, (row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id))::INTEGER AS rn FROM events) WHERE rn <= 3")


def _sessions(s, d):
    gap = _seconds() - F.lag(_seconds()).over(_user())
    marked = _e(s, d).withColumn("new", F.when(gap > 86400, 1).otherwise(0))
    numbered = marked.withColumn("session", F.sum("new").over(_user()))
    return numbered.groupBy("user_id", "session").agg(F.count("*").alias("n"), F.min("event_id").alias("first"))


op("sessions", _sessions, f"SELECT user_id, session, count(*) AS n, min(event_id) AS first FROM (SELECT *, (sum(fresh) OVER {_SQL})::BIGINT AS session FROM (SELECT *, CASE WHEN epoch(ts)::BIGINT - lag(epoch(ts)::BIGINT) OVER {_SQL} > 86400 THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY 1, 2")
