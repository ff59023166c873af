"""Windowed multisets, running totals and per-window joins of an event stream."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .. import oracles
from ..join import similarity_join
from ..scratch import folder as scratch
from ..sources.tables import read_table

OPERATORS: dict[str, tuple] = {}


def op(name: str, sql: str | None = None):
    def put(f):
        OPERATORS[f"stream_{name}"] = (f, sql)
        return f

    return put


def stream_events(spark: SparkSession, where: str) -> DataFrame:
    """The events table as a stream of files, with the schema of the table."""
    schema = read_table(spark, where, "events").schema
    files = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(where)
    return files.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str, name: str, every: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Run until the input is used up; rows go to Parquet, never to the driver.

    ``append`` adds files; ``complete`` replaces them with each batch; ``update`` adds a batch's changed rows and gives, for each
    of ``keys``, those of the last batch.  ``every`` runs by processing time and stops once all input is read.
    """
    spark, path = stream.sparkSession, scratch(stream.sparkSession, f"{name}_{uuid.uuid4().hex[:8]}")
    out = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state")
    out = out.trigger(processingTime=every) if every else out.trigger(availableNow=True)
    if mode == "append":
        query = out.format("parquet").option("path", f"{path}/rows").start()
    elif mode == "complete":
        query = out.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{path}/rows")).start()
    else:
        query = out.foreachBatch(lambda batch, k: batch.withColumn("_batch", F.lit(k)).write.mode("overwrite").parquet(f"{path}/rows/_of={k}")).start()
    if every:
        query.processAllAvailable()
        query.stop()
    else:
        query.awaitTermination()
    if mode != "update":
        return spark.read.schema(stream.schema).parquet(f"{path}/rows")
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("_batch", LongType())])).option("recursiveFileLookup", "true").parquet(f"{path}/rows")
    values = [c for c in stream.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*values), "_batch").alias("_last")).select(*(c if c in keys else F.col(f"_last.{c}").alias(c) for c in stream.columns))


def late_rows(query) -> int:
    """Rows that the watermark has dropped so far, over all stateful operators, from the query's progress."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def _k() -> object:
    return F.get_json_object("props", "$.k")


@op("running_totals", "SELECT user_id, count(*) AS card FROM events GROUP BY user_id")
def _running(s, d):
    """Sums grow row by row, so the totals of entities are kept up to date."""
    return drained(stream_events(s, d).groupBy("user_id").agg(F.count("*").alias("card")), "complete", "totals")


@op("running_totals_update", "SELECT user_id, count(*) AS card FROM events GROUP BY user_id")
def _running_update(s, d):
    """The same, but a batch gives only the entities it changed, and batches come by processing time."""
    return drained(stream_events(s, d).groupBy("user_id").agg(F.count("*").alias("card")), "update", "totals_update", every="1 second", keys=("user_id",))


@op("distinct_elements", "SELECT user_id, count(DISTINCT json_extract_string(props, '$.k')) AS ucard FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY user_id")
def _distinct_elements(s, d):
    """Each user's number of different elements, with those seen so far as state: repeats in later batches add nothing."""
    import pandas as pd

    from ..workers import ship

    ship(s)

    def grown(key, frames, state):
        seen = set(state.get[0]) if state.exists else set()
        for pdf in frames:
            seen.update(pdf["k"])
        state.update((sorted(seen),))
        yield pd.DataFrame({"user_id": [key[0]], "ucard": [len(seen)]})

    rows = stream_events(s, d).select("user_id", _k().alias("k")).filter("k is not null")
    counts = rows.groupBy("user_id").applyInPandasWithState(grown, "user_id long, ucard long", "seen array<string>", "update", "NoTimeout")
    return drained(counts, "update", "ucard", keys=("user_id",))


@op("element_frequency", "SELECT json_extract_string(props, '$.k') AS k, count(*) AS freq FROM events GROUP BY 1 HAVING count(*) > 100")
def _alarm(s, d, q=100):
    """Elements that have become stop words."""
    return drained(stream_events(s, d).groupBy(_k().alias("k")).agg(F.count("*").alias("freq")).filter(F.col("freq") > q), "complete", "stop_words")


@op("tumbling_multisets", "SELECT user_id, date_trunc('day', ts)::TIMESTAMP AS day, event_type, count(*) AS mult FROM events GROUP BY ALL")
def _tumbling(s, d):
    rows = stream_events(s, d).groupBy(F.window("ts", "1 day"), "user_id", "event_type").agg(F.count("*").alias("mult"))
    return drained(rows.select("user_id", F.col("window.start").alias("day"), "event_type", "mult"), "complete", "tumbling")


@op("sliding_counts", "SELECT date_trunc('day', ts)::TIMESTAMP - (o * INTERVAL 1 DAY) AS start, count(*) AS n FROM events, (SELECT unnest(range(0, 7)) AS o) GROUP BY ALL")
def _sliding(s, d):
    rows = stream_events(s, d).groupBy(F.window("ts", "7 days", "1 day", "0 days")).agg(F.count("*").alias("n"))
    return drained(rows.select(F.col("window.start").alias("start"), "n"), "complete", "sliding")


@op("sessions", """WITH m AS (SELECT max(ts) AS m FROM events), e AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER u + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts)),
    g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e)
    SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM g, m GROUP BY user_id, g, m HAVING max(ts) + INTERVAL 30 MINUTE <= m - INTERVAL 1 HOUR""")
def _sessions(s, d):
    rows = stream_events(s, d).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    return drained(rows.select("user_id", F.col("session_window.start").alias("start"), "n"), "append", "sessions")


@op("closed_windows", "SELECT * FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS day, event_type, count(*) AS n FROM events GROUP BY ALL) WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
def _watermark(s, d):
    """Days that the watermark has closed; what comes later than it is dropped and counted in the progress."""
    rows = stream_events(s, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drained(rows.select(F.col("window.start").alias("day"), "event_type", "n"), "append", "closed")


@op("static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def _static(s, d):
    customers = read_table(s, d, "customer", ["c_custkey", "c_mktsegment"])
    return drained(stream_events(s, d).join(customers, F.expr("user_id = c_custkey")).select("event_id", "c_mktsegment"), "append", "static")


@op("interval_join", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts BETWEEN p.ts - INTERVAL 2 HOUR AND p.ts")
def _interval(s, d):
    p = stream_events(s, d).filter("event_type = 'purchase'").withWatermark("ts", "3 hours").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    c = stream_events(s, d).filter("event_type = 'click'").withWatermark("ts", "3 hours").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    return drained(p.join(c, F.expr("pu = cu and ct between pt - interval 2 hours and pt")).select("purchase", "click"), "append", "interval")


@op("duplicates_dropped", "SELECT DISTINCT event_id FROM events")
def _distinct(s, d):
    return drained(stream_events(s, d).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append", "distinct")


@op("pairs_of_batch", oracles.pairs("user_props", "ruzicka", 0.3))
def _pairs(s, d):
    """Sums of lesser multiplicities can't be kept up row by row, so each batch of complete multisets is joined as a whole."""
    key = f"pairs_{uuid.uuid4().hex[:8]}"
    path = scratch(s, key)

    def joined(batch: DataFrame, _: int) -> None:
        rows = batch.withColumnRenamed("user_id", "entity")
        similarity_join(rows, "ruzicka", 0.3, unique=True).select("e1", "e2", F.round("sim", 9).alias("sim")).write.mode("overwrite").parquet(f"{path}/pairs")

    counts = stream_events(s, d).withColumn("element", _k()).groupBy("user_id", "element").agg(F.count("*").alias("mult"))
    counts.writeStream.outputMode("complete").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(joined).start().awaitTermination()
    return s.read.parquet(f"{path}/pairs")
