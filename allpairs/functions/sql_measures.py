"""Measures as temporary SQL functions, and joins written in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

FUNCTIONS = {
    "sim_ruzicka": ("o DOUBLE, n1 DOUBLE, n2 DOUBLE", "o / (n1 + n2 - o)"),
    "sim_dice": ("o DOUBLE, n1 DOUBLE, n2 DOUBLE", "2 * o / (n1 + n2)"),
    "sim_cosine": ("o DOUBLE, n1 DOUBLE, n2 DOUBLE", "o / sqrt(n1 * n2)"),
    "sim_overlap_coefficient": ("o DOUBLE, n1 DOUBLE, n2 DOUBLE", "o / least(n1, n2)"),
}


def register(spark: SparkSession) -> None:
    for name, (args, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


def join_sql(spark: SparkSession, raw_view: str, function: str, t: float) -> DataFrame:
    """The two-phase join as one SQL statement over a view of raw rows."""
    if function not in FUNCTIONS:
        raise ValueError(f"no function is called {function}")
    return spark.sql(
        f"""
        WITH joined AS (SELECT entity, element, mult, sum(mult) OVER (PARTITION BY entity) AS card FROM {{rows}}),
        pairs AS (
            SELECT /*+ MERGE(r) */ l.entity AS e1, r.entity AS e2, l.card AS n1, r.card AS n2, sum(least(l.mult, r.mult)) AS o
            FROM joined l JOIN joined r ON l.element = r.element AND l.entity < r.entity
            GROUP BY l.entity, r.entity, l.card, r.card)
        SELECT e1, e2, {function}(o, n1, n2) AS sim FROM pairs WHERE {function}(o, n1, n2) >= :t
        """,
        args={"t": t},
        rows=spark.table(raw_view),
    )
