"""DuckDB statements that give what the registered queries give."""

from __future__ import annotations

from .workloads import RAW_SQL

_TOTALS = {"card": "sum(mult)::BIGINT", "ucard": "count(*)::BIGINT", "sumsq": "sum(mult * mult)", "l1": "sum(abs(mult))"}

#: measure: totals it needs, shared sum, value of (s, a totals, b totals)
MEASURES = {
    "jaccard": ("ucard", "count(*)", "s::DOUBLE / (a + b - s)::DOUBLE"),
    "ruzicka": ("card", "sum(least(l.mult, r.mult))::BIGINT", "s::DOUBLE / (a + b - s)::DOUBLE"),
    "dice_set": ("ucard", "count(*)", "2 * s::DOUBLE / (a + b)::DOUBLE"),
    "dice_multiset": ("card", "sum(least(l.mult, r.mult))::BIGINT", "2 * s::DOUBLE / (a + b)::DOUBLE"),
    "cosine_set": ("ucard", "count(*)", "s::DOUBLE / sqrt(a::DOUBLE * b::DOUBLE)"),
    "cosine_multiset": ("card", "sum(least(l.mult, r.mult))::BIGINT", "s::DOUBLE / sqrt(a::DOUBLE * b::DOUBLE)"),
    "cosine_vector": ("sumsq", "sum(abs(l.mult) * abs(r.mult))", "s::DOUBLE / sqrt(a::DOUBLE * b::DOUBLE)"),
    "cosine_signed": ("sumsq", "sum(l.mult * r.mult)", "s::DOUBLE / sqrt(a::DOUBLE * b::DOUBLE)"),
    "cosine_vector_l1": ("l1", "sum(abs(l.mult) * abs(r.mult))", "s::DOUBLE / (a::DOUBLE * b::DOUBLE)"),
    "overlap": ("card", "sum(least(l.mult, r.mult))::BIGINT", "s::DOUBLE"),
    "inner_product": ("card", "sum(l.mult * r.mult)", "s::DOUBLE"),
    "union_size": ("card", "sum(least(l.mult, r.mult))::BIGINT", "(a + b - s)::DOUBLE"),
    "symmetric_difference": ("card", "sum(least(l.mult, r.mult))::BIGINT", "(a + b - 2 * s)::DOUBLE"),
    "overlap_coefficient": ("card", "sum(least(l.mult, r.mult))::BIGINT", "s::DOUBLE / least(a, b)::DOUBLE"),
    "containment": ("card", "sum(least(l.mult, r.mult))::BIGINT", "greatest(s::DOUBLE / a::DOUBLE, s::DOUBLE / b::DOUBLE)"),
    "tversky": ("card", "sum(least(l.mult, r.mult))::BIGINT", "s::DOUBLE / (s::DOUBLE + CAST(0.5 AS DOUBLE) * (a - s)::DOUBLE + CAST(0.5 AS DOUBLE) * (b - s)::DOUBLE)"),
    "tanimoto": ("sumsq", "sum(l.mult * r.mult)", "s::DOUBLE / (a + b - s)::DOUBLE"),
    "squared_l2": ("sumsq", "sum(l.mult * r.mult)", "(a + b - 2 * s)::DOUBLE"),
    "kulczynski": ("ucard", "count(*)", "(s::DOUBLE / a::DOUBLE + s::DOUBLE / b::DOUBLE) / 2"),
    "bray_curtis": ("card", "sum(least(l.mult, r.mult))::BIGINT", "1 - 2 * s::DOUBLE / (a + b)::DOUBLE"),
}


def raw(workload: str, q: int | None = None, min_elements: int | None = None) -> str:
    sql = RAW_SQL[workload]
    if min_elements is not None:
        sql = f"SELECT * FROM ({sql}) WHERE entity IN (SELECT entity FROM ({sql}) GROUP BY entity HAVING count(*) >= {min_elements})"
    if q is not None:
        sql = f"SELECT * FROM ({sql}) WHERE element NOT IN (SELECT element FROM ({sql}) GROUP BY element HAVING count(*) > {q})"
    return sql


def joined(workload: str, *totals: str) -> str:
    return f"SELECT entity, element, mult, {', '.join(f'{_TOTALS[t]} OVER (PARTITION BY entity) AS uni_{t}' for t in totals)} FROM ({raw(workload)})".replace("count(*)::BIGINT OVER (PARTITION BY entity)", "(count(*) OVER (PARTITION BY entity))::BIGINT").replace("sum(mult)::BIGINT OVER (PARTITION BY entity)", "(sum(mult) OVER (PARTITION BY entity))::BIGINT")


def totals(workload: str, *names: str) -> str:
    return f"SELECT entity, {', '.join(f'{_TOTALS[t]} AS uni_{t}' for t in names)} FROM ({raw(workload)}) GROUP BY entity"


def scored(workload: str, measure: str, q: int | None = None, min_elements: int | None = None, index_q: int | None = None, raw_sql: str | None = None) -> str:
    """Every candidate with its value; ``index_q`` drops elements after the totals."""
    total, shared, value = MEASURES[measure]
    rows = raw_sql or raw(workload, q, min_elements)
    index = "rows_" if index_q is None else f"(SELECT * FROM rows_ WHERE element NOT IN (SELECT element FROM rows_ GROUP BY element HAVING count(*) > {index_q}))"
    return f"""WITH rows_ AS MATERIALIZED ({rows}), totals_ AS (SELECT entity, {_TOTALS[total]} AS n FROM rows_ GROUP BY entity),
shared_ AS (SELECT l.entity AS e1, r.entity AS e2, {shared} AS s FROM {index} l JOIN {index} r ON l.element = r.element AND l.entity < r.entity GROUP BY l.entity, r.entity),
sims_ AS (SELECT e1, e2, round({value}, 9) AS sim FROM (SELECT e1, e2, s, x.n AS a, y.n AS b FROM shared_ JOIN totals_ x ON x.entity = e1 JOIN totals_ y ON y.entity = e2))
"""


def pairs(workload: str, measure: str, t: float, inclusive: bool = True, distance: bool = False, **more) -> str:
    op = {(True, False): ">=", (False, False): ">", (True, True): "<=", (False, True): "<"}[inclusive, distance]
    return scored(workload, measure, **more) + f"SELECT e1, e2, sim FROM sims_ WHERE sim {op} CAST({t} AS DOUBLE)"


def sweep(workload: str, measure: str, thresholds: list[float]) -> str:
    counts = " UNION ALL ".join(f"SELECT CAST({t} AS DOUBLE) AS t, count(*)::BIGINT AS pairs FROM sims_ WHERE sim >= CAST({t} AS DOUBLE)" for t in thresholds)
    return scored(workload, measure) + counts


def components(pairs_sql: str) -> str:
    """Least reachable entity of each, by a recursive walk; for small graphs."""
    return f"""WITH RECURSIVE found AS MATERIALIZED ({pairs_sql}), edge AS (SELECT e1 AS a, e2 AS b FROM found UNION SELECT e2, e1 FROM found),
reach AS (SELECT a AS entity, a AS seen FROM edge UNION SELECT reach.entity, edge.b FROM reach JOIN edge ON edge.a = reach.seen),
label AS (SELECT entity, min(seen) AS community FROM reach GROUP BY entity)
SELECT entity, community, (count(*) OVER (PARTITION BY community))::BIGINT AS size FROM label"""
