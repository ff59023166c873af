"""Runners for sweeps of the threshold, of machines, of C, of methods and measures, with times of phases and steps.

All four algorithms of a sweep work on the same workload and measure, from raw rows that are written once.  Times are medians
of ``repeat`` runs that write their rows nowhere; what is computed before a run is not part of it.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable
from functools import partial
from pathlib import Path
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import costs, planner, quality
from ..baselines.prefix_replication import prefix_replication, records, replicate_prefixes, replication_cost, verify_whole
from ..counters import counted
from ..join import attach, similarity_join
from ..joining.sharding import routed_rows, sharded_totals
from ..measures import by_name
from ..preprocess import drop_small_entities, drop_stop_words
from ..scratch import folder, written
from ..similarity.index import pair_increments
from ..similarity.score import score_pairs
from ..sources.tables import read_table
from ..workloads import WORKLOADS

THRESHOLDS = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)
OURS = ("online_aggregation", "lookup", "sharding")
BASELINE = "prefix_replication"
LIMITS = tuple(1 << k for k in range(5, 16))


def raw_rows(spark: SparkSession, where: str, workload: str) -> DataFrame:
    return written(WORKLOADS[workload](spark, where), f"raw_{workload}")


def seconds(make: Callable[[], DataFrame], repeat: int = 5) -> float:
    return round(costs.timed(make, repeat), 3)


def algorithm(name: str, raw: DataFrame, measure: str, t: float, **options) -> DataFrame:
    if name == BASELINE:
        return prefix_replication(raw, by_name(measure), t)
    return similarity_join(raw, measure, t, joining=name, unique=True, **options)


def threshold_sweep(spark: SparkSession, where: str, workload: str = "order_parts", measure: str = "ruzicka", steps=THRESHOLDS, algorithms=(*OURS, BASELINE), repeat: int = 5) -> list[dict]:
    """Seconds and pairs of every algorithm at every threshold; pairs must be the same for all."""
    raw, out = raw_rows(spark, where, workload), []
    algorithm(algorithms[0], raw, measure, steps[0]).count()  # code is compiled before anything is timed
    for t in steps:
        for name in algorithms:
            make = partial(algorithm, name, raw, measure, t)
            out.append({"workload": workload, "measure": measure, "t": t, "algorithm": name, "seconds": seconds(make, repeat), "pairs": make().count()})
    return out


def machine_sweep(spark: SparkSession | None, where: str, workload: str = "order_parts", measure: str = "ruzicka", t: float = 0.5, cores=(1, 2, 4, 8), algorithms=(*OURS, BASELINE), repeat: int = 3) -> list[dict]:
    """The same at one threshold, each number of cores in a process of its own."""
    out = []
    for n in cores:
        code = f"from allpairs.experiments.__main__ import session; from allpairs.experiments.runners import threshold_sweep; import json; s = session({n}); print('ROWS', json.dumps(threshold_sweep(s, {where!r}, {workload!r}, {measure!r}, ({t},), {tuple(algorithms)!r}, {repeat})))"
        ran = subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[2], env=os.environ.copy(), capture_output=True, text=True, check=True)
        rows = json.loads(next(x for x in ran.stdout.splitlines() if x.startswith("ROWS ")).removeprefix("ROWS "))
        out += [{"cores": n} | r for r in rows]
    return out


def phases(spark: SparkSession, raw: DataFrame, measure: str, t: float, joining: str, repeat: int = 3, **options) -> dict:
    """Medians of both phases with joined rows written in between, and counters of one run."""
    m, path = by_name(measure), folder(spark, f"allpairs-phase-{time.time_ns()}")
    times = [costs.phase_times(raw, lambda r: attach(r, m, joining=joining, **options), lambda j: score_pairs(pair_increments(j), m, t), path) for _ in range(repeat)]
    with counted(spark) as c:
        score_pairs(pair_increments(spark.read.parquet(path)), m, t).write.format("noop").mode("overwrite").save()
    return {"joining_seconds": round(median(x["joining"] for x in times), 3), "similarity_seconds": round(median(x["similarity"] for x in times), 3), "shuffled_mb": round(c.shuffled_bytes / 1e6, 1), "spilled_mb": round(c.spilled_bytes / 1e6, 1), "largest_task_rows": max((s["most_rows"] for s in c.stages), default=0)}


def realistic_size(spark: SparkSession, where: str, workload: str = "doc_shingles", measure: str = "ruzicka", t: float = 0.5, repeat: int = 3, lookup_bytes: int = 1 << 16, most_cells: int = 100_000_000, budget_seconds: float = 600) -> list[dict]:
    """Outcomes under a budget: the lookup table doesn't fit, the baseline would ship too much; the others with their phases apart."""
    raw = raw_rows(spark, where, workload)
    out = []
    for name, make in (
        ("lookup", lambda: similarity_join(raw, measure, t, joining="lookup", max_table_bytes=lookup_bytes, unique=True)),
        (BASELINE, lambda: prefix_replication(raw, by_name(measure), t, most_cells=most_cells)),
        (f"{BASELINE}_hash_order", lambda: prefix_replication(raw, by_name(measure), t, order="hash", most_cells=most_cells)),
    ):
        got = costs.run(make, budget_seconds)
        out.append({"algorithm": name, "state": got.state, "seconds": got.seconds, "reason": got.reason})
    for name in ("online_aggregation", "sharding"):
        out.append({"algorithm": name, "state": "ok"} | phases(spark, raw, measure, t, name, repeat))
    small = drop_small_entities(raw, 50)
    out.append({"algorithm": "lookup_after_min_50", "state": "ok", "seconds": seconds(lambda: similarity_join(small, measure, t, joining="lookup", unique=True), repeat)})
    return out


def sharding_steps(spark: SparkSession, where: str, workload: str = "doc_shingles", measure: str = "ruzicka", limits=LIMITS, repeat: int = 3) -> list[dict]:
    """Seconds of sharding's two steps for each C: the totals of giants, then all rows with their totals."""
    raw, m, out = raw_rows(spark, where, workload), by_name(measure), []
    for c in limits:
        first, second = [], []
        for _ in range(repeat):
            began = time.perf_counter()
            giants = written(sharded_totals(raw, m, C=c), "giants")
            between = time.perf_counter()
            routed_rows(raw, giants, (m,)).write.format("noop").mode("overwrite").save()
            first.append(between - began)
            second.append(time.perf_counter() - between)
        out.append({"C": c, "giants": giants.count(), "step1_seconds": round(median(first), 3), "step2_seconds": round(median(second), 3), "sum_seconds": round(median(a + b for a, b in zip(first, second, strict=True)), 3)})
    return out


def kernel_share(spark: SparkSession, where: str, workload: str = "order_parts", measure: str = "jaccard", steps=(0.1, 0.5, 0.9), repeat: int = 3) -> list[dict]:
    """What part of the baseline's time goes into copying records and comparing those that meet, after they are ordered."""
    raw, m, out = raw_rows(spark, where, workload), by_name(measure), []
    for t in steps:
        ordered = seconds(lambda: records(raw), repeat)
        recs = written(records(raw), "records")
        kernel = seconds(lambda t=t, recs=recs: verify_whole(replicate_prefixes(recs, m, t), m, t), repeat)
        out.append({"t": t, "order_seconds": ordered, "kernel_seconds": kernel, "kernel_share": round(kernel / (kernel + ordered), 3), "cells": replication_cost(raw, m, t).first()["cells"]})
    return out


def proxy_study(spark: SparkSession, where: str, workload: str = "doc_shingles", steps=THRESHOLDS, least: int = 50, sample_of: int = 4) -> list[dict]:
    """Coverage and false positives for each threshold, for all entities and for those of at least ``least`` elements; judged on a sample by another column."""
    raw, out = raw_rows(spark, where, workload), []
    evidence = read_table(spark, where, "documents", ["doc_id", "lang"]).select(F.col("doc_id").alias("entity"), F.col("lang").alias("value"))
    for name, rows in (("all", raw), (f"min_{least}", drop_small_entities(raw, least))):
        pairs = written(similarity_join(rows, "ruzicka", min(steps), unique=True).select("e1", "e2", "sim"), "pairs")
        entities = rows.select("entity").distinct().count()
        for t in steps:
            found = pairs.filter(F.col("sim") >= t)
            judged = quality.false_positive_rate(found, evidence, sample_of).first()
            covered = quality.coverage(found).first()["covered"]
            out.append({"entities": name, "t": t, "pairs": found.count(), "covered": covered, "coverage": round(covered / max(1, entities), 4), "sampled": judged["pairs"], "false_positive_rate": judged["rate"]})
    return out


def ablations(spark: SparkSession, where: str, workload: str = "page_words", measure: str = "ruzicka", t: float = 0.5, q: int = 50, repeat: int = 3) -> list[dict]:
    """Seconds with and without partial sums, stop words, chunks and bounds."""
    raw, m = raw_rows(spark, where, workload), by_name(measure)
    from ..joining.online import attach_online

    ways: dict[str, Callable[[], DataFrame]] = {
        "totals with partial sums": lambda: attach_online(raw, m, impl="smj"),
        "totals without": lambda: attach_online(raw, m, impl="smj", combiner="none"),
        f"join without elements of over {q} entities": lambda: similarity_join(raw, m, t, q=q, unique=True),
        "join with bounds": lambda: similarity_join(raw, m, t, q=10 * q, prune=True, unique=True),
        "join without bounds": lambda: similarity_join(raw, m, t, q=10 * q, unique=True),
        "join in chunks": lambda: similarity_join(raw, m, t, q=10 * q, similarity="chunked", max_list_rows=100, unique=True),
    }
    out = []
    for name, make in ways.items():
        with counted(spark) as c:
            make().write.format("noop").mode("overwrite").save()
        out.append({"way": name, "seconds": seconds(make, repeat), "shuffled_mb": round(c.shuffled_bytes / 1e6, 1), "largest_task_rows": max((s["most_rows"] for s in c.stages), default=0)})
    left = drop_stop_words(raw, q)
    return [*out, {"way": "increments", "all": planner.statistics(raw).increments, f"q{q}": planner.statistics(left).increments}]


def measure_swap(spark: SparkSession, where: str, workload: str = "order_parts", measures=("ruzicka", "jaccard", "dice_multiset", "cosine_multiset", "cosine_vector", "overlap_coefficient"), t: float = 0.5, repeat: int = 5) -> list[dict]:
    """Seconds of the same join under other measures."""
    raw = raw_rows(spark, where, workload)
    similarity_join(raw, measures[0], t, unique=True).count()
    return [{"measure": m, "seconds": seconds(lambda m=m: similarity_join(raw, m, t, unique=True), repeat), "pairs": similarity_join(raw, m, t, unique=True).count()} for m in measures]


EXPERIMENTS: dict[str, Callable[..., list[dict]]] = {
    f.__name__: f for f in (threshold_sweep, machine_sweep, realistic_size, sharding_steps, kernel_share, proxy_study, ablations, measure_swap)
}
