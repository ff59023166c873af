"""What runs cost, counted before they run or measured while they do."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from dataclasses import dataclass
from statistics import median

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .baselines.prefix_replication import OverBudget, replication_cost  # noqa: F401
from .joining import LookupTableTooLarge
from .preprocess import element_frequency, entity_sizes
from .similarity.index import pair_increments


def index_cost(raw: DataFrame, q: int | None = None, T: int = 1) -> DataFrame:  # noqa: N803
    """increments of the whole index, the longest list, what its task works through, and that of one chunk pair of T chunks."""
    freq = element_frequency(raw) if q is None else element_frequency(raw).filter(F.col("freq") <= q)
    f = F.col("freq")
    return freq.agg(
        F.coalesce(F.sum((f * (f - 1) / 2).cast("long")), F.lit(0)).cast("long").alias("increments"),
        F.coalesce(F.max(f), F.lit(0)).cast("long").alias("longest_list"),
        F.coalesce(F.max((f * (f - 1) / 2).cast("long")), F.lit(0)).cast("long").alias("slowest_task"),
        F.coalesce(F.max(F.ceil(f / T)), F.lit(0)).cast("long").alias("longest_chunk"),
        F.coalesce(F.sum(f * T), F.lit(0)).cast("long").alias("rows_shipped"),
    )


def joining_cost(raw: DataFrame) -> DataFrame:
    sizes = entity_sizes(raw)
    return sizes.agg(F.count("*").alias("entities"), F.max("ucard").alias("largest_entity"), F.sum("ucard").alias("rows"))


def lookup_footprint(raw: DataFrame, limits: list[int]) -> DataFrame:
    """Entries of the lookup table for each C: all entities with more elements."""
    sizes = entity_sizes(raw)
    counted = sizes.agg(*(F.sum((F.col("ucard") > c).cast("long")).alias(f"c{c}") for c in limits))
    return counted.select(F.explode(F.array(*(F.struct(F.lit(c).cast("long").alias("limit"), F.coalesce(F.col(f"c{c}"), F.lit(0)).alias("entries")) for c in limits))).alias("x")).select("x.*")


def max_intersection(raw: DataFrame) -> DataFrame:
    """The most elements that two entities share: what the slowest scoring group gets without partial sums."""
    shared = pair_increments(raw).groupBy("e1", "e2").agg(F.count("*").alias("shared"))
    return shared.agg(F.count("*").alias("candidates"), F.max("shared").alias("longest_intersection"))


def selectivity(candidates: DataFrame, result: DataFrame) -> DataFrame:
    return candidates.agg(F.count("*").alias("candidates")).crossJoin(result.agg(F.count("*").alias("results")))


@dataclass(frozen=True)
class RunOutcome:
    state: str  # ok, table_too_large, over_budget, timeout, failed
    seconds: float | None = None
    rows: int | None = None
    reason: str = ""


def run(make: Callable[[], DataFrame], most_seconds: float | None = None) -> RunOutcome:
    """Runs a query to its end without keeping its rows; after ``most_seconds`` its jobs are cancelled.

    What Spark gives up on, as for want of memory or disk, is ``failed`` with the first line of why.
    """
    from pyspark import SparkContext
    from pyspark.errors import PySparkException

    context, tag = SparkContext._active_spark_context, f"allpairs-run-{time.time_ns()}"
    late = threading.Event()

    def stop() -> None:
        late.set()
        context.cancelJobsWithTag(tag)

    timer = threading.Timer(most_seconds, stop) if most_seconds is not None else None
    began = time.perf_counter()
    if timer:
        context.addJobTag(tag)
        timer.start()
    try:
        rows = make().count()
    except LookupTableTooLarge as e:
        return RunOutcome("table_too_large", reason=str(e))
    except OverBudget as e:
        return RunOutcome("over_budget", reason=str(e))
    except (PySparkException, Py4JJavaError) as e:
        return RunOutcome("timeout" if late.is_set() else "failed", time.perf_counter() - began, reason=str(e).strip().splitlines()[0][:300])
    finally:
        if timer:
            timer.cancel()
            context.removeJobTag(tag)
    return RunOutcome("ok", time.perf_counter() - began, rows)


def timed(make: Callable[[], DataFrame], repeat: int = 5) -> float:
    """Median seconds to write the rows nowhere."""
    def once() -> float:
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        return time.perf_counter() - began

    return median(once() for _ in range(repeat))


def phase_times(raw: DataFrame, attach: Callable[[DataFrame], DataFrame], similar: Callable[[DataFrame], DataFrame], path: str) -> dict[str, float]:
    """Seconds of either phase, with joined rows written in between."""
    began = time.perf_counter()
    attach(raw).write.mode("overwrite").parquet(path)
    between = time.perf_counter()
    similar(raw.sparkSession.read.parquet(path)).write.format("noop").mode("overwrite").save()
    return {"joining": between - began, "similarity": time.perf_counter() - between}


def startup_seconds(spark, repeat: int = 3) -> float:
    """What a job of no work takes."""
    return timed(lambda: spark.range(1), repeat)


def ratio(baseline_seconds: float, own_seconds: float) -> float:
    return baseline_seconds / own_seconds


def scaleout_drop(small: float, large: float) -> float:
    """Share of the run time that more machines save."""
    return 1 - large / small
