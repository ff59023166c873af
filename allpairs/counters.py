"""What a run did, from Spark's own status store: seconds, rows, shuffle, spill and the slowest task of each stage."""

from __future__ import annotations

import contextlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from statistics import median

from pyspark.sql import DataFrame, SparkSession

from .measures import Measure

_SUMS = ("executorRunTime", "executorCpuTime", "inputBytes", "inputRecords", "shuffleReadBytes", "shuffleReadRecords", "shuffleWriteBytes", "shuffleWriteRecords", "memoryBytesSpilled", "diskBytesSpilled")


@dataclass
class Counters:
    """Sums over the stages of a run; ``stages`` has them one by one, with the most and the median rows of a task."""

    stages: list[dict] = field(default_factory=list)

    def total(self, name: str) -> int:
        return sum(s[name] for s in self.stages)

    @property
    def task_seconds(self) -> float:
        return self.total("executorRunTime") / 1000

    @property
    def shuffled_bytes(self) -> int:
        return self.total("shuffleWriteBytes")

    @property
    def spilled_bytes(self) -> int:
        return self.total("diskBytesSpilled")

    @property
    def peak_memory(self) -> int:
        return max((s["peakExecutionMemory"] for s in self.stages), default=0)

    def slowest(self) -> dict:
        """The stage whose largest task is the longest; empty if nothing ran."""
        return max(self.stages, key=lambda s: s["most_seconds"], default={})

    def share(self, word: str) -> float:
        """Share of all task time that stages with an operator of this name take."""
        mine = sum(s["executorRunTime"] for s in self.stages if word in s["name"] or word in s["operators"])
        return mine / max(1, self.total("executorRunTime"))


def _tasks(store, stage_id: int, attempt: int) -> dict:
    seconds, rows = [], []
    tasks = store.taskList(stage_id, attempt, 1 << 30)
    for k in range(tasks.size()):
        metrics = tasks.apply(k).taskMetrics()
        if metrics.isDefined():
            m = metrics.get()
            seconds.append(m.executorRunTime() / 1000)
            rows.append(m.inputMetrics().recordsRead() + m.shuffleReadMetrics().recordsRead())
    return {"tasks": len(rows), "most_rows": max(rows, default=0), "median_rows": median(rows) if rows else 0, "most_seconds": max(seconds, default=0.0), "median_seconds": median(seconds) if seconds else 0.0}


def _operators(store, stage_id: int) -> str:
    graph = store.operationGraphForStage(stage_id)
    names: list[str] = []

    def walk(cluster) -> None:
        names.append(cluster.name())
        inner = cluster.childClusters()
        for k in range(inner.size()):
            walk(inner.apply(k))

    with contextlib.suppress(Exception):
        walk(graph.rootCluster())
    return " ".join(names)


@contextlib.contextmanager
def counted(spark: SparkSession) -> Iterator[Counters]:
    """Fills in what the stages that run inside the block did, once it ends."""
    out, scala = Counters(), spark.sparkContext._jsc.sc()
    store, gateway = scala.statusStore(), spark.sparkContext._gateway

    def known() -> dict[tuple[int, int], object]:
        scala.listenerBus().waitUntilEmpty(60_000)
        found = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): s for s in (found.apply(k) for k in range(found.size()))}

    before = set(known())
    yield out
    for (stage_id, attempt), s in sorted(known().items()):
        if (stage_id, attempt) in before or s.status().toString() != "COMPLETE":
            continue
        with contextlib.suppress(Exception):
            row = {"stage": stage_id, "name": s.name(), "peakExecutionMemory": s.peakExecutionMemory()} | {n: getattr(s, n)() for n in _SUMS}
            out.stages.append(row | _tasks(store, stage_id, attempt) | {"operators": _operators(store, stage_id)})


def explain_phases(raw: DataFrame, measure: Measure, t: float, **options) -> dict[str, str]:
    """Formatted plans of the two phases and of the whole join; nothing of the join itself runs."""
    from .join import attach, similarity_join
    from .similarity.index import pair_increments
    from .similarity.score import score_pairs

    joining = {k: v for k, v in options.items() if k in ("joining", "impl", "C", "salt")}
    joined = attach(raw, measure, **joining)
    plans = {"joining": joined, "similarity": score_pairs(pair_increments(joined, (measure,), t, prune=options.get("prune", False)), measure, t), "whole": similarity_join(raw, measure, t, unique=True, **options)}
    return {name: _formatted(df) for name, df in plans.items()}


def _formatted(df: DataFrame) -> str:
    jvm = df.sparkSession.sparkContext._jvm
    return df._jdf.queryExecution().explainString(jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
