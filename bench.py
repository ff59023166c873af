"""Times the headline queries; prints one JSON line.

A query's figure is the median of up to five runs, fewer once BENCH_SECONDS of them have gone by.  The comparison of the four
algorithms has one workload and one measure at each of three thresholds, from raw rows that are written once.
"""

from __future__ import annotations

import json
import os
import time
from functools import partial
from statistics import median

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from allpairs.baselines.prefix_replication import replication_cost
from allpairs.costs import run
from allpairs.experiments.runners import BASELINE, OURS, algorithm, kernel_share, phases, raw_rows, sharding_steps
from allpairs.join import similarity_join
from allpairs.measures import jaccard
from allpairs.workloads import WORKLOADS


def main() -> None:
    where, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "4")
    most = float(os.environ.get("BENCH_SECONDS", "12"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "5g")).config("spark.ui.enabled", "false")
        .config("spark.sql.shuffle.partitions", str(4 * int(cpus))).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    out, more = {}, {}

    def timed(name: str, make, again: bool = True) -> None:
        runs = []
        while not runs or again and len(runs) < 5 and sum(runs) < most:
            began = time.perf_counter()
            more[f"{name}_rows"] = make().agg(F.count("*")).first()[0]
            runs.append(time.perf_counter() - began)
        out[name] = round(median(runs), 2)

    def joined(w: str, t: float, **options):
        return lambda: similarity_join(WORKLOADS[w](spark, where), "ruzicka", t, unique=True, **options)

    timed("warm_up", joined("user_props", 0.5), again=False)
    timed("warm_up_shingles", joined("doc_shingles", 0.9), again=False)
    for t in (0.1, 0.5, 0.9):
        timed(f"shingles_online_t{int(10 * t)}", joined("doc_shingles", t))
    for joining in ("lookup", "sharding"):
        timed(f"shingles_{joining}_t5", joined("doc_shingles", 0.5, joining=joining))
    timed("shingles_pruned_t5", joined("doc_shingles", 0.5, prune=True))
    timed("shingles_banded_t5", joined("doc_shingles", 0.5, prune="bands"))
    timed("shingles_auto_t5", joined("doc_shingles", 0.5, similarity="auto"))
    timed("orders_online_t5", joined("order_parts", 0.5))
    timed("props_online_t3", joined("user_props", 0.3))

    # one workload of entities of some 280 elements, one measure, all four algorithms
    raw = raw_rows(spark, where, "conv_words")
    for t in (0.9, 0.5, 0.1):
        for name in OURS:
            timed(f"words_{name}_t{int(10 * t)}", partial(algorithm, name, raw, "jaccard", t))
        # the baseline is stopped after ten times the budget of a query; its figure is then a lower bound, and says so
        got = run(partial(algorithm, BASELINE, raw, "jaccard", t), 10 * most)
        out[f"words_{BASELINE}_t{int(10 * t)}"], more[f"words_{BASELINE}_t{int(10 * t)}_state"] = round(got.seconds, 2), got.state
        more[f"words_ratio_t{int(10 * t)}"] = round(out[f"words_{BASELINE}_t{int(10 * t)}"] / out[f"words_{OURS[0]}_t{int(10 * t)}"], 2)
        more[f"words_cells_t{int(10 * t)}"] = replication_cost(raw, jaccard(), t).first()[0]
    more["kernel_share"] = {r["t"]: r["kernel_share"] for r in kernel_share(spark, where, "conv_words", steps=(0.9,), repeat=1)}
    shingles = raw_rows(spark, where, "doc_shingles")
    more["phases"] = {name: phases(spark, shingles, "ruzicka", 0.5, name, repeat=1) for name in ("online_aggregation", "sharding")}
    more["sharding_steps"] = sharding_steps(spark, where, limits=(32, 1024, 32768), repeat=1)
    spark.stop()
    total = round(sum(v for k, v in out.items() if not k.startswith("warm_up")), 2)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": total, "unit": "sec", "queries": out, "counts": more, "sf": where.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
