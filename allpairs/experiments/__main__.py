"""``python -m allpairs.experiments NAME... [--where DIR] [--cores N] [--set key=value]``: rows as JSON lines."""

from __future__ import annotations

import argparse
import ast
import json
import os

from pyspark.sql import SparkSession

from .runners import EXPERIMENTS


def session(cores: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName("experiments").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "5g")).config("spark.ui.enabled", "false")
        .config("spark.sql.shuffle.partitions", str(4 * cores)).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("names", nargs="+", choices=list(EXPERIMENTS))
    parser.add_argument("--where", default=os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"))
    parser.add_argument("--cores", type=int, default=int(os.environ.get("BENCH_CPUS", "4")))
    parser.add_argument("--set", nargs="*", default=[], help="options of the runner, as key=value")
    got = parser.parse_args()
    options = {}
    for pair in got.set:
        key, value = pair.split("=", 1)
        try:
            options[key] = ast.literal_eval(value)
        except (ValueError, SyntaxError):
            options[key] = value
    for name in got.names:
        spark = None if name == "machine_sweep" else session(got.cores)
        for row in EXPERIMENTS[name](spark, got.where, **options):
            print(json.dumps({"experiment": name} | row), flush=True)


if __name__ == "__main__":
    main()
