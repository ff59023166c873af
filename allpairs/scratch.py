"""Tables written once to the folder that driver and executors share, and deleted at exit."""

from __future__ import annotations

import atexit
import contextlib
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_local: list[str] = []
_written: list[tuple[SparkSession, str]] = []
#: Operators that only pass on what is stored already.
_STORED = {"Project", "Filter", "Relation", "LocalRelation", "LogicalRDD", "Range", "SubqueryAlias", "InMemoryRelation", "View"}


def folder(spark: SparkSession, name: str = "") -> str:
    """``spark.checkpoint.dir``; a temporary folder only on a local master where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        if not _local:
            _local.append(tempfile.mkdtemp(prefix="allpairs-"))
        base = f"file://{_local[0]}"
    return f"{base.rstrip('/')}/{name}" if name else base.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once and read back: nothing of it is computed twice, and its lineage ends."""
    spark = df.sparkSession
    path = folder(spark, f"allpairs-{name}-{uuid.uuid4().hex}")
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def derived(df: DataFrame) -> bool:
    """Whether more than a scan, a projection or a filter makes these rows."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    names = {m.group(1) for line in plan.splitlines() if (m := re.match(r"[\s:+-]*([A-Za-z]+)", line))}
    return not names <= _STORED


def once(df: DataFrame, name: str) -> DataFrame:
    """Rows that several steps read: written first if they are made by more than a scan."""
    return written(df, name) if derived(df) else df


def _file_system(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        with contextlib.suppress(Exception):
            if spark.sparkContext._jsc is not None:
                files, where = _file_system(spark, path)
                files.delete(where, True)
