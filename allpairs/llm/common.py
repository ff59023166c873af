"""What all operators of this subpackage share: input columns, shared scratch tables, worker paths."""

from __future__ import annotations

import atexit
import contextlib
import gc
import os
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of one key that any task can take.
HOT_ROWS = 256
_ROOT = str(Path(__file__).resolve().parents[2])
_local_base: list[str] = []
_written: list[tuple[SparkSession, str]] = []


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns an operator works on, so that other columns of any name can't clash; null text is empty."""
    return docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver has it.

    On clusters without that folder the package is passed with ``--py-files`` instead.
    """
    paths = spark.sparkContext.environment.get("PYTHONPATH", "")
    if _ROOT not in paths.split(os.pathsep):
        spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(filter(None, [_ROOT, paths]))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; on ``local`` masters a temporary one if unset."""
    base = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    if not _local_base:
        _local_base.append("file://" + tempfile.mkdtemp(prefix="allpairs-"))
    return _local_base[0]


def keep(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back.

    This cuts the lineage: rows whose numbering depends on how tasks were cut can't change when
    an executor is lost, and Python stages don't run twice.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/allpairs-{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _written.append((spark, path))
    # shuffle files of what is written now are of no more use; Spark deletes them once the JVM has collected their plans
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        with contextlib.suppress(Exception):
            if spark.sparkContext._jsc is not None:
                _delete(spark, path)


def forget(*tables: DataFrame) -> None:
    """Delete scratch tables that nothing lazy still reads."""
    for df in tables:
        for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            for known in [x for x in _written if x[1].rsplit("/", 1)[-1] == path.rsplit("/", 1)[-1]]:
                _delete(*known)
                _written.remove(known)


def size_bounded_batches(batches, text_at: int, max_bytes: int = 4 << 20):
    """Slices of Arrow record batches that hold at most ``max_bytes`` of text, or one row.

    Spark itself bounds a batch by ``spark.sql.execution.arrow.maxBytesPerBatch``; this bounds what is made of it.
    """
    import numpy as np
    import pyarrow.compute as pc

    for batch in batches:
        ends = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(batch.column(text_at)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)])
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(ends, ends[at] + max_bytes, "right")) - 1)
            yield batch.slice(at, to - at)
            at = to


def unused(df: DataFrame, *names: str) -> list[str]:
    """Names like the given ones that no column of ``df`` has, whatever the case."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def quoted(name: str):
    """A column by name, whatever characters the name has."""
    return F.col(f"`{name.replace('`', '``')}`")


def columns_of(df: DataFrame) -> list:
    return [quoted(c) for c in df.columns]


def spread_join(big: DataFrame, small: DataFrame, keys: list[str], size: str, how: str = "inner", parts: int = 4096) -> DataFrame:
    """``big`` joined with ``small``, which has one row for each key and in ``size`` how many rows of ``big`` have it.

    Keys of more than a ``parts``-th of all rows that ``small`` counts, fewer than ``parts``, are broadcast, so their rows
    stay where they are; all others are shuffled, and no task gets more of one key than that part.
    """
    seen = small.agg(F.coalesce(F.sum(size), F.lit(0)).alias("total"), F.coalesce(F.max(size), F.lit(0)).alias("most")).first()
    limit = max(HOT_ROWS, seen["total"] // parts)
    if seen["most"] <= limit:
        return big.join(small, keys, how)
    hot = keep(small.filter(F.col(size) > limit), "hot_keys")
    cold = big.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(small.filter(F.col(size) <= limit), keys, how)
    return big.join(F.broadcast(hot), keys, "left_semi" if how == "left_semi" else "inner").unionByName(cold)


def with_columns_of_text(df: DataFrame, text_col: str, fields: str, make) -> DataFrame:
    """All columns of ``df`` and those of ``fields``, which ``make()(texts)`` gives as arrays in a Python stage.

    Null texts reach it as None.  ``make`` runs once a task, on the worker.  An input column that has the name of a
    new one is replaced; ``unused`` finds names that aren't taken.
    """
    from pyspark.sql.types import StructField, StructType

    ship(df.sparkSession)
    new = StructType.fromDDL(fields)
    taken = {f.name.lower() for f in new}
    df = df.select(*(quoted(c) for c in df.columns if c.lower() not in taken))
    at, names = df.columns.index(text_col), [*df.columns, *(f.name for f in new)]
    # the stage knows columns by number, as a name with a dot can't be given to it
    numbered = [f"c{k}" for k in range(len(names))]
    fields_ = [StructField(n, f.dataType, f.nullable) for n, f in zip(numbered, [*df.schema.fields, *new.fields], strict=True)]

    def run(batches):
        import pyarrow as pa

        columns_of = make()
        for batch in size_bounded_batches(batches, at, 1 << 20):
            arrays = columns_of(batch.column(at).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns, *arrays], numbered)

    return df.toDF(*numbered[: len(df.columns)]).mapInArrow(run, StructType(fields_)).toDF(*names)
