"""Long lists cut into chunks: every pair of chunks is worked on apart, and no element is dropped.

A list of T chunks sends each row to the T chunk pairs it takes part in; quadratic work is spread over T(T+1)/2 tasks, each
with two chunks at most.  Lists that fit have one chunk and go the same way.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..measures import Measure
from ..preprocess import element_frequency
from ..scratch import written
from .index import carried, met_near, near_columns, totals_of

#: Rows of one chunk: a chunk pair costs at most the square of this, about 17 million comparisons.
LIST_ROWS = 4096
#: Lists of more than one chunk that are told to every task; there are at most rows / max_list_rows of them.
MOST_BROADCAST = 1_000_000


def chunks_for(joined: DataFrame, T: int | None, max_list_rows: int, freq_limit: int | None = None) -> DataFrame:  # noqa: N803
    """element and its number of chunks, for lists of more than one."""
    return element_frequency(joined).select("element", chunks_of(F.col("freq"), T, max_list_rows, freq_limit).alias("_chunks")).filter("_chunks > 1")


def chunks_of(freq: Column, T: int | None, max_list_rows: int, freq_limit: int | None = None) -> Column:  # noqa: N803
    needed = F.lit(T) if T is not None else F.ceil(freq / max_list_rows).cast("int")
    return needed if freq_limit is None else F.when(freq > freq_limit, needed).otherwise(F.lit(1))


def pair_increments_chunked(joined: DataFrame, T: int | None = None, max_list_rows: int = LIST_ROWS, freq_limit: int | None = None, pairs: str = "unordered", measures: tuple[Measure, ...] = (), t: float | None = None) -> DataFrame:  # noqa: N803
    """Increments as :func:`allpairs.similarity.index.pair_increments` gives them.

    ``T`` chunks for every list, or as many as keep each at ``max_list_rows``; with ``freq_limit`` only lists over it.
    ``pairs='ordered'`` works on all T squared ordered chunk pairs, and drops the half that repeats.  With ``measures`` and
    ``t``, pairs whose totals alone rule them out are left out.  The rows of long lists are dealt to chunks where they are,
    before anything gathers a list: the table of those lists is counted first and broadcast.
    """
    uni = sorted(c for c in joined.columns if c.startswith("uni_"))
    near = near_columns(joined)
    base = joined.select("element", "entity", "mult", *uni, *near)
    if near:  # whole lists of a group lie in one task, and are no longer than two of its chunks
        rows = F.count("*").over(Window.partitionBy(*near[:-1], "element"))
        planned = base.withColumn("_rows", rows).filter("_rows > 1").withColumn("_chunks", chunks_of(F.col("_rows"), T, max_list_rows, freq_limit)).drop("_rows")
    else:
        long_lists = written(chunks_for(joined, T, max_list_rows, freq_limit), "long_lists")
        planned = base.join(F.broadcast(long_lists) if long_lists.count() <= MOST_BROADCAST else long_lists, "element", "left").withColumn("_chunks", F.coalesce("_chunks", F.lit(1)))
    own = planned.withColumn("_own", F.pmod(F.xxhash64(F.col("entity")), F.col("_chunks")).cast("int"))
    dealt = own.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_chunks") - 1)))
    possible = met_near(joined)
    for m in measures if t is not None else ():
        if m.bound is not None:
            possible = possible & m.bound(*totals_of(m, "l.uni_{}", "r.uni_{}"), t)
    if pairs == "ordered":
        return _ordered(dealt, joined, possible)
    keyed = dealt.withColumn("_p", F.least("_own", "_other")).withColumn("_q", F.greatest("_own", "_other")).drop("_other", "_chunks")
    left, right = keyed.alias("l"), keyed.alias("r")
    # with two different chunks under a key, pairs inside either belong to that chunk's own key
    apart = (F.col("l._p") == F.col("l._q")) | (F.col("l._own") != F.col("r._own"))
    on = _same("element", "_p", "_q") & (F.col("l.entity") < F.col("r.entity")) & apart & possible
    return _given(left.join(right.hint("merge"), on), joined)


def _ordered(dealt: DataFrame, joined: DataFrame, possible: Column) -> DataFrame:
    firsts = dealt.withColumn("_p", F.col("_own")).withColumn("_q", F.col("_other")).drop("_own", "_other", "_chunks")
    seconds = dealt.withColumn("_p", F.col("_other")).withColumn("_q", F.col("_own")).drop("_own", "_other", "_chunks")
    on = _same("element", "_p", "_q") & (F.col("l.entity") < F.col("r.entity")) & possible
    return _given(firsts.alias("l").join(seconds.alias("r").hint("merge"), on), joined)


def _same(*names: str) -> Column:
    out = F.lit(True)
    for n in names:
        out = out & (F.col(f"l.{n}") == F.col(f"r.{n}"))
    return out


def _given(met: DataFrame, joined: DataFrame) -> DataFrame:
    return met.select(F.col("l.entity").alias("e1"), F.col("r.entity").alias("e2"), F.col("l.mult").alias("f1"), F.col("r.mult").alias("f2"), *carried(joined))
