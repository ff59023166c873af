"""Totals in one pass over rows that are grouped by entity.

``window``    one exchange and sort, all JVM; the group spills if it must.
``tagged``    partial totals of each task and its rows go to the entity's task together, totals sorted first, and are
              read in one stream: shuffles little more than the rows and holds none of a group.
``smj``       totals by aggregation, then a merge join, which AQE can split at giant entities.
``salted``    like ``smj``, but an entity's rows are dealt to ``salt`` parts and its totals copied to each.
``buffered``  the whole group in memory of one task, for comparison only.
``cogrouped`` the group and its totals side by side in one task, for comparison only.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from ..measures import Measure
from ..partials import totals_wanted, unilateral_totals
from ..workers import ship


def attach_online(raw: DataFrame, *measures: Measure, impl: str = "window", salt: int = 16, combiner: str = "native") -> DataFrame:
    wanted = totals_wanted(measures)
    if not wanted:
        return raw
    ship(raw.sparkSession)
    of = {name: m for m in measures for name in m.uni}
    if impl == "window":
        group = Window.partitionBy("entity")
        return raw.select("*", *(of[name].total(name)(F.col("mult")).over(group).alias(f"uni_{name}") for name in wanted))
    if impl == "smj":
        return raw.join(_totals(raw, measures, combiner).hint("merge"), "entity")
    if impl == "salted":
        parts = _totals(raw, measures, combiner).withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
        dealt = raw.withColumn("_salt", F.pmod(F.xxhash64("element"), F.lit(salt)).cast("int"))
        return dealt.join(parts.hint("merge"), ["entity", "_salt"]).drop("_salt").select(*raw.columns, *(f"uni_{n}" for n in wanted))
    if impl == "tagged":
        return _tagged(raw, measures, of, wanted, combiner)
    if impl == "buffered":
        return _buffered(raw, measures, of, wanted)
    if impl == "cogrouped":
        return _cogrouped(raw, measures)
    raise ValueError(f"no implementation is called {impl}")


def _totals(raw: DataFrame, measures, combiner: str) -> DataFrame:
    """``none`` ships every row to its group and adds up there, for the ablation of combiners."""
    return unilateral_totals(raw.repartition("entity") if combiner == "none" else raw, *measures)


def _each(raw: DataFrame, of: dict, wanted: list[str], kinds: dict) -> list:
    """What a row adds to each total, in the total's type."""
    return [of[n].each(n)(F.col("mult")).cast(kinds[f"uni_{n}"]).alias(f"uni_{n}") for n in wanted]


def _tagged(raw: DataFrame, measures, of: dict, wanted: list[str], combiner: str) -> DataFrame:
    totals = [f"uni_{n}" for n in wanted]
    kinds = {f.name: f.dataType for f in unilateral_totals(raw, *measures).schema}
    fields = [f for f in raw.schema.fields if f.name in ("entity", "element", "mult")]
    merges = {f"uni_{n}": of[n].merge(n) for n in wanted}
    rows = raw.select("entity", F.lit(1).alias("tag"), "element", "mult", *(F.lit(None).cast(kinds[t]).alias(t) for t in totals))
    partial = unilateral_totals(raw, *measures) if combiner == "native" else raw.select("entity", *_each(raw, of, wanted, kinds))
    if combiner == "partition":
        partial = partial.mapInPandas(lambda frames: _per_task(frames, merges), partial.schema)
    heads = partial.select("entity", F.lit(0).alias("tag"), F.lit(None).cast(fields[1].dataType).alias("element"), F.lit(None).cast(fields[2].dataType).alias("mult"), *totals)
    routed = heads.unionByName(rows).repartition("entity").sortWithinPartitions("entity", "tag")
    schema = StructType([*fields, *(StructField(t, kinds[t]) for t in totals)])
    return routed.mapInPandas(lambda frames: _stream(frames, totals, [merges[t] for t in totals]), schema)


def _per_task(frames: Iterator, merges: dict[str, str]) -> Iterator:
    """Totals of what a task has read so far; given out batch by batch, so nothing grows with the task."""
    for pdf in frames:
        yield pdf.groupby("entity", as_index=False, sort=False).agg(merges)


def _stream(frames: Iterator, totals: list[str], combine: list[str]) -> Iterator:
    """Partial totals of an entity come before its rows, and may be many; an entity may go on in the next batch."""
    open_entity, held = None, None
    for pdf in frames:
        heads = pdf[pdf["tag"] == 0]
        sums = heads.groupby("entity", sort=False)[totals].agg(dict(zip(totals, combine, strict=True)))
        if held is not None and open_entity in sums.index:
            for t, c in zip(totals, combine, strict=True):
                two = (sums.loc[open_entity, t], held[t])
                sums.loc[open_entity, t] = two[0] + two[1] if c == "sum" else max(two) if c == "max" else min(two)
        elif held is not None and len(pdf) and pdf["entity"].iloc[0] == open_entity:
            sums.loc[open_entity] = held
        rows = pdf[pdf["tag"] == 1]
        if len(rows):
            given = sums.loc[rows["entity"]]
            yield rows.drop(columns=["tag", *totals]).reset_index(drop=True).join(given.reset_index(drop=True))
        if len(pdf):
            open_entity = pdf["entity"].iloc[-1]
            held = sums.loc[open_entity] if open_entity in sums.index else None


def _buffered(raw: DataFrame, measures, of: dict, wanted: list[str]) -> DataFrame:
    kinds = {f.name: f.dataType for f in unilateral_totals(raw, *measures).schema}
    merges = {f"uni_{n}": of[n].merge(n) for n in wanted}
    ready = raw.select("entity", "element", "mult", *_each(raw, of, wanted, kinds))

    def group(pdf):
        return pdf.sort_values("element").assign(**{t: getattr(pdf[t], how)() for t, how in merges.items()})

    return ready.groupBy("entity").applyInPandas(group, ready.schema)


def _cogrouped(raw: DataFrame, measures) -> DataFrame:
    cells, totals = raw.select("entity", "element", "mult"), unilateral_totals(raw, *measures)
    schema = StructType([*cells.schema.fields, *(f for f in totals.schema.fields if f.name != "entity")])

    def side_by_side(rows, own):
        return rows.merge(own, on="entity")

    return cells.groupBy("entity").cogroup(totals.groupBy("entity")).applyInPandas(side_by_side, schema)
