"""Exact filter-and-verify join: whole records go, once for each of their rarest elements, to where candidates meet.

Three stages: a global element order (rare first, or by hash where frequencies can't be held), replication of each record under
its prefix and verification of the records that meet, and, if wanted, the records joined to the pairs.  Elements may share
routing keys (``grouping``).  Multisets are expanded to sets first.  The source of the method is public literature on
prefix-filtered set joins; costs grow with prefix length times record length.

Where records are long, that is more than any disk holds (at 0.1 GB of documents and t = 0.9, 901 million cells under prefix elements
that two records hold).  ``kernel='blocks'`` routes whole records by size instead: those of near sizes meet in one task, once, and are
paired there by their rarest elements and compared whole.  Records whose prefix nobody shares are found first and don't move.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructField, StructType

from ..joining import attach_online
from ..measures import Measure, UnsupportedMeasure
from ..model import as_sets, expand_to_set, positive
from ..preprocess import element_frequency
from ..scratch import once, written
from ..similarity.blocks import pair_sums_blocked
from ..similarity.score import value_of
from ..workers import ship


#: Records of short lists that are worked on together, and elements that are compared at once.
LISTED_ROWS = 1 << 16
LISTED_CELLS = 1 << 21
#: A record that meets more elements than this is compared by itself.
SHORT_CELLS = 1 << 13


class OverBudget(RuntimeError):
    """More cells would be shipped than the run may ship."""


def element_order(raw: DataFrame, by: str = "frequency") -> DataFrame:
    """element and ``pos``: elements come in ascending (pos, element)."""
    if by == "frequency":
        return element_frequency(raw).select("element", F.col("freq").alias("pos"))
    if by == "hash":
        return raw.select("element").distinct().withColumn("pos", F.xxhash64("element"))
    raise ValueError(f"no order is called {by}")


def records(raw: DataFrame, order: str = "frequency") -> DataFrame:
    """entity, n and ``items``, all its elements in the global order."""
    if order == "hash":
        placed = raw.withColumn("pos", F.xxhash64("element"))
    else:
        placed = raw.join(element_order(raw, order), "element")
    return placed.groupBy("entity").agg(F.sort_array(F.collect_list(F.struct("pos", "element"))).alias("_items"), F.count("*").alias("n")).select("entity", "n", F.transform("_items", lambda x: x["element"]).alias("items"))


def prefixes(recs: DataFrame, measure: Measure, t: float) -> DataFrame:
    length = F.greatest(measure.prefix_len(F.col("n"), t), F.lit(0)).cast("int")
    return recs.withColumn("prefix", F.slice("items", F.lit(1), length))


def replication_cost(raw: DataFrame, measure: Measure, t: float, order: str = "frequency") -> DataFrame:
    """Cells that replication ships: prefix length times size, summed."""
    sizes = raw.groupBy("entity").agg(F.count("*").alias("n"))
    return sizes.agg(F.coalesce(F.sum(measure.prefix_len(F.col("n"), t) * F.col("n")), F.lit(0)).cast("long").alias("cells"))


def replicate_prefixes(recs: DataFrame, measure: Measure, t: float, grouping: int | None = None) -> DataFrame:
    """Each record once a prefix element (or routing key)."""
    copies = prefixes(recs, measure, t).withColumn("key", F.explode("prefix")).drop("prefix")
    if grouping is None:
        return copies
    routed = copies.withColumn("key", F.pmod(F.xxhash64("key"), F.lit(grouping)))
    return routed.dropDuplicates(["key", "entity"])


def _sim(measure: Measure, shared, left, right):
    conj = {name: shared for name in measure.conj}
    return measure.combine(conj, {n: left for n in measure.uni}, {n: right for n in measure.uni})


def verify_whole(copies: DataFrame, measure: Measure, t: float, inclusive: bool = True, dedup: str = "first", filters: tuple[str, ...] = ("length",)) -> DataFrame:
    """Pairs of records under one key, compared whole; a pair that meets under several keys is given once."""
    on = (F.col("l.key") == F.col("r.key")) & (F.col("l.entity") < F.col("r.entity"))
    if "length" in filters:
        low, high = measure.len_range(F.col("l.n"), t)
        on = on & (F.col("r.n") >= low - 1e-6) & (F.col("r.n") <= high + 1e-6)
    met = copies.alias("l").join(copies.alias("r").hint("merge"), on)
    both = met.withColumn("_both", F.array_intersect("l.items", "r.items"))
    scored = both.withColumn("sim", _sim(measure, F.size("_both").cast("long"), F.col("l.n"), F.col("r.n"))).filter(measure.passes(F.col("sim"), t, inclusive))
    if dedup == "first":
        scored = scored.filter(F.element_at("_both", 1) == F.col("l.key"))
    pairs = scored.select(F.col("l.entity").alias("e1"), F.col("r.entity").alias("e2"), "sim")
    return pairs if dedup == "first" else pairs.distinct()


def _plain(items: DataFrame, *names: str) -> DataFrame:
    """Elements of several parts, such as an expanded set's, as one string each, by which Arrow can tell them apart."""
    for name in names:
        kind = items.schema[name].dataType
        if isinstance(kind, StructType):
            items = items.withColumn(name, F.to_json(name))
        elif isinstance(kind, ArrayType) and isinstance(kind.elementType, StructType):
            items = items.withColumn(name, F.transform(name, lambda x: F.to_json(x)))
    return items


def verify_indexed(copies: DataFrame, measure: Measure, t: float, inclusive: bool = True) -> DataFrame:
    """The same inside one task for each key: records in order of size, each compared at once with all those of the sizes it may pair with.

    A task reads its keys in one stream and works on many short lists together; of a long list, one record after the other.
    """
    ship(copies.sparkSession)
    kind = copies.schema["entity"].dataType
    schema = StructType([StructField("a", kind), StructField("b", kind), StructField("shared", DoubleType()), StructField("na", DoubleType()), StructField("nb", DoubleType())])

    def run(batches):
        import pyarrow as pa

        held = None
        for batch in batches:
            held = pa.concat_tables([*([] if held is None else [held]), pa.Table.from_batches([batch])])
            if held.num_rows < LISTED_ROWS or held["key"][0] == held["key"][-1]:
                continue
            cut = int(_starts(held["key"])[-1])  # the last key may go on
            yield from _listed(held.slice(0, cut), measure, t)
            held = held.slice(cut)
        if held is not None and held.num_rows:
            yield from _listed(held, measure, t)

    lists = _plain(copies.select("key", "entity", "n", "items"), "key", "items").repartition("key").sortWithinPartitions("key", "n", "entity")
    first = F.col("a") < F.col("b")
    found = lists.mapInArrow(run, schema).withColumn("sim", _sim(measure, F.col("shared"), F.col("na"), F.col("nb"))).filter(measure.passes(F.col("sim"), t, inclusive))
    return found.select(F.when(first, F.col("a")).otherwise(F.col("b")).alias("e1"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("e2"), "sim").distinct()


def _starts(keys):
    """Where each run of equal keys begins."""
    import numpy as np

    codes = np.asarray(keys.combine_chunks().dictionary_encode().indices)
    return np.flatnonzero(np.diff(codes, prepend=-1))


def _listed(table, measure: Measure, t: float):
    """Pairs of records of one key that may reach t, as batches of entities, the number of elements they share and their sizes."""
    import numpy as np
    import pyarrow as pa

    entity, lists = table["entity"].combine_chunks(), table["items"].combine_chunks()
    sizes, lengths = np.asarray(table["n"]).astype(np.int64), np.asarray(lists.value_lengths()).astype(np.int64)
    coded = lists.flatten().dictionary_encode()
    codes, many = np.asarray(coded.indices).astype(np.int64), len(coded.dictionary)
    ends = np.concatenate([[0], np.cumsum(lengths)])
    starts = _starts(table["key"])
    group = np.repeat(np.arange(len(starts)), np.diff(starts, append=len(sizes)))
    most = int(sizes.max()) + 2
    least = np.maximum(np.ceil(measure.len_range(sizes.astype(float), t)[0] - 1e-6), 0).astype(np.int64)
    rows = np.arange(len(sizes))
    low = np.minimum(np.searchsorted(group * most + sizes, group * most + np.minimum(least, most - 1)), rows)
    cells = ends[rows] - ends[low]
    in_rows = np.repeat(rows * many, lengths) + codes
    in_rows.sort()
    here = np.zeros(many, bool)

    def given(i, k, shared):
        if measure.plain is not None:  # the rest is left to Spark's own arithmetic
            with np.errstate(divide="ignore", invalid="ignore"):
                good = measure.plain[1](shared.astype(float), sizes[i].astype(float), sizes[k].astype(float)) >= t - 1e-6
            i, k, shared = i[good], k[good], shared[good]
        return pa.RecordBatch.from_arrays([entity.take(pa.array(i)), entity.take(pa.array(k)), *(pa.array(x.astype(float)) for x in (shared, sizes[i], sizes[k]))], ["a", "b", "shared", "na", "nb"])

    short = np.flatnonzero((low < rows) & (cells <= SHORT_CELLS))
    done = np.concatenate([[0], np.cumsum(cells[short])])
    begin = 0
    while begin < len(short):
        stop = max(begin + 1, int(np.searchsorted(done, done[begin] + LISTED_CELLS, "right")) - 1)
        mine = short[begin:stop]
        others = mine - low[mine]
        k = np.repeat(mine, others)
        i = np.arange(len(k)) - np.repeat(np.cumsum(others) - others - low[mine], others)
        at = np.cumsum(lengths[i]) - lengths[i]
        probe = codes[np.arange(lengths[i].sum()) + np.repeat(ends[i] - at, lengths[i])] + np.repeat(k * many, lengths[i])
        hit = in_rows[np.minimum(np.searchsorted(in_rows, probe), len(in_rows) - 1)] == probe
        yield given(i, k, np.add.reduceat(hit.astype(np.int64), at))
        begin = stop
    for k in np.flatnonzero((low < rows) & (cells > SHORT_CELLS)).tolist():
        mine = codes[ends[k] : ends[k + 1]]
        here[mine] = True
        begin = int(low[k])
        while begin < k:
            stop = min(k, max(begin + 1, int(np.searchsorted(ends, ends[begin] + LISTED_CELLS, "right")) - 1))
            shared = np.add.reduceat(here[codes[ends[begin] : ends[stop]]].astype(np.int64), ends[begin:stop] - ends[begin])
            yield given(np.arange(begin, stop), np.full(stop - begin, k), shared)
            begin = stop
        here[mine] = False


def able(cells: DataFrame, measure: Measure, t: float) -> DataFrame:
    """Rows of entities that may be in a pair: with a whole prefix of elements of its own, an entity is in none.

    Only a part of the elements, chosen by hash, is looked at, some three times what prefixes take.  Elements of one hash are taken
    for one, which can only leave more entities.
    """
    size = F.count("*") if measure.sets else F.sum("mult")
    share = min(1000, int(3 * measure.prefix_len(1000, t)))
    part = cells.select("entity", "mult", F.xxhash64("element").alias("h")).filter(F.pmod("h", F.lit(1000)) < share)
    alone = part.groupBy("h").agg(F.min("entity").alias("entity"), F.max("entity").alias("other"), size.alias("own")).filter("entity = other")
    own = alone.groupBy("entity").agg(F.sum("own").alias("own"))
    sizes = cells.groupBy("entity").agg(size.alias("n"))
    length = F.greatest(measure.prefix_len(F.col("n"), t), F.lit(1))
    some = sizes.join(own, "entity", "left").filter(F.coalesce("own", F.lit(0)) < length).select("entity")
    return cells.join(written(some, "able"), "entity", "left_semi")


def verify_blocks(raw: DataFrame, measure: Measure, t: float, inclusive: bool = True) -> DataFrame:
    """Records of near sizes meet in blocks, whole, and are paired by their rarest elements."""
    cells = positive(as_sets(raw) if measure.sets else raw)
    joined = once(attach_online(able(cells, measure, t), measure), "joined_rows")
    pairs = pair_sums_blocked(joined, measure, t, prune=True).withColumn("sim", value_of(measure))
    return pairs.filter(measure.passes(F.col("sim"), t, inclusive)).select("e1", "e2", "sim")


def rejoin_records(pairs: DataFrame, recs: DataFrame) -> DataFrame:
    left, right = (recs.select(F.col("entity").alias(f"e{k}"), F.col("items").alias(f"items{k}")) for k in (1, 2))
    return pairs.join(left, "e1").join(right, "e2")


def prefix_replication(raw: DataFrame, measure: Measure, t: float, order: str = "frequency", grouping: int | None = None, kernel: str = "nested", filters: tuple[str, ...] = ("length",), dedup: str | None = None, inclusive: bool = True, expand: bool | None = None, most_cells: int | None = None) -> DataFrame:
    """e1, e2, sim.  ``most_cells`` counts what would be shipped first, and raises OverBudget."""
    if measure.prefix_len is None:
        raise UnsupportedMeasure(f"{measure.name} has no prefix length")
    if kernel == "blocks":
        return verify_blocks(raw, measure, t, inclusive)
    cells = expand_to_set(raw) if (not measure.sets if expand is None else expand) else raw
    if most_cells is not None and (shipped := replication_cost(cells, measure, t).first()["cells"]) > most_cells:
        raise OverBudget(f"{shipped} cells would be shipped; the budget is {most_cells}")
    copies = replicate_prefixes(records(cells, order), measure, t, grouping)
    if kernel == "indexed":
        return verify_indexed(copies, measure, t, inclusive)
    return verify_whole(copies, measure, t, inclusive, dedup or ("first" if grouping is None else "distinct"), filters)
