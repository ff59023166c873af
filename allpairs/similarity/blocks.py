"""Dense collections, where nearly every pair shares elements: whole blocks of entities meet, and no increments are made.

Entities are dealt to B blocks.  Every pair of blocks is one task's work, which sums what each pair of its entities shares
in memory and gives only pairs that can reach the threshold.  A row is shipped B times and a pair only if it is a result,
where the index ships every pair that shares anything.  With ``prune``, blocks hold entities of near totals, only blocks that
can have results meet, and in a task only pairs that share one of their rarest elements are summed.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, MapType, StringType, StructField, StructType

from ..measures import Measure, UnsupportedMeasure
from ..preprocess import element_frequency
from ..scratch import written
from ..workers import ship

#: Entities and rows of one block; a task holds two, and the sums of all their pairs (32 MB).
BLOCK_ENTITIES = 2048
BLOCK_ROWS = 1 << 18
#: Rows of one block where pairs are pruned: no sums of all pairs are held then.
PRUNED_ROWS = 3 << 19
#: Different strings that are told to every task as numbers; beyond, rows keep their strings.
MOST_NUMBERED = 1_000_000
#: Meetings of two entities at one element that are looked at together.
MEETINGS = 1 << 21
#: Numbers of one dense slice of a block, for measures that add products.
SLICE = 1 << 21
#: Values this near the threshold are left to Spark's own arithmetic.
NEAR = 1e-6


def blocks_for(joined: DataFrame) -> int:
    """As many blocks as keep each within both limits."""
    entities, rows = joined.agg(F.count_distinct("entity"), F.count("*")).first()
    return max(1, -(-entities // BLOCK_ENTITIES), -(-rows // BLOCK_ROWS))


def fits(rows: DataFrame, measure: Measure) -> bool:
    """Whether the measure has a form on arrays and elements are single values."""
    return measure.plain is not None and not measure.distance and measure.symmetric and not isinstance(rows.schema["element"].dataType, (StructType, ArrayType, MapType))


def banded_blocks(joined: DataFrame, measure: Measure, t: float) -> tuple[Column, list[list[int]]]:
    """The block of a row by its entity's total, and for each block those that it can have results with, itself included."""
    total = F.col(f"uni_{measure.uni[0]}").cast("double")
    least = measure.least_ratio(t) * (1 - NEAR)
    band = F.coalesce(F.floor(F.log(total) * F.lit(8 / max(-math.log(least), 0.08))), F.lit(0).cast("long"))
    counted = joined.groupBy(band.alias("band")).agg(F.count("*").alias("rows"), F.min(total).alias("low"), F.max(total).alias("high")).orderBy("band").collect()
    blocks, places = [], {}  # low, high and rows of each block; first block and number of blocks of each band
    for r in counted:
        parts = -(-r["rows"] // PRUNED_ROWS)
        if parts == 1 and blocks and blocks[-1][2] + r["rows"] <= PRUNED_ROWS:
            blocks[-1] = (blocks[-1][0], r["high"], blocks[-1][2] + r["rows"])
            places[r["band"]] = (len(blocks) - 1, 1)
        else:
            places[r["band"]] = (len(blocks), parts)
            blocks += [(r["low"], r["high"], r["rows"] / parts)] * parts
    meets = [[q for q, b in enumerate(blocks) if not (min(a[1], b[1]) < least * max(a[0], b[0]))] for a in blocks]
    if not places:
        return F.lit(0), [[0]]
    first, many = (F.create_map(*(F.lit(x) for band_, place in places.items() for x in (band_, place[k])))[band] for k in (0, 1))
    return (first + F.pmod(F.xxhash64("entity"), many.cast("long"))).cast("int"), meets


def numbered(joined: DataFrame) -> DataFrame | None:
    """element and its number, the most frequent ones first from 0, for sets of strings; None if there are too many to tell every task."""
    ordered = element_frequency(joined).orderBy(F.desc("freq"), "element")
    placed = written(ordered.select("element", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1).alias("at")), "numbers")
    counts = sorted((r["part"], r["count"]) for r in placed.groupBy("part").count().collect())
    if not counts or sum(c for _, c in counts) > MOST_NUMBERED:
        return None
    before = F.create_map(*(F.lit(x) for k, (part, _) in enumerate(counts) for x in (part, sum(c for _, c in counts[:k]))))
    return placed.select("element", (F.col("at") + before[F.col("part")]).cast("int").alias("number"))


def pair_sums_blocked(joined: DataFrame, measure: Measure, t: float, blocks: int | None = None, prune: bool = False) -> DataFrame:
    """e1, e2 (e1 < e2), the shared sum and both totals, for every pair whose value is near t or above it.

    Rows come as :func:`allpairs.join.attach` gives them.  The measure adds one kind of shared sum that numpy knows.
    """
    if not fits(joined, measure):
        raise UnsupportedMeasure(f"{measure.name} of these elements has no form for whole blocks")
    ship(joined.sparkSession)
    total, shared, value = f"uni_{measure.uni[0]}", *measure.plain
    kinds = dict(joined.dtypes)
    prune = bool(prune) and measure.least_ratio is not None and shared in ("least", "one")
    if prune:
        place, meets = banded_blocks(joined, measure, t)
    else:
        B = blocks_for(joined) if blocks is None else blocks  # noqa: N806
        place, meets = F.pmod(F.xxhash64("entity"), F.lit(B)).cast("int"), [list(range(B))] * B
    known = numbered(joined) if prune and shared == "one" and isinstance(joined.schema["element"].dataType, StringType) else None
    if known is None:
        packed = joined.groupBy("entity", total, place.alias("_own")).agg(F.collect_list("element").alias("elements"), F.collect_list(F.col("mult").cast("double")).alias("mults"))
    else:
        n = F.col("number")
        rows = joined.select("entity", "element", total, place.alias("_own")).join(F.broadcast(known), "element")
        packed = rows.groupBy("entity", total, "_own").agg(F.collect_list(F.when(n < 1 << 16, n - (1 << 15)).cast("short")).alias("common"), F.collect_list(F.when(n >= 1 << 16, n)).alias("elements"))
    others = F.array(*(F.array(*(F.lit(q) for q in row)) for row in meets))
    dealt = packed.withColumn("_other", F.explode(F.element_at(others, F.col("_own") + 1))).withColumn("_p", F.least("_own", "_other")).withColumn("_q", F.greatest("_own", "_other")).drop("_other")
    entity, uni = joined.schema["entity"].dataType, joined.schema[total].dataType
    schema = StructType([StructField("a", entity), StructField("b", entity), StructField("na", uni), StructField("nb", uni), StructField("s", DoubleType())])

    def met(table):
        import numpy as np
        import pyarrow as pa

        at = np.asarray(table["_own"])
        apart = table["_p"][0].as_py() != table["_q"][0].as_py()
        mine = at == table["_p"][0].as_py()
        left = _block(table.filter(pa.array(mine)))
        right = _block(table.filter(pa.array(~mine))) if apart else left
        if not left[1].size or not right[1].size:
            return _arrow(table, total).empty_table()
        codes = pa.concat_arrays([left[0], right[0]] if apart else [left[0]]).dictionary_encode()
        ids, many = np.asarray(codes.indices), len(codes.dictionary)
        ids_l, ids_r = ids[: len(left[0])], ids[len(left[0]) :] if apart else ids
        names = [table.filter(pa.array(mine)), table.filter(pa.array(~mine)) if apart else table]
        n_l, n_r = (np.asarray(x[total].cast(pa.float64())) for x in names)
        if prune:
            found = _pruned_sums(ids_l, left, n_l, ids_r, right, n_r, many, apart, shared, value, t)
        elif shared == "least" or not (np.isfinite(left[1]).all() and np.isfinite(right[1]).all()):
            found = _sums_by_row(ids_l, left, ids_r, right, many, apart, shared)
        else:
            found = _product_sums(ids_l, left, ids_r, right, many, shared)
        rows, cols, sums = [], [], []
        for first, s in () if prune else found:
            with np.errstate(divide="ignore", invalid="ignore"):
                keep = ~(value(s, n_l[first : first + len(s), None], n_r[None, :]) < t - NEAR) & (s != 0)  # NaN is above all in Spark
            if not apart:
                keep &= np.arange(len(n_r))[None, :] > np.arange(first, first + len(s))[:, None]
            i, j = np.nonzero(keep)
            rows.append(i + first)
            cols.append(j)
            sums.append(s[i, j])
        for i, j, s in found if prune else ():
            rows.append(i)
            cols.append(j)
            sums.append(s)
        if not rows:
            return _arrow(table, total).empty_table()
        i, j = pa.array(np.concatenate(rows)), pa.array(np.concatenate(cols))
        return pa.table([names[0]["entity"].take(i), names[1]["entity"].take(j), names[0][total].take(i), names[1][total].take(j), pa.array(np.concatenate(sums))], _arrow(table, total))

    pairs = dealt.groupBy("_p", "_q").applyInArrow(met, schema)
    first, (name,) = F.col("a") < F.col("b"), measure.conj
    conj = F.col("s").cast("long") if kinds["mult"] in ("bigint", "int", "smallint", "tinyint") else F.col("s")
    return pairs.select(F.when(first, F.col("a")).otherwise(F.col("b")).alias("e1"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("e2"), F.when(first, F.col("na")).otherwise(F.col("nb")).alias(f"{total}_1"), F.when(first, F.col("nb")).otherwise(F.col("na")).alias(f"{total}_2"), conj.alias(f"conj_{measure.name}_{name}"))


def _arrow(table, total: str):
    import pyarrow as pa

    entity, uni = table.schema.field("entity").type, table.schema.field(total).type
    return pa.schema([("a", entity), ("b", entity), ("na", uni), ("nb", uni), ("s", pa.float64())])


def _block(table):
    """Elements and multiplicities of all entities, one after the other, and where each entity's begin."""
    import numpy as np

    lists = table["elements"].combine_chunks()
    if "common" in table.column_names:
        import pyarrow as pa

        both = [(x.flatten(), np.asarray(x.value_lengths()).astype(np.int64)) for x in (table["common"].combine_chunks(), lists)]
        starts = np.concatenate([[0], np.cumsum(both[0][1] + both[1][1])])
        out = np.empty(starts[-1], np.int32)
        for (values, sizes), begin, more in zip(both, (starts[:-1], starts[:-1] + both[0][1]), (1 << 15, 0)):
            out[np.repeat(begin - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())] = np.asarray(values).astype(np.int32) + more
        return pa.array(out), np.ones(len(out)), starts
    values = table["mults"].combine_chunks()
    return lists.flatten(), np.asarray(values.flatten()), np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()))]).astype(np.int64)


def _each(shared: str, mine, theirs):
    import numpy as np

    if shared == "least":
        return np.minimum(mine, theirs)
    return np.ones_like(theirs) if shared == "one" else np.abs(mine * theirs) if shared == "magnitude" else mine * theirs


def _sums_by_row(ids_l, left, ids_r, right, many: int, apart: bool, shared: str):
    """For one left entity after the other, the sums with every right one over the elements that both hold."""
    import numpy as np

    here, held = np.zeros(many), np.zeros(many, bool)
    for k in range(len(left[2]) - 1):
        mine = ids_l[left[2][k] : left[2][k + 1]]
        here[mine], held[mine] = left[1][left[2][k] : left[2][k + 1]], True
        low = 0 if apart else k  # of one block, only those after it
        ids, values = ids_r[right[2][low] :], right[1][right[2][low] :]
        sums = np.zeros((1, len(right[2]) - 1))
        sums[0, low:] = np.add.reduceat(np.where(held[ids], _each(shared, here[ids], values), 0.0), right[2][low:-1] - right[2][low])
        here[mine], held[mine] = 0, False
        yield k, sums


def _pruned_sums(ids_l, left, n_l, ids_r, right, n_r, many: int, apart: bool, shared: str, value, t: float):
    """Pairs near t or above it, with their sums: rarest elements first, a pair is summed only if from the first element that both
    hold on, either has enough left.  Any order of elements gives the same pairs.
    """
    import numpy as np

    freq = np.bincount(ids_l, minlength=many) + (np.bincount(ids_r, minlength=many) if apart else 0)
    place = np.empty(many, np.int64)
    place[np.argsort(freq, kind="stable")] = np.arange(many)
    sides = []
    for ids, (_, mults, starts), n in ((ids_l, left, n_l), (ids_r, right, n_r))[: 1 + apart]:
        who = np.repeat(np.arange(len(n)), np.diff(starts))
        order = np.lexsort((place[ids], who))
        codes, mults = place[ids][order], mults[order]
        weight = mults if shared == "least" else np.ones(len(mults))
        sums = np.concatenate([[0], np.cumsum(weight)])
        rest = n[who] - (sums[:-1] - sums[starts[:-1]][who])  # of the total, from here on
        able = np.flatnonzero(value(rest, n[who], rest) >= t - NEAR)
        able = able[np.argsort(codes[able], kind="stable")]
        sides.append((codes, mults, starts, who[able], rest[able], codes[able], n))
    a, b = sides[0], sides[-1]
    low, high = np.searchsorted(b[5], a[5], "left"), np.searchsorted(b[5], a[5], "right")
    if not apart:  # of one block, each two once
        low = np.arange(len(a[5])) + 1
    ends = np.cumsum(high - low)
    here = np.zeros(many)
    pairs, begin = [], 0
    while begin < len(ends):
        done = ends[begin - 1] if begin else 0
        stop = max(begin + 1, int(np.searchsorted(ends, done + MEETINGS, "right")))
        k = np.repeat(np.arange(begin, stop), (high - low)[begin:stop])
        m = np.arange(len(k)) - (ends[k] - (high - low)[k] - done) + low[k]
        i, j = a[3][k], b[3][m]
        good = value(np.minimum(a[4][k], b[4][m]), a[6][i], b[6][j]) >= t - NEAR
        i, j = i[good], j[good]
        if not apart:
            i, j = np.minimum(i, j), np.maximum(i, j)
        pairs.append(np.unique(i * np.int64(len(b[6])) + j))
        if sum(map(len, pairs[1:])) > max(len(pairs[0]), 4 * MEETINGS):  # copies meet at every element: each pair is held once, or twice
            pairs = [np.unique(np.concatenate(pairs))]
        begin = stop
    if not pairs:
        return
    pairs = np.unique(np.concatenate(pairs))
    who, other = pairs // len(b[6]), pairs % len(b[6])
    starts, lengths = b[2], np.diff(b[2])
    bounds = np.flatnonzero(np.diff(who, prepend=-1, append=len(a[6])))
    for first, last in zip(bounds[:-1], bounds[1:]):
        i, mine = who[first], other[first:last]
        codes = a[0][a[2][i] : a[2][i + 1]]
        here[codes] = a[1][a[2][i] : a[2][i + 1]]
        size = lengths[mine]
        at = np.cumsum(size) - size
        cells = np.arange(size.sum()) + np.repeat(starts[mine] - at, size)
        got = here[b[0][cells]]
        s = np.add.reduceat(np.minimum(got, b[1][cells]) if shared == "least" else (got > 0).astype(float), at)
        here[codes] = 0
        good = value(s, a[6][i], b[6][mine]) >= t - NEAR
        if good.any():
            yield np.full(int(good.sum()), i), mine[good], s[good]


def _product_sums(ids_l, left, ids_r, right, many: int, shared: str):
    """Sums of products of all pairs at once, by dense slices of the elements."""
    import numpy as np

    of = {"product": lambda v: v, "magnitude": np.abs, "one": np.ones_like}[shared]

    sides = []
    for ids, (_, values, starts) in ((ids_l, left), (ids_r, right)):
        who = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
        order = np.argsort(ids, kind="stable")
        sides.append((ids[order], who[order], of(values)[order], len(starts) - 1))
    out = np.zeros((sides[0][3], sides[1][3]))
    step = max(1, SLICE // max(sides[0][3], sides[1][3]))
    for low in range(0, many, step):
        dense = []
        for ids, who, values, n in sides:
            a, b = np.searchsorted(ids, [low, low + step])
            slab = np.zeros((n, min(step, many - low)))
            slab[who[a:b], ids[a:b] - low] = values[a:b]
            dense.append(slab)
        out += dense[0] @ dense[1].T
    for low in range(0, len(out), 256):
        yield low, out[low : low + 256]
