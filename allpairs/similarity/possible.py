"""Entities that can be in a result at all, and who with, found before any list is made.

What two entities share starts at the rarest element that both hold.  From there on either must have enough left to reach the
threshold, so only the rarest elements of each need to meet, and of those that meet only pairs whose rests and totals allow
it count.  Entities connected by such meetings are near each other; a pair of a result is always among near entities.
Elements go as hashes of 32 bits in arrays, dealt by another part of the hash; elements of one hash are taken for one, which
can only bring more entities together.  No pair is shipped: a task gives only who belongs with whom.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, IntegerType, StructField, StructType

from ..graph.components import components
from ..measures import Measure
from ..model import positive
from ..scratch import written
from ..workers import ship

#: Rows that a task packs together.
PACKED_ROWS = 1 << 17
#: Bytes of the source, as Spark counts them, for each part of the hashes; a part is held by one task.
PART_BYTES = 1 << 22
MOST_PARTS = 1 << 14
#: Meetings of two entities at one element that are looked at together.
MEETINGS = 1 << 20
#: Entities near each other whose lists one task pairs; more are dealt to chunks, and each two chunks meet.
NEAR_ENTITIES = 1024
#: Near entities for each task that pairs lists.
TASK_ENTITIES = 1024
#: Entities whose group is told to every task.
MOST_BROADCAST = 1_000_000
#: Values this near the threshold are kept.
NEAR = 1e-6
#: What rows of near entities carry: their task, the group, the two chunks that meet, and the row's own.
KEYS, OWN = ("near_at", "near", "near_p", "near_q"), "near_own"


def applies(measure: Measure) -> bool:
    """Whether the value is made of one shared sum that no entity's total is below, and falls with the partner's total."""
    return measure.plain is not None and measure.plain[0] in ("least", "one") and measure.symmetric and not measure.distance and measure.least_ratio is not None


def parts_for(cells: DataFrame) -> int:
    size = int(cells._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return min(MOST_PARTS, max(8, -(-size // PART_BYTES)))


def groups(cells: DataFrame, measure: Measure, t: float, parts: int | None = None) -> DataFrame:
    """entity, near (the least entity of its group) and near_chunks, for every entity that may be in a pair.

    Rows are those of :func:`allpairs.model.normalize_raw`, each cell once.
    """
    ship(cells.sparkSession)
    many = parts_for(cells) if parts is None else parts
    kind, value = cells.schema["entity"].dataType, measure.plain[1]
    entities, binary = StructField("entities", ArrayType(kind)), lambda *names: [StructField(n, BinaryType()) for n in names]
    packed = StructType([StructField("part", IntegerType()), entities, *binary("buckets", "lengths", "hashes", "weights")])
    ranked = StructType([StructField("bucket", IntegerType()), StructField("part", IntegerType()), entities, *binary("wholes", "lengths", "hashes", "classes", "weights")])
    first = StructType([StructField("part", IntegerType()), entities, *binary("wholes", "lengths", "hashes", "rests")])
    edges = StructType([StructField("e1", kind), StructField("e2", kind)])

    def pack(batches):
        import pyarrow as pa

        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= PACKED_ROWS:
                yield _packed(pa.Table.from_batches(held))
                held, n = [], 0
        if n:
            yield _packed(pa.Table.from_batches(held))

    def rank(table):
        """How frequent each cell's element is, for cells of elements that somebody else has too; dealt by entity."""
        import numpy as np

        hashes, weights = _numbers(table, "hashes", np.int32), _numbers(table, "weights", np.float32)
        lengths, buckets = _numbers(table, "lengths", np.int32), _numbers(table, "buckets", np.int32)
        order = np.argsort(hashes, kind="stable")
        starts = np.flatnonzero(np.diff(hashes[order].astype(np.int64), prepend=1 << 40))
        freq = np.empty(len(hashes), np.int32)
        freq[order] = np.repeat(np.diff(starts, append=len(order)), np.diff(starts, append=len(order)))
        del order
        common = freq > 1
        begins = np.cumsum(lengths) - lengths
        wholes, kept = np.add.reduceat(weights.astype(float), begins), np.add.reduceat(common.astype(np.int32), begins)
        classes = np.minimum(np.log2(freq[common]) * 8, 255).astype(np.uint8)
        by = np.argsort(buckets, kind="stable")
        columns = {"wholes": wholes.astype(np.float32), "lengths": kept.astype(np.int32)}
        cells = {"hashes": hashes[common], "classes": classes, "weights": weights[common]}
        return _dealt(buckets, by, table["entities"].combine_chunks().flatten(), columns, cells, "bucket", {"part": table["part"][0].as_py()}, ranked)

    def prefix(table):
        """Cells at which a passing pair can first meet, with what the entity has left from there on."""
        import numpy as np

        codes = table["entities"].combine_chunks().flatten().dictionary_encode()
        runs, lengths = np.asarray(codes.indices), _numbers(table, "lengths", np.int32)
        n = np.bincount(runs, _numbers(table, "wholes", np.float32), len(codes.dictionary))
        part = np.repeat(np.asarray(table["part"]), [len(x.as_py()) // 4 for x in table["hashes"]])
        who, hashes, weights = np.repeat(runs, lengths), _numbers(table, "hashes", np.int32), _numbers(table, "weights", np.float32)
        order = np.lexsort((hashes, part, _numbers(table, "classes", np.uint8), who))[::-1]  # the most frequent first
        who, part, hashes, sums = who[order], part[order], hashes[order], np.cumsum(weights[order], dtype=float)
        begins = np.flatnonzero(np.diff(who, prepend=-1))
        rest = sums - np.repeat(np.concatenate([[0.0], sums])[begins], np.diff(begins, append=len(who)))
        with np.errstate(divide="ignore", invalid="ignore"):
            able = np.flatnonzero(value(rest, n[who], rest) >= t - NEAR)
        who, part, hashes, rest = who[able], part[able], hashes[able], rest[able]
        order = np.lexsort((who, part))
        who, part = who[order], part[order]
        starts = np.flatnonzero((np.diff(part, prepend=-1) != 0) | (np.diff(who, prepend=-1) != 0))
        columns = {"wholes": n[who[starts]].astype(np.float32), "lengths": np.diff(starts, append=len(who)).astype(np.int32)}
        return _dealt(part[starts], np.arange(len(starts)), _taken(codes.dictionary, who[starts]), columns, {"hashes": hashes[order], "rests": rest[order].astype(np.float32)}, "part", {}, first)

    def meet(table):
        import numpy as np
        import pyarrow as pa

        codes = table["entities"].combine_chunks().flatten().dictionary_encode()
        lengths = _numbers(table, "lengths", np.int32)
        own = np.asarray(codes.indices)
        n = np.zeros(len(codes.dictionary))
        n[own] = _numbers(table, "wholes", np.float32)
        hashes = _numbers(table, "hashes", np.int32)
        order = np.argsort(hashes, kind="stable")
        label = connected(hashes[order], np.repeat(own, lengths)[order], _numbers(table, "rests", np.float32)[order].astype(float), n, value, t)
        moved = np.flatnonzero(label != np.arange(len(label)))
        return pa.table([_taken(codes.dictionary, moved), _taken(codes.dictionary, label[moved])], names=["e1", "e2"])

    h = F.xxhash64("element")
    weight = F.lit(1.0) if measure.plain[0] == "one" else F.col("mult")
    rows = positive(cells).select("entity", F.pmod(h, F.lit(many)).cast("int").alias("part"), F.shiftright(h, 32).cast("int").alias("hash"), weight.cast("float").alias("weight"), F.pmod(F.xxhash64("entity"), F.lit(many)).cast("int").alias("bucket"))
    known = rows.mapInArrow(pack, packed).groupBy("part").applyInArrow(rank, ranked)
    met = known.groupBy("bucket").applyInArrow(prefix, first).groupBy("part").applyInArrow(meet, edges)
    found = written(components(written(met, "near"), lambda df: written(df, "stars")), "groups")
    sizes = found.groupBy("component").agg(F.ceil(F.count("*") / NEAR_ENTITIES).cast("int").alias("near_chunks"))
    return written(found.join(sizes, "component").select(F.col("node").alias("entity"), F.col("component").alias("near"), "near_chunks"), "near")


def possible(cells: DataFrame, measure: Measure, t: float, parts: int | None = None) -> DataFrame:
    """Rows of entities that may be in a pair."""
    return among(cells, groups(cells, measure, t, parts)) if applies(measure) else cells


def _told(near: DataFrame) -> DataFrame:
    return F.broadcast(near) if near.count() <= MOST_BROADCAST else near


def among(cells: DataFrame, near: DataFrame) -> DataFrame:
    """Rows of entities that may be in a pair; all rows of each, so that totals stay what they were."""
    return cells.join(_told(near.select("entity")), "entity", "left_semi").select(*cells.columns)


def dealt_near(joined: DataFrame, near: DataFrame) -> DataFrame:
    """Rows go to their group, those of a large one to each pair of chunks that theirs is in; whole lists of a group lie in one task."""
    own = joined.join(_told(near), "entity").withColumn(OWN, F.pmod(F.xxhash64("entity"), F.col("near_chunks")).cast("int"))
    other = own.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("near_chunks") - 1)))
    rows = other.select(*joined.columns, "near", F.least(OWN, "_other").alias("near_p"), F.greatest(OWN, "_other").alias("near_q"), OWN)
    tasks = max(int(joined.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-near.count() // TASK_ENTITIES))
    # lists of a join by the element as well would be moved once more, were they not dealt by their task's number
    return rows.withColumn("near_at", F.pmod(F.xxhash64(*KEYS[1:]), F.lit(tasks)).cast("int")).repartitionById(tasks, F.col("near_at"))


def connected(hashes, who, rest, n, value, t: float):
    """The least number of each entity's group; cells are in order of their hashes."""
    import numpy as np

    label = np.arange(len(n))
    at = 0
    while at < len(hashes):
        starts = np.flatnonzero(np.diff(hashes.astype(np.int64), prepend=1 << 40))
        sizes = np.diff(starts, append=len(hashes))
        mine = label[who]
        open_ = np.repeat(np.minimum.reduceat(mine, starts) != np.maximum.reduceat(mine, starts), sizes)
        open_[:at] = False  # what has met everyone already may still be met by those before it only
        after = np.repeat(starts + sizes, sizes) - np.arange(len(hashes)) - 1
        ends = np.cumsum(np.where(open_, after, 0))
        stop = max(at + 1, int(np.searchsorted(ends, MEETINGS, "right")))
        k = np.repeat(np.arange(at, stop), np.where(open_, after, 0)[at:stop])
        begin = ends - np.where(open_, after, 0)
        m = np.arange(len(k)) - begin[k] + k + 1
        i, j = who[k], who[m]
        apart = label[i] != label[j]
        k, m, i, j = k[apart], m[apart], i[apart], j[apart]
        with np.errstate(divide="ignore", invalid="ignore"):
            good = value(np.minimum(rest[k], rest[m]), n[i], n[j]) >= t - NEAR
        i, j = i[good], j[good]
        while len(i):
            a, b = label[i], label[j]
            np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
            while (label[label] != label).any():
                label = label[label]
            differ = label[i] != label[j]
            i, j = i[differ], j[differ]
        at = stop
    return label


def _numbers(table, name: str, kind):
    import numpy as np

    return np.frombuffer(b"".join(x.as_py() for x in table[name]), kind)


def _taken(dictionary, codes):
    import pyarrow as pa

    return dictionary.take(pa.array(codes, pa.int64()))


def _dealt(places, order, entities, columns: dict, cells: dict, name: str, fixed: dict, schema: StructType):
    """A row for each place: its runs of cells, each an entity's, with the arrays as bytes."""
    import numpy as np
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema

    lengths = columns["lengths"]
    begins = np.cumsum(lengths) - lengths
    size = lengths[order]
    at = np.repeat(begins[order] - (np.cumsum(size) - size), size) + np.arange(size.sum())
    cells = {c: x[at] for c, x in cells.items()}
    columns = {c: x[order] for c, x in columns.items()}
    places, entities = places[order], _taken(entities, order)
    firsts = np.flatnonzero(np.diff(places, prepend=-1))
    runs = np.append(firsts, len(places))
    ends = np.concatenate([[0], np.cumsum(size)])[runs]
    out = {name: pa.array(places[firsts].astype(np.int32)), "entities": pa.ListArray.from_arrays(pa.array(runs.astype(np.int32)), entities)}
    out |= {c: pa.array([v] * len(firsts), pa.int32()) for c, v in fixed.items()}
    out |= {c: pa.array([x[a:b].tobytes() for a, b in zip(runs[:-1], runs[1:])], pa.binary()) for c, x in columns.items()}
    out |= {c: pa.array([x[a:b].tobytes() for a, b in zip(ends[:-1], ends[1:])], pa.binary()) for c, x in cells.items()}
    return pa.table([out[f.name] for f in schema], schema=to_arrow_schema(schema))


def _packed(table):
    """One row for each part: its entities, how many cells each has there, and these cells' hashes and weights."""
    import numpy as np
    import pyarrow as pa

    codes = table["entity"].combine_chunks().dictionary_encode()
    who, part, hashes, weights, buckets = np.asarray(codes.indices), *(np.asarray(table[c]) for c in ("part", "hash", "weight", "bucket"))
    order = np.lexsort((who, part))
    who, part, hashes, weights, buckets = who[order], part[order], hashes[order], weights[order], buckets[order]
    starts = np.flatnonzero((np.diff(part, prepend=-1) != 0) | (np.diff(who, prepend=-1) != 0))  # an entity in a part
    firsts = np.flatnonzero(np.diff(part, prepend=-1))
    runs, ends = np.append(np.searchsorted(starts, firsts), len(starts)), np.append(firsts, len(part))
    lengths = np.diff(starts, append=len(who)).astype(np.int32)
    split = lambda x, cuts: pa.array([x[a:b].tobytes() for a, b in zip(cuts[:-1], cuts[1:])], pa.binary())
    entities = pa.ListArray.from_arrays(pa.array(runs.astype(np.int32)), _taken(codes.dictionary, who[starts]))
    columns = [pa.array(part[firsts]), entities, split(buckets[starts].astype(np.int32), runs), split(lengths, runs), split(hashes.astype(np.int32), ends), split(weights.astype(np.float32), ends)]
    return pa.RecordBatch.from_arrays(columns, ["part", "entities", "buckets", "lengths", "hashes", "weights"])
