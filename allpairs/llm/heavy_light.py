"""Exact Jaccard join of word-shingle sets: subsets for light sets, inverted lists for heavy ones.

Equal sets are joined first by a 128-bit digest of the set, so a group of copies is one set from
there on.  Two sets of n <= m shingles link if they share c(n, m) of them.  Sets of at most
``boundary`` shingles are light: each lists its subsets of size c for every size it may link with,
and light sets link through a common subset.  All other pairs meet in inverted lists, which hold a
set under its rarest shingles only: a set can lack at most d(n) of its shingles in one it links with,
so d + 1 of them suffice, and if that many are in no other set it links with none.  The boundary is
where the number of subsets plus the weighted number of list entries, taken from the counts of small
sizes, is least.

Rarity is counted three times, so that few rows move: over all sets for a hash-chosen part of the
shingles, which settles most sets (one with more than d of these to itself links with none); over all
shingles of the sets that are left; and again inside each cluster of sets that lists connect.

A list isn't multiplied out.  First its sets are compared with one centre (the one with fewest
shingles of its own); then only pairs of the list that are still in different components are.  So a
large group of near copies costs about its size, and no link between components goes unseen.  If
links are to be counted too, all pairs of sets of a component are verified afterwards, in blocks; that
costs the square of a component's sets, and components alone don't need it.

Texts without words link with nothing.  Each distinct set has a number of its own, which all joins and
components use; ids only come back at the end.  So rows with a null or repeated id are documents of
their own: they share a component only if their texts do.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial
from itertools import combinations
from math import comb

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from allpairs.graph.components import components

from .common import columns_of, forget, id_and_text, keep, ship, size_bounded_batches, spread_join, unused
from .shingles import mixed, shingle_sets

#: The first count of rarity looks at a part of all shingles: one and a half times what a set may lack, and half of this many 256ths.
LOWEST_SHARE = 26
#: What an entry of an inverted list costs against a listed subset, with the comparisons it brings.
ENTRY_COST = 8
#: Subsets are never cheaper for sets larger than this.
MOST_LIGHT = 40
BITMAP_WORDS = 8
#: Sets of a component are compared in blocks of about this many, a block with a block in one task; each set moves once a block.
BLOCK = 1024
#: And of about this many shingles, if the sets are large.
BLOCK_SHINGLES = 1 << 20
#: Rows of a list that are paired with each other in one task; longer lists are dealt in blocks.
LIST_BLOCK = 2048
#: Bits for each row that a bitmap of rows tells, and the width of the longest bitmap's places; beyond, more rows pass it.
BITS_A_ROW = 16
WIDEST = 27


@dataclass(frozen=True)
class Similarity:
    """Jaccard similarity of at least num / den, in whole numbers."""

    num: int
    den: int

    def least_size(self, n):
        return -(-self.num * n // self.den)

    def shared(self, n, m):
        """The least intersection of sets of n and m elements that link."""
        return -(-self.num * (n + m) // (self.num + self.den))

    # the same as columns
    def lacks(self, n: Column) -> Column:
        return n - _ceil(n * self.num, self.den)

    def needs(self, n: Column, m: Column) -> Column:
        return _ceil((n + m) * self.num, self.num + self.den)


def _ceil(x: Column, y: int) -> Column:
    up = x + (y - 1)
    return ((up - F.pmod(up, F.lit(y))) / y).cast("long")


def _sets(docs: DataFrame, k: int, share: int | None, counts_only: bool = False, once: bool = False) -> DataFrame:
    """row, doc_id, n, two digests, the chosen part of each document's shingles (all if share is None; left empty if only counts are wanted) and its size.

    ``once`` leaves out rows that repeat one the task has just seen, so a large group of equal rows is one row a task.
    """

    def made(batches: Iterator) -> Iterator:
        import pyarrow as pa

        seen: set[bytes] = set()
        for batch in size_bounded_batches(batches, 1, 1 << 20):
            if once:
                digests = batch.column(0).to_pylist()
                fresh = []
                for d in digests:
                    fresh.append(d not in seen)
                    seen.add(d)
                if not all(fresh):
                    batch = batch.filter(pa.array(fresh))
                if len(seen) > 1 << 17:
                    seen.clear()
            sets = shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), k)
            part = sets if share is None else [x[: np.searchsorted(x, np.uint64(share << 56))] for x in sets] if share < 256 else sets
            one = np.array([x.sum(dtype=np.uint64) for x in sets], np.uint64).view(np.int64)
            two = np.array([mixed(x ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64) for x in sets], np.uint64).view(np.int64)
            of = [len(x) for x in part]
            if counts_only:
                part = [x[:0] for x in part]
            bits = np.concatenate([toggled(x) for x in sets]) if share is None and sets else np.zeros(BITMAP_WORDS * len(sets), np.int64)
            flat = np.concatenate(part).view(np.int64) if part else np.empty(0, np.int64)
            offsets = np.cumsum([0, *map(len, part)], dtype=np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([len(x) for x in sets], pa.int64()), pa.array(one), pa.array(two), pa.array(of, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)), pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * BITMAP_WORDS), pa.array(bits))], ["row", "doc_id", "n", "one", "two", "of", "part", "bits"])

    return docs.select("row", "text", "doc_id").mapInArrow(made, "row binary, doc_id long, n long, one long, two long, of long, part array<long>, bits array<long>")


def _perhaps_among(rows: DataFrame, some: DataFrame) -> DataFrame:
    """Rows whose ``row`` may be one of ``some``: all that are, and about one in BITS_A_ROW of the others.  A bitmap is told to every task, so texts stay where they are."""
    width = min(WIDEST, max(6, (BITS_A_ROW * some.count() - 1).bit_length()))
    place = F.xxhash64("row").bitwiseAND((1 << width) - 1)
    words = some.select(F.shiftright(place, 6).alias("word"), place.bitwiseAND(63).alias("bit")).groupBy("word").agg(F.expr("bit_or(shiftleft(1L, cast(bit as int)))").alias("told"))
    near = rows.withColumn("word", F.shiftright(place, 6)).withColumn("bit", place.bitwiseAND(63)).join(F.broadcast(words), "word")
    return near.filter("shiftright(told, cast(bit as int)) & 1 = 1").select(*rows.columns)


def toggled(elements: np.ndarray) -> np.ndarray:
    """A bitmap in which each element toggles one bit: two bitmaps differ in no more bits than their sets do in elements."""
    odd = np.bincount((elements & np.uint64(64 * BITMAP_WORDS - 1)).astype(np.int64), minlength=64 * BITMAP_WORDS) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8")


def subsets_listed(n: int, boundary: int, similar: Similarity) -> dict[tuple[int, int], int]:
    """For the size pairs (n', m') a light set of n takes part in: the size of the subsets it lists."""
    pairs = {(min(n, m), max(n, m)) for m in range(similar.least_size(n), boundary + 1) if similar.least_size(max(n, m)) <= min(n, m)}
    return {(a, b): similar.shared(a, b) for a, b in pairs if similar.shared(a, b) <= n}


def choose_boundary(sizes: dict[int, int], similar: Similarity) -> int:
    """The size up to which listing subsets costs less than list entries; 0 if it never does."""

    def cost(boundary: int) -> int:
        total = 0
        for n, count in sizes.items():
            if n <= boundary:
                total += count * sum(comb(n, c) for c in subsets_listed(n, boundary, similar).values())
            if n > boundary or n >= similar.least_size(boundary + 1):
                total += count * ENTRY_COST * (n - similar.least_size(n) + 1)
        return total

    return min(range(MOST_LIGHT + 1), key=lambda b: (cost(b), b))


def _subset_keys(light: DataFrame, boundary: int, similar: Similarity) -> DataFrame:
    def listed(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in (b.slice(at, 512) for b in batches for at in range(0, b.num_rows, 512)):
            ids, sizes, keys = [], [], []
            for set_id, n, elements in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                x = np.array(elements, np.int64).view(np.uint64)
                for (a, b), c in subsets_listed(n, boundary, similar).items():
                    left_out = np.array(list(combinations(range(n), n - c)), np.int64).reshape(comb(n, c), n - c)
                    sums = mixed(x).sum(dtype=np.uint64) - mixed(x)[left_out].sum(1, dtype=np.uint64)
                    key = np.unique(mixed(sums + np.uint64(a << 32 | b)))
                    keys.append(key.view(np.int64))
                    ids += [set_id] * len(key)
                    sizes += [n] * len(key)
            flat = np.concatenate(keys) if keys else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(flat), pa.array(ids, pa.int64()), pa.array(sizes, pa.int64())], ["key", "set_id", "n"])

    return light.select("set_id", "n", "elements").mapInArrow(listed, "key long, set_id long, n long")


def _counted(elements: DataFrame, *within: str) -> DataFrame:
    """Rows (e, set_id, ...) that share their shingle with another set, and in how many it is; a hot shingle has a row a set, three numbers wide, and its window spills."""
    return elements.withColumn("f", F.count("*").over(Window.partitionBy(*within, "e"))).filter("f > 1")


def _entries(full: DataFrame, own: Column, name: str) -> DataFrame:
    """cluster, key, set_id, n, u: each set under its rarest shared shingles, as many as it needs besides the u that only it has."""
    shared = _counted(full.select("cluster", "set_id", "n", F.explode("elements").alias("e")), "cluster")
    of_set = Window.partitionBy("set_id", "n")
    ranked = shared.withColumn("u", F.col("n") - F.count("*").over(of_set)).withColumn("rank", F.row_number().over(of_set.orderBy("f", "e")))
    return keep(ranked.filter(F.col("rank") <= own - F.col("u")).select("cluster", F.col("e").alias("key"), "set_id", "n", "u"), name)


def _verified(pairs: DataFrame, full: DataFrame, similar: Similarity) -> DataFrame:
    left, right = (full.select(F.col("set_id").alias(c), F.col("elements").alias(f"x{c}")) for c in ("a", "b"))
    met = pairs.join(left, "a").join(right, "b")
    shared, total = F.size(F.array_intersect("xa", "xb")), F.size("xa") + F.size("xb")
    return met.filter(shared * similar.den >= (total - shared) * similar.num).select("a", "b")


_LIST = ["light", "cluster", "key"]
_MEMBER = ["set_id", "n", "u", "bits"]


def _may_link(boundary: int, similar: Similarity) -> Column:
    """Whether two sets of a list may link: sizes fit, each lacks few enough of its own shingles, their bitmaps differ in few enough bits, and the path is the one for their sizes."""
    low, high = F.least("n", "n2"), F.greatest("n", "n2")
    needs = similar.needs(F.col("n"), F.col("n2"))
    may = (low * similar.den >= high * similar.num) & (F.least(F.col("n") - F.col("u"), F.col("n2") - F.col("u2")) >= needs)
    differ = sum((F.bit_count(F.col("bits")[k].bitwiseXOR(F.col("bits2")[k])) for k in range(BITMAP_WORDS)), F.lit(0))
    return may & (differ <= F.col("n") + F.col("n2") - 2 * needs) & (F.col("light") == (high <= boundary))


def _second(rows: DataFrame, *more: str) -> DataFrame:
    return rows.select(*_LIST, *more, *(F.col(c).alias(f"{c}2") for c in _MEMBER))


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("set_id", "set_id2").alias("a"), F.greatest("set_id", "set_id2").alias("b")).distinct()


def _centre_pairs(lists: DataFrame, full: DataFrame, boundary: int, similar: Similarity) -> DataFrame:
    """Each list's sets with its centre, the one with fewest shingles of its own."""
    centres = lists.groupBy(*_LIST).agg(F.min(F.struct("u", "set_id", "n")).alias("c"), F.count("*").alias("size")).filter("size > 1").select(*_LIST, "size", "c.*")
    centres = keep(centres.join(full.select("set_id", "n", "bits"), ["set_id", "n"]), "centres")
    met = spread_join(lists.select(*_LIST, *_MEMBER), _second(centres, "size"), _LIST, "size")
    return _ordered(met.filter((F.col("set_id") != F.col("set_id2")) & _may_link(boundary, similar)))


def _cross_pairs(named: DataFrame, boundary: int, similar: Similarity) -> DataFrame:
    """Pairs of a list whose sets are in different components; long lists are dealt in blocks, a block with a block in one task."""
    lists = keep(named.groupBy(*_LIST).agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("size")).filter("lo < hi").select(*_LIST, "size"), "mixed_lists")
    rows = spread_join(named, lists, _LIST, "size").withColumn("blocks", F.ceil(F.col("size") / LIST_BLOCK).cast("long"))
    own = rows.withColumn("own", F.pmod(F.xxhash64("set_id"), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = own.select(*_LIST, *_MEMBER, "label", "own", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"))
    second = _second(dealt, "p", "q", F.col("label").alias("label2"), F.col("own").alias("own2"))
    met = dealt.join(second, [*_LIST, "p", "q"])
    apart = (F.col("set_id") < F.col("set_id2")) & (F.col("label") != F.col("label2")) & ((F.col("p") == F.col("q")) | (F.col("own") != F.col("own2")))
    return _ordered(met.filter(apart & _may_link(boundary, similar)))


def intersections(left: list[np.ndarray], right: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """How many elements each set of ``left`` shares with each of ``right``, by products of 0-1 matrices of ``width`` elements at a time."""
    out = np.zeros((len(left), len(right)), np.int64)
    flat = [np.concatenate(x) for x in (left, right)]
    common = np.intersect1d(*flat)
    places = []
    for sets, x in zip((left, right), flat, strict=True):
        owner, at = np.repeat(np.arange(len(sets)), [len(e) for e in sets]), np.searchsorted(common, x)
        real = np.zeros(len(x), bool) if not len(common) else common[np.minimum(at, len(common) - 1)] == x
        order = np.argsort(at[real], kind="stable")
        places.append((owner[real][order], at[real][order]))
    for begin in range(0, len(common), width):
        part = []
        for sets, (owner, at) in zip((left, right), places, strict=True):
            s, e = np.searchsorted(at, [begin, begin + width])
            cells = np.zeros((len(sets), min(width, len(common) - begin)), np.float32)
            cells[owner[s:e], at[s:e] - begin] = 1
            part.append(cells)
        out += (part[0] @ part[1].T).astype(np.int64)
    return out


def _links_inside(members: DataFrame, full: DataFrame, similar: Similarity) -> DataFrame:
    """set_id and linked, the number of documents of other sets that each links with: every pair of a component is verified, in blocks."""
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("long")
    sizes = keep(members.groupBy("component").agg(blocks.alias("blocks"), F.count("*").alias("size")), "component_sizes")
    placed = spread_join(members.select("set_id", "component", "copies"), sizes, ["component"], "size").withColumn("own", F.pmod(F.xxhash64("set_id"), F.col("blocks")))
    met = placed.join(full.select("set_id", "elements"), "set_id").withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = met.select("component", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own", "set_id", "copies", "elements")

    def verified(key, table):
        import pyarrow as pa

        lo, hi = key[1].as_py(), key[2].as_py()
        own, ids, copies = (table.column(c).to_numpy() for c in ("own", "set_id", "copies"))
        column = table.column("elements").combine_chunks()
        ends = np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False))])
        flat = column.flatten().to_numpy()
        sets = [flat[s:e] for s, e in zip(ends[:-1], ends[1:], strict=True)]
        a, b = np.flatnonzero(own == lo), np.flatnonzero(own == hi)
        linked = np.zeros(len(ids), np.int64)
        if len(a) and len(b):
            n = np.array([len(x) for x in sets], np.int64)
            shared = intersections([sets[i] for i in a], [sets[i] for i in b])
            link = (shared * similar.den >= (n[a][:, None] + n[b][None, :] - shared) * similar.num) & (ids[a][:, None] != ids[b][None, :])
            linked[a] += link @ copies[b]
            if lo != hi:
                linked[b] += copies[a] @ link
        return pa.table({"set_id": pa.array(ids), "linked": pa.array(linked)})

    return keep(dealt.groupBy("component", "lo", "hi").applyInArrow(verified, "set_id long, linked long"), "block_links").groupBy("set_id").agg(F.sum("linked").alias("linked"))


def _row(id_col: str, text: Column) -> Column:
    return F.unhex(F.md5(F.concat(F.coalesce(F.col(id_col).cast("long").cast("string"), F.lit("")), F.lit(":"), text)))


def _by_id(id_col: str) -> Column:
    """What the least of is the row with the least id; rows without one come last."""
    return F.struct(F.col(id_col).isNull().alias("without"), F.col(id_col).alias("id"), F.col("row").alias("row"))


def sets_and_components(docs: DataFrame, k: int = 5, similar: Similarity = Similarity(4, 5), id_col: str = "doc_id", text_col: str = "text", boundary: int | None = None, links: bool = False) -> tuple[DataFrame, DataFrame]:
    """Every row (row, doc_id, n, its set's digests; ``row`` is a digest of its id and text), and every set: digests, set_id, component (the least set_id it reaches by links), its least id and the row that has it; with ``links`` also n_links of each of its documents."""
    spark = docs.sparkSession
    ship(spark)
    rows = id_and_text(docs, id_col, text_col).withColumn("doc_id", F.col("doc_id").cast("long"))
    rows = rows.withColumn("row", _row("doc_id", F.col("text")))
    share = min(256, max(LOWEST_SHARE, 256 * 3 * (similar.den - similar.num) // (2 * similar.den) + LOWEST_SHARE // 2))
    digest = ["n", "one", "two"]
    narrow = keep(_sets(rows, k, share, counts_only=True).select("row", "doc_id", *digest), "set_digests")
    groups = keep(narrow.filter("n > 0").groupBy(*digest).agg(F.min(_by_id("doc_id")).alias("best"), F.count("*").alias("copies")).select(*digest, "copies", F.col("best.id").alias("least_id"), "best.row", F.monotonically_increasing_id().alias("set_id")), "set_groups")

    # shingles are made a second time rather than kept: they take more room than the texts
    own = F.lit(1) + similar.lacks(F.col("n"))
    chosen = _sets(rows, k, share, once=True).select("row", *digest, "part").join(groups, ["row", *digest]).select("set_id", F.explode("part").alias("e"))
    # rows with one id and one text are told apart by nothing, so a shingle of one set is one whose least and greatest set are the same
    seen = chosen.groupBy("e").agg(F.min("set_id").alias("set_id"), F.max("set_id").alias("other")).filter("set_id = other").groupBy("set_id").agg(F.count("*").alias("u"))
    left_over = keep(groups.join(seen, "set_id", "left").filter(F.coalesce("u", F.lit(0)) < own).select("set_id", "row", *digest), "left_over")

    again = _perhaps_among(rows, left_over)
    # a set has one row here, so where rows met they are told apart without another move
    met = _sets(again, k, None, once=True).join(left_over, ["row", *digest]).dropDuplicates(["row", *digest, "set_id"])
    full = keep(met.select("set_id", "n", F.col("part").alias("elements"), "bits"), "full_sets")
    if boundary is None:
        small = full.filter(F.col("n") <= MOST_LIGHT).groupBy("n").count().collect()
        boundary = choose_boundary({r["n"]: r["count"] for r in small}, similar)

    first = _entries(full.withColumn("cluster", F.lit(0).cast("long")), own, "entries_first")
    # sets that share no list can't link, so rarity may be counted again inside each cluster of lists: what is shared by accident only is then rare
    least = keep(first.groupBy("cluster", "key").agg(F.min("set_id").alias("b"), F.count("*").alias("size")).filter("size > 1"), "least_of_lists")
    edges = spread_join(first, least, ["cluster", "key"], "size").filter("set_id <> b").select(F.col("set_id").alias("a"), "b").distinct()
    clusters = keep(components(edges, partial(keep, name="clusters"), "a", "b").select(F.col("node").alias("set_id"), F.col("component").alias("cluster")).distinct(), "clustered")
    forget(first)
    entries = _entries(full.join(clusters, "set_id"), own, "entries")
    listed = _subset_keys(full.filter(F.col("n") <= boundary), boundary, similar).select(F.lit(0).cast("long").alias("cluster"), "key", "set_id", "n", F.lit(0).cast("long").alias("u"), F.lit(True).alias("light"))
    lists = keep(entries.withColumn("light", F.lit(False)).unionByName(listed).join(full.select("set_id", "n", "bits"), ["set_id", "n"]), "lists")

    tried = keep(_centre_pairs(lists, full, boundary, similar), "centre_pairs")
    found = keep(_verified(tried, full, similar), "centre_links")
    hold = partial(keep, name="stars")
    labels = components(found, hold, "a", "b")
    named = keep(lists.join(labels.withColumnRenamed("node", "set_id"), "set_id", "left").withColumn("label", F.coalesce("component", "set_id")).drop("component"), "named_lists")
    rest = keep(_cross_pairs(named, boundary, similar).join(tried, ["a", "b"], "left_anti"), "cross_pairs")
    more = keep(_verified(rest, full, similar), "cross_links")
    labels = keep(components(found.unionByName(more), hold, "a", "b"), "components")

    sets = groups.join(labels.withColumnRenamed("node", "set_id"), "set_id", "left").withColumn("component", F.coalesce("component", "set_id"))
    if links:
        linked = _links_inside(sets.join(labels.withColumnRenamed("node", "set_id").select("set_id"), "set_id", "left_semi"), full, similar)
        sets = sets.join(linked, "set_id", "left").withColumn("n_links", F.col("copies") - 1 + F.coalesce("linked", F.lit(0))).drop("linked")
    return narrow, keep(sets, "sets")


def join(docs: DataFrame, k: int = 5, similar: Similarity = Similarity(4, 5), id_col: str = "doc_id", text_col: str = "text", boundary: int | None = None, links: bool = False) -> DataFrame:
    """doc_id, n_shingles, component_id (the least id it reaches by links, itself included; null if none of them has an id) of every row; with ``links`` also n_links, the number of other rows it links with."""
    narrow, sets = sets_and_components(docs, k, similar, id_col, text_col, boundary, links)
    counts = ["n_links"] if links else []
    least = sets.groupBy("component").agg(F.min("least_id").alias("component_id"))
    named = keep(sets.join(least, "component").select("n", "one", "two", "copies", F.lit(True).alias("worded"), "component_id", *counts), "named_sets")
    placed = spread_join(narrow, named, ["n", "one", "two"], "copies", "left")
    return placed.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("worded"), F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"), *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in counts))


def without_near_copies(docs: DataFrame, k: int = 5, similar: Similarity = Similarity(4, 5), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component, that of its least id (one without an id only if none has one), and every row without words.

    Of rows with one id and one text any one stays.  All columns of ``docs`` come back as they were.
    """
    narrow, sets = sets_and_components(docs, k, similar, id_col, text_col)
    first = sets.groupBy("component").agg(F.min(_by_id("least_id")).alias("best")).select("best.row")
    row, size = unused(docs, "row", "size")
    stay = keep(narrow.groupBy("row").agg(F.count("*").alias(size)).join(first, "row").withColumnRenamed("row", row), "rows_that_stay")
    text = F.coalesce(F.col(text_col), F.lit(""))
    worded = F.rlike(text, F.lit(r"[^\x20\x09-\x0D]"))
    kept = spread_join(docs.filter(worded).withColumn(row, _row(id_col, text)), stay, [row], size)
    # rows with one id and one text are one copy group; of each task's one goes on
    single = kept.groupBy(row).agg(F.first(F.struct(*columns_of(docs))).alias(size)).select(f"{size}.*")
    return docs.filter(~worded).unionByName(single)
