"""Canonical exact digests of documents, in DataFrame functions only.

A text is brought to a canonical form (compatibility composition, full case folding, white space
folded to single blanks), hashed to 128 bits, and compared byte for byte with the other texts of
its hash bucket: the least and the greatest canonical text of a bucket are the same if all are, and
both are found task by task before anything moves.  Should two different canonical texts ever meet in
one bucket, all of that bucket get a 256-bit digest of the canonical bytes after the 128 bits.  Two
texts have the same fingerprint exactly if their canonical forms are equal, so the likeness of two
fingerprints is 1 or 0.  The edited text of a row is compared with the row's own text in place.

Nulls: null text is the empty text; a null id sorts first.  Empty tables give empty results.
Repeated rows have equal fingerprints; rows with one id come in the order of their texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import id_and_text, keep, spread_join

#: Rows that meet in one window partition, about.
BUCKET_ROWS = 2048
#: Ranges of ids are cut in two steps, each into at most so many; ranges of one id are not cut.
MOST_CUTS = 4096
_UNICODE = "com.ibm.icu.text.Normalizer", "com.ibm.icu.lang.UCharacter"


def canonical(text: Column) -> Column:
    """ASCII takes the short way, which gives the same: lower case, then white space."""
    composed = F.reflect(F.lit(_UNICODE[0]), F.lit("compose"), text, F.lit(True))
    folded = F.reflect(F.lit(_UNICODE[1]), F.lit("foldCase"), composed, F.lit(True))
    again = F.reflect(F.lit(_UNICODE[0]), F.lit("compose"), folded, F.lit(True))
    plain = F.octet_length(text) == F.length(text)
    return F.trim(F.regexp_replace(F.when(plain, F.lower(text)).otherwise(again), r"[\s\x1c-\x1f\x85\p{Z}]+", " "))


def digest(canon: Column) -> Column:
    """128 bits: two xxhash64 with different first values, as hexadecimal."""
    return F.lower(F.concat(*(F.lpad(F.hex(F.xxhash64(F.lit(k), canon)), 16, "0") for k in (1, 2))))


def _cuts(rows: int) -> list[float]:
    n = min(MOST_CUTS, rows // BUCKET_ROWS + 1)
    return [k / n for k in range(1, n)]


def _place_among(id_: Column, bounds: Column) -> Column:
    """How many of the ascending bounds are at or below the id; a null id is below all."""
    return F.greatest(F.coalesce(F.size(F.filter(bounds, lambda x: x <= id_)), F.lit(0)), F.lit(0)).cast("long")


def _among(id_: Column, bounds: list[int]) -> Column:
    """The same for bounds known beforehand, by a two-level search."""
    if not bounds:
        return F.lit(0).cast("long")
    step = max(1, int(len(bounds) ** 0.5))
    rows = [bounds[k : k + step] for k in range(0, len(bounds), step)]
    which = _place_among(id_, F.array(*(F.lit(r[0]).cast("long") for r in rows)))
    at = F.element_at(F.array(*(F.array(*(F.lit(v).cast("long") for v in r)) for r in rows)), F.greatest(which, F.lit(1)).cast("int"))
    return F.when(which > 0, (which - 1) * step + _place_among(id_, at)).otherwise(0).cast("long")


def _placed(docs: DataFrame) -> DataFrame:
    """Adds _bucket: the place of the row's id among ranges of about BUCKET_ROWS rows, in id order.

    At most MOST_CUTS ranges are cut first; each that is still too long is cut once more, by bounds of its own,
    which are broadcast: at most MOST_CUTS rows of an array.
    """
    rows = docs.count()
    points = _cuts(rows)
    bounds = sorted(set(docs.select(F.percentile_approx("doc_id", points, 20 * len(points)).alias("p")).first()["p"] or [])) if points else []
    first = docs.withColumn("_bucket", _among(F.col("doc_id"), bounds))
    inner = _cuts(rows // (len(points) + 1))
    if len(points) + 1 < MOST_CUTS or not inner:
        return first
    finer = keep(first.groupBy("_bucket").agg(F.array_distinct(F.percentile_approx("doc_id", inner, 20 * len(inner))).alias("_inner")), "inner_bounds")
    return first.join(F.broadcast(finer), "_bucket").withColumn("_bucket", F.col("_bucket") * MOST_CUTS + _place_among(F.col("doc_id"), F.col("_inner"))).drop("_inner")


def with_next(docs: DataFrame, *carry: str) -> DataFrame:
    """Adds next_text and next_<carry>: those of the following row in id order, for the last row of the first.

    The table is cut into id ranges; the first row of each range also stands, as a sentinel, at the
    end of the range before, so no window spans all rows.
    """
    placed = _placed(docs)
    firsts = keep(placed.groupBy("_bucket").agg(F.min(F.struct(F.col("doc_id").isNotNull().alias("k"), F.col("doc_id").alias("v"))).getField("v").alias("_first")), "range_starts")
    # one row a range: the one before each, and the last one before the first
    order = Window.orderBy("_bucket")
    last = F.max("_bucket").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    starts = firsts.select(F.col("_first"), F.coalesce(F.lag("_bucket").over(order), last).alias("_before"))
    heads = docs.join(starts, F.col("doc_id").eqNullSafe(F.col("_first")))
    heads = heads.groupBy("_before", "_first").agg(F.min(F.struct("text", *carry)).alias("_head")).select(F.col("_before").alias("_bucket"), F.col("_first").alias("doc_id"), "_head.*")
    rows = placed.select("doc_id", "text", *carry, "_bucket", F.lit(0).alias("_head")).unionByName(heads.withColumn("_head", F.lit(1)))
    order = Window.partitionBy("_bucket").orderBy("_head", F.col("doc_id").asc_nulls_first(), "text")
    ahead = [F.lead(c).over(order).alias(f"next_{c}") for c in ("text", *carry)]
    return rows.select("*", *ahead).filter("_head = 0").drop("_head", "_bucket")


def _named(key: Column, canon: Column, clashes: DataFrame | None, known: str = "_clash") -> Column:
    """The digest itself, or with that of the bytes behind it where different texts share a bucket."""
    return key if clashes is None else F.when(F.col(known), F.concat(key, F.lit("-"), F.sha2(canon, 256))).otherwise(key)


def _clash_marked(rows: DataFrame, key: str, clashes: DataFrame | None) -> DataFrame:
    if clashes is None:
        return rows
    return rows.join(clashes.select(F.col("key").alias(key), F.lit(True).alias("_clash")), key, "left").withColumn("_clash", F.coalesce("_clash", F.lit(False)))


def _clashing(rows: DataFrame, narrow: DataFrame, wide) -> DataFrame | None:
    """key of every hash bucket that holds different canonical texts; None if there is none."""
    shared = keep(narrow.groupBy(F.col("fp").alias("key")).agg(F.count("*").alias("size")).filter("size > 1"), "shared_keys")
    texts = rows.select(canonical(F.col("text")).alias("canon")).select(wide(F.col("canon")).alias("key"), "canon")
    met = spread_join(texts, shared, ["key"], "size")
    clashes = keep(met.groupBy("key").agg(F.min("canon").alias("lo"), F.max("canon").alias("hi")).filter("lo <> hi").select("key"), "clashes")
    return None if clashes.isEmpty() else clashes


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", wide=digest) -> DataFrame:
    """doc_id, n_chars, fp, next_fp, edited_sha256 and edited_fp of every row.

    The edited text is the row's with its last quarter replaced by the next row's beginning.
    ``wide`` is the hash whose buckets are compared byte by byte.
    """
    rows = id_and_text(docs, id_col, text_col)

    def all_of(clashes: DataFrame | None) -> DataFrame:
        hashed = _clash_marked(rows.withColumn("_canon", canonical(F.col("text"))).withColumn("key", wide(F.col("_canon"))), "key", clashes)
        marked = with_next(hashed.select("doc_id", "text", _named(F.col("key"), F.col("_canon"), clashes).alias("fp")), "fp")
        n = F.length("text")
        quarter = F.floor(n / 4).cast("int")
        edited = F.concat(F.substring("text", F.lit(1), n - quarter), F.substring("next_text", F.lit(1), quarter))
        changed = marked.select("doc_id", "text", n.cast("long").alias("n_chars"), "fp", "next_fp", edited.alias("edited"))
        canon = changed.withColumn("edited_sha256", F.sha2("edited", 256)).withColumn("_canon", canonical(F.col("edited"))).withColumn("_key", wide(F.col("_canon")))
        named = _clash_marked(canon, "_key", clashes).withColumn("edited_fp", _named(F.col("_key"), F.col("_canon"), clashes))
        # where only the hashes are equal, bytes tell the edited text from the row's own
        other = (F.col("edited_fp") == F.col("fp")) & (F.col("edited") != F.col("text")) & (canonical(F.col("text")) != F.col("_canon"))
        apart = F.when(other, F.concat("_key", F.lit("-"), F.sha2("_canon", 256))).otherwise(F.col("edited_fp"))
        return keep(named.select("doc_id", "n_chars", "fp", "next_fp", "edited_sha256", apart.alias("edited_fp")), "fingerprints")

    first = all_of(None)
    clashes = _clashing(rows, first, wide)
    return first if clashes is None else all_of(clashes)
