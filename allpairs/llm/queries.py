"""The registered queries of this subpackage: thin digests of what the operators return."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, heavy_light, language, media, packing, personal_data, pieces, sharding, token_files, tokens, toxicity
from .common import documents, keep, labels


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return heavy_light.join(documents(spark, sf_dir), 3, heavy_light.Similarity(9, 10), links=True)


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    images = token_files.write(documents(spark, sf_dir), tokens.model_path("byte_bpe_50k.json"))
    return token_files.read(images)


def op3_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.shard(documents(spark, sf_dir), 40)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang")
    out = language.held_out(F.col("doc_id"))
    model = language.fit(docs.filter(~F.coalesce(out, F.lit(False))))
    found = keep(language.predict(docs.select("doc_id", "text"), model).select("doc_id", "lang_pred", "lang_score"), "languages")
    return found.select("doc_id", out.alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_crc32 (unsigned, little-endian 32-bit ids) and whether decoding gives the text again."""
    return keep(pieces.round_trips(documents(spark, sf_dir), tokens.model_path("piece_bpe_32k.model")), "round_trips")


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), tokens.model_path("word_bpe_49k.json"), 2048)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    model = toxicity.fit(toxicity.training_rows(docs, labels(spark, sf_dir)))
    found = keep(toxicity.score(docs, model).select("doc_id", "toxicity"), "toxicity")
    return found.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op8_canonical_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fingerprints.fingerprints(documents(spark, sf_dir))
    same = lambda x: (F.col("fp") == F.col(x)).cast("double")
    return found.select("doc_id", "n_chars", "edited_sha256", F.col("fp").alias("fingerprint"), F.col("edited_fp").alias("edited_fingerprint"), same("edited_fp").alias("near_edited"), same("next_fp").alias("near_next"))


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found, _ = personal_data.find(documents(spark, sf_dir))
    of = lambda k: F.filter("spans", lambda s: s["kind"] == k)
    base = personal_data.described(F.filter("spans", lambda s: s["base"]))
    return found.select("doc_id", *(F.size(of(k)).cast("long").alias(f"n_{k}") for k in personal_data.BASE), F.sha2(base, 256).alias("base_sha256"), personal_data.described(F.col("spans")).alias("spans"))


def op10_jpeg_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.features(media.store(documents(spark, sf_dir)))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_ngram_jaccard_join, op2_token_files, op3_feistel_shards, op4_language, op5_sentencepiece, op6_best_fit_packing, op7_toxicity, op8_canonical_fingerprints, op9_personal_data, op10_jpeg_columns)}


#: All pairs by brute force: shingles by string, intersections by a join, components by a walk along links.
_LINKED = r"""WITH RECURSIVE words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
shingles AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM words),
sizes AS (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
met AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS shared FROM shingles a JOIN shingles b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
links AS MATERIALIZED (SELECT x, y FROM met JOIN sizes p ON p.doc_id = x JOIN sizes q ON q.doc_id = y WHERE 100 * shared >= 90 * (p.n + q.n - shared)),
edges AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
walk AS (SELECT x, x AS seen FROM edges UNION SELECT walk.x, edges.y FROM walk JOIN edges ON edges.x = walk.seen),
least AS (SELECT x, min(seen) AS component_id FROM walk GROUP BY x),
degrees AS (SELECT x, count(*) AS n_links FROM edges GROUP BY x)
SELECT d.doc_id, coalesce(s.n, 0)::BIGINT AS n_shingles, coalesce(l.component_id, d.doc_id)::BIGINT AS component_id, coalesce(g.n_links, 0)::BIGINT AS n_links
FROM documents d LEFT JOIN sizes s ON s.doc_id = d.doc_id LEFT JOIN least l ON l.x = d.doc_id LEFT JOIN degrees g ON g.x = d.doc_id"""


def oracle_sql() -> dict[str, str]:
    """The others hash with functions that DuckDB lacks, tokenize, learn or search."""
    return {"op1_ngram_jaccard_join": _LINKED}
