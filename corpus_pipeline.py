"""From raw documents to packed sequences: toxic and unreadable documents go, near copies and personal data too.

Each stage takes what the one before kept, decides on all of it, and returns the columns of
``documents``; the last returns packed pieces.  ``run`` writes each stage's rows to the shared
folder and reads them back, so a lost executor costs one stage at most.

All stages: an empty table gives an empty one; rows are decided one by one, so repeated rows (but for near copies)
stay repeated and a null or repeated id does no harm; texts of any length are read whole; further columns of any
name come back as they were, and no name that a stage works with is taken from them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from allpairs.llm import heavy_light, language, packing, personal_data, tokens, toxicity
from allpairs.llm.common import columns_of, documents, keep, labels, unused

#: A document of no language that was learned, or of one as likely as another, goes.
LEAST_LANGUAGE_SCORE = 0.5


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without documents whose toxicity is at the threshold or above.

    A null text is scored as the empty one and stays unless all others are toxic; without labels of both classes
    every document stays.
    """
    model = toxicity.fit(toxicity.training_rows(docs, labels(spark, sf_dir)))
    (score,) = unused(docs, "toxicity")
    return toxicity.score(docs, model, into=score).filter(F.col(score) < toxicity.THRESHOLD).select(*columns_of(docs))


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without documents that have no letter (null texts too), or whose language can't be told.

    Of languages that tie the first of the alphabet counts; without labelled rows no language is known and every document goes.
    """
    model = language.fit(docs.filter(~F.coalesce(language.held_out(F.col("doc_id")), F.lit(False))))
    found, score = unused(docs, "lang_pred", "lang_score")
    known = (F.col(found) != language.UNKNOWN) & (F.col(score) >= LEAST_LANGUAGE_SCORE)
    return language.predict(docs, model, into=(found, score)).filter(known).select(*columns_of(docs))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the least id, of each component of texts that share four fifths of their five-word shingles.

    Texts without words (null texts too) link with nothing and all stay; a row without an id stays for its component
    only if none there has one; of rows with one id and one text any one stays.
    """
    return heavy_light.without_near_copies(docs, 5, heavy_light.Similarity(4, 5))


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """With each span of personal data replaced by its kind; a text without any is as it was, a null text empty."""
    (spans,) = unused(docs, "spans")
    found, _ = personal_data.find(docs, carry=tuple(docs.columns), into=spans)
    clean = found.withColumn("text", personal_data.redact(F.coalesce("text", F.lit("")), F.col(spans)))
    if "n_chars" in docs.columns:
        clean = clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return clean.select(*columns_of(docs))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 ids with their sequence and place in it; a null text is one end id."""
    return packing.pack(docs, tokens.model_path("word_bpe_49k.json"), 2048)


STAGES = [
    ("toxicity", toxicity_stage),
    ("language", language_stage),
    ("near_duplicates", near_duplicate_stage),
    ("personal_data", personal_data_stage),
    ("packing", packing_stage),
]

#: Two stages are learned and one packs by search, which SQL can't express; tests compare each stage with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = keep(stage(spark, docs, sf_dir), name)
    return docs
