"""Language of texts: multinomial naive Bayes over hashed character n-grams.

n-gram counts of a bounded sample of labelled rows (all rows of a language that has no more than the
bound) are summed on the executors; what reaches the driver is one count for each language and
bucket.  The matrix of log-probabilities is broadcast; a batch of texts is scored by gathering its
rows and summing them text by text.

Null text, and text without a letter, is ``und`` with score 0.  Ties go to the language that comes
first in the alphabet.  Without labelled rows everything is ``und``.  Texts of any length are scored
whole, repeated rows each; an input column with the name of a result is replaced by it.  The model has
one number for each bucket and language: with very many languages there are fewer buckets, so that it
stays below MOST_MODEL_BYTES.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ship, size_bounded_batches, with_columns_of_text
from .ngrams import Grams

ORDERS = (1, 2, 3)
BITS = 16
SMOOTHING = 0.5
#: Labelled rows of each language that are learned from, chosen by a hash of their id.
MOST_DOCUMENTS = 8_000
#: A score is the posterior of a text of so many n-grams with the same mean likelihoods.
SCORE_GRAMS = 100
UNKNOWN = "und"
#: What is broadcast is no larger; 341 languages have all the buckets.
MOST_MODEL_BYTES = 1 << 28


def held_out(id_: Column) -> Column:
    return F.pmod(F.crc32(id_.cast("string").cast("binary")), F.lit(4)) == 2


@dataclass
class LanguageModel:
    languages: list[str]
    log_p: np.ndarray  # (orders * 2 ** bits, languages)
    bits: int = BITS


def bits_for(languages: int) -> int:
    most = MOST_MODEL_BYTES // (4 * len(ORDERS) * max(1, languages))
    return max(4, min(BITS, most.bit_length() - 1))


def fit(labelled: DataFrame, most_documents: int = MOST_DOCUMENTS, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    spark = labelled.sparkSession
    ship(spark)
    rows = labelled.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    counts = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    languages = sorted(counts)
    if not languages:
        return LanguageModel([], np.zeros((len(ORDERS) << BITS, 0), np.float32))
    share = F.lit(0)
    for lang, n in counts.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1 << 20, (most_documents << 20) // n + 1))).otherwise(share)
    sample = rows.filter(F.pmod(F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("sample")), F.lit(1 << 20)) < share)

    bits = bits_for(len(languages))

    def counted(batches):
        import pyarrow as pa

        place = {x: k for k, x in enumerate(languages)}
        for batch in size_bounded_batches(batches, 0, 1 << 20):
            grams = Grams(batch.column(0).to_pylist(), max(ORDERS))
            lang = np.array([place[x] for x in batch.column(1).to_pylist()], np.int64)[grams.owner]
            at = np.concatenate([(lang * len(ORDERS) + k << bits) + grams.buckets(n, bits) for k, n in enumerate(ORDERS)])
            key, n = np.unique(at, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(n.astype(np.int64))], ["key", "n"])

    # one count for each language and bucket that occurs: bounded by their numbers
    found = sample.select("text", "lang").mapInArrow(counted, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).toArrow()
    seen = np.zeros(len(languages) * len(ORDERS) << bits, np.float32)
    seen[found["key"].to_numpy()] = found["n"].to_numpy()
    by_order = seen.reshape(len(languages), len(ORDERS), 1 << bits) + np.float64(SMOOTHING)
    log_p = np.log(by_order / by_order.sum(2, keepdims=True)).reshape(len(languages), -1).T
    # what all languages share drops out of the comparison; small numbers keep single precision exact enough
    return LanguageModel(languages, (log_p - log_p.mean(1, keepdims=True)).astype(np.float32), bits)


def predict(docs: DataFrame, model: LanguageModel, text_col: str = "text", into: tuple[str, str] = ("lang_pred", "lang_score")) -> DataFrame:
    """All columns, and the two named ``into``: the language and its score."""
    shared = docs.sparkSession.sparkContext.broadcast(model.log_p)
    languages, bits = [*model.languages, UNKNOWN], model.bits

    def make():
        import pyarrow as pa

        log_p = shared.value

        def columns_of(texts):
            grams = Grams(texts, max(ORDERS))
            total = np.zeros((len(texts), log_p.shape[1]))
            some = np.flatnonzero(np.diff(grams.starts))
            for k, n in enumerate(ORDERS):
                if len(some) and log_p.shape[1]:
                    total[some] += np.add.reduceat(log_p[grams.buckets(n, bits) + (k << bits)], grams.starts[some], 0)
            if not log_p.shape[1]:
                return [pa.array([UNKNOWN] * len(texts)), pa.array(np.zeros(len(texts)))]
            best = total.argmax(1)
            n_grams = np.maximum(1, np.diff(grams.starts))[:, None]
            mild = total * np.minimum(1, SCORE_GRAMS / n_grams)
            p = np.exp(mild - mild.max(1, keepdims=True))
            score = np.where(grams.has_letter, p.max(1) / p.sum(1), 0.0)
            return [pa.array([languages[b] if ok else UNKNOWN for b, ok in zip(best, grams.has_letter, strict=True)]), pa.array(score)]

        return columns_of

    return with_columns_of_text(docs, text_col, f"`{into[0]}` string, `{into[1]}` double", make)
