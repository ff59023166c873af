"""Toxicity of texts: a linear classifier on character n-grams scaled by naive Bayes log-count ratios.

A text's features are the hashed n-grams it has, each worth its log-count ratio between toxic and
other training texts; logistic regression learns their weights from a bounded sample of labelled
rows.  How many training texts of each class have a bucket is counted on the executors; only what the
counts leave is sent to the driver.  Whole texts of any length are scored, repeated rows each; null and
empty texts get the score of no feature; an input column with the name of the result is replaced by it.
Repeated labels of one document count once, the highest; labels without a document, or null, don't; of
several texts with one id the least is learned from.
Without training rows of both classes every score is 0.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import keep, ship, size_bounded_batches, with_columns_of_text
from .ngrams import Grams

ORDERS = (3, 4, 5)
BITS = 18
#: Labelled rows of each class that are learned from, chosen by a hash of their id.
MOST_OF_A_CLASS = 2_000
#: n-grams of fewer training texts are left out.
LEAST_TEXTS = 3
#: And so are those that say little: whose log-count ratio is nearer to 0.
LEAST_RATIO = 1.0
RIDGE = 1.0
THRESHOLD = 0.7


def held_out(id_: Column) -> Column:
    return F.pmod(F.crc32(id_.cast("string").cast("binary")), F.lit(3)) == 1


@dataclass
class ToxicityModel:
    bias: float
    weights: np.ndarray  # one for each bucket, ratios included


def _features(grams: Grams) -> list[np.ndarray]:
    """For each text the distinct buckets it has."""
    of = [grams.buckets(n, BITS) for n in ORDERS]
    return [np.unique(np.concatenate([b[s:e] for b in of])) for s, e in zip(grams.starts[:-1], grams.starts[1:], strict=True)]


def training_rows(docs: DataFrame, labels: DataFrame, most: int = MOST_OF_A_CLASS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """text and toxic of at most ``most`` labelled rows of each class, none held out."""
    known = labels.select(F.col(id_col).alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).filter("doc_id is not null and toxic in (0, 1)").filter(~held_out(F.col("doc_id")))
    single = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = F.xxhash64(F.lit("sample"), "doc_id"), F.col("doc_id")
    chosen = keep(single.filter("toxic = 1").orderBy(*order).limit(most).unionByName(single.filter("toxic = 0").orderBy(*order).limit(most)), "chosen")
    # at most 2 * most rows of two numbers
    return docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("toxic").alias("toxic"))


def fit(rows: DataFrame) -> ToxicityModel:
    """``rows``: bounded training rows with doc_id, text and toxic."""
    spark, size = rows.sparkSession, 1 << BITS
    ship(spark)
    rows = keep(rows.select("doc_id", "text", "toxic"), "training_rows")
    of_class = {r["toxic"]: r["count"] for r in rows.groupBy("toxic").count().collect()}
    if len(of_class) < 2:
        return ToxicityModel(-30.0, np.zeros(size, np.float32))

    def counted(batches):
        import pyarrow as pa

        for batch in size_bounded_batches(batches, 0, 1 << 20):
            toxic = np.array(batch.column(1).to_pylist(), bool)
            found = _features(Grams(batch.column(0).to_pylist(), max(ORDERS)))
            every = np.concatenate(found)
            bad = np.concatenate([f if t else f[:0] for f, t in zip(found, toxic, strict=True)])
            texts, of_bad = np.bincount(every, minlength=size), np.bincount(bad, minlength=size)
            some = np.flatnonzero(texts)
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(texts[some]), pa.array(of_bad[some])], ["bucket", "texts", "bad"])

    # one row for each bucket that occurs
    counts = rows.select("text", "toxic").mapInArrow(counted, "bucket long, texts long, bad long").groupBy("bucket").agg(F.sum("texts").alias("texts"), F.sum("bad").alias("bad")).toArrow()
    texts, bad = np.zeros(size), np.zeros(size)
    texts[counts["bucket"].to_numpy()], bad[counts["bucket"].to_numpy()] = counts["texts"].to_numpy(), counts["bad"].to_numpy()
    ratio = log_count_ratio(texts, bad, of_class[0], of_class[1])
    says = spark.sparkContext.broadcast(ratio != 0)

    def make():
        import pyarrow as pa

        stays = says.value
        return lambda texts: [pa.array([f[stays[f]].astype(np.int32) for f in _features(Grams(texts, max(ORDERS)))], pa.list_(pa.int32()))]

    featured = with_columns_of_text(rows, "text", "buckets array<int>", make)
    # bounded by the sample; in the order of ids, so that fits don't depend on how tasks were cut
    table = featured.select("doc_id", "toxic", "buckets").toArrow().sort_by("doc_id").combine_chunks()
    lists = table["buckets"].combine_chunks() if table["buckets"].num_chunks != 1 else table["buckets"].chunk(0)
    return _trained(lists.flatten().to_numpy(), np.diff(lists.offsets.to_numpy()), table["toxic"].to_numpy().astype(float), ratio)


def log_count_ratio(texts: np.ndarray, toxic: np.ndarray, n_other: int, n_toxic: int) -> np.ndarray:
    """Of each bucket, from how many texts have it and how many of those are toxic; 0 where that says little."""
    ratio = np.log(((toxic + 1) / (n_toxic + 2)) / ((texts - toxic + 1) / (n_other + 2)))
    ratio[(texts < LEAST_TEXTS) | (np.abs(ratio) < LEAST_RATIO)] = 0
    return ratio


def _trained(index: np.ndarray, lens: np.ndarray, y: np.ndarray, ratio: np.ndarray, rounds: int = 60) -> ToxicityModel:
    size = len(ratio)
    row = np.repeat(np.arange(len(y), dtype=np.int32), lens)
    each = np.where(y > 0, 0.5 / y.sum(), 0.5 / (1 - y).sum()) * len(y)  # both classes weigh the same

    value = ratio[index]

    def loss(w: np.ndarray) -> tuple[float, np.ndarray]:
        z = np.bincount(row, w[:-1][index] * value, len(y)) + w[-1]
        g = each * (1 / (1 + np.exp(-np.clip(z, -50, 50))) - y)
        value_ = float(each @ (np.logaddexp(0, z) - y * z)) + RIDGE / 2 * float(w[:-1] @ w[:-1])
        return value_, np.append(np.bincount(index, g[row] * value, size) + RIDGE * w[:-1], g.sum())

    w = _lbfgs(loss, np.zeros(size + 1), rounds)
    weights = w[:-1] * ratio
    weights[np.abs(weights) < 1e-4 * np.abs(weights).max()] = 0
    return ToxicityModel(float(w[-1]), weights.astype(np.float32))


def _lbfgs(f, w: np.ndarray, rounds: int, memory: int = 8) -> np.ndarray:
    """Limited-memory quasi-Newton steps with backtracking."""
    value, g = f(w)
    steps: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(rounds):
        d, alphas = -g, []
        for s, u in reversed(steps):
            a = (s @ d) / (s @ u)
            alphas.append(a)
            d = d - a * u
        d = d * ((steps[-1][0] @ steps[-1][1]) / (steps[-1][1] @ steps[-1][1]) if steps else 1 / max(1.0, float(np.abs(g).max())))
        for (s, u), a in zip(steps, reversed(alphas), strict=True):
            d = d + (a - (u @ d) / (s @ u)) * s
        rate, slope = 1.0, float(g @ d)
        while True:
            new, h = f(w + rate * d)
            if new <= value + 1e-4 * rate * slope or rate < 1e-6:
                break
            rate /= 2
        s, u = rate * d, h - g
        if s @ u > 1e-12:
            steps = [*steps[1 - memory :], (s, u)]
        done = value - new < 1e-6 * abs(value)
        w, value, g = w + s, new, h
        if done:
            break
    return w


def score(docs: DataFrame, model: ToxicityModel, text_col: str = "text", into: str = "toxicity") -> DataFrame:
    """All columns, and the one named ``into``: toxicity from 0 to 1."""
    shared = docs.sparkSession.sparkContext.broadcast(model.weights)
    bias = model.bias

    def make():
        import pyarrow as pa

        weights = shared.value

        def columns_of(texts):
            grams = Grams(texts, max(ORDERS))
            total = np.full(len(texts), bias)
            at = []
            for n in ORDERS:
                b = grams.buckets(n, BITS)
                some = np.flatnonzero(weights[b])
                at.append((grams.owner[some] << BITS) | b[some])
            distinct = np.unique(np.concatenate(at))
            total += np.bincount(distinct >> BITS, weights[distinct & ((1 << BITS) - 1)], len(texts))
            return [pa.array(1 / (1 + np.exp(-np.clip(total, -50, 50))))]

        return columns_of

    return with_columns_of_text(docs, text_col, f"`{into}` double", make)
