"""Toxicity by logistic regression over hashed word n-grams and skip-grams, trained by FTRL-proximal.

Each coordinate has its own rate, and L1 leaves few weights that aren't zero, so the model is a short list of
(feature, weight) that is broadcast; its size is bounded by the number of hash buckets.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import crc_bucket, documents, importable, stored
from .textkernel import PUNCT_TABLE, STEP, Texts, mix, runs, slices, texts_of

QUERY = "op8_toxicity_ftrl"
#: Labelled rows, and bytes of their whole texts, that a model is fitted on at most: those with the smallest hash of their
#: id. One task holds the features of so many bytes: about half as many again.
TRAIN_ROWS, TRAIN_BYTES = 20_000, 256 << 20
#: Features are hashed into 2**BITS buckets.
BITS = 20
THRESHOLD = 0.7
_U = np.uint64


@dataclass(frozen=True)
class Settings:
    alpha: float = 2.0
    beta: float = 1.0
    l1: float = 5.0
    l2: float = 0.0
    epochs: int = 8
    positive: float = 1.0  # weight of a toxic row
    bits: int = BITS


def features(texts: Texts, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text number, bucket) of every word, every two words in a row and every two words with one between."""
    words = runs(texts, PUNCT_TABLE)
    h, doc, keep = words.hash, words.doc, _U((1 << bits) - 1)
    out = [(doc, mix(h + STEP[10]) & keep)]
    for gap, a, b in ((1, 11, 12), (2, 13, 14)):
        near = np.flatnonzero(doc[gap:] == doc[:-gap])
        out.append((doc[near], mix(h[near] * STEP[a] + h[near + gap] * STEP[b]) & keep))
    return np.concatenate([d for d, _ in out]), np.concatenate([f for _, f in out]).astype(np.int64)


def distinct(doc: np.ndarray, feature: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    key = np.unique(doc << bits | feature)
    return key >> bits, key & ((1 << bits) - 1)


def fit(rows: list[tuple[np.ndarray, int]], settings: Settings = Settings()) -> tuple[float, np.ndarray, np.ndarray]:
    """Bias, buckets and weights that aren't zero. rows: distinct buckets and label of each document, in training order."""
    s, size = settings, 1 << settings.bits
    z, n = np.zeros(size + 1), np.zeros(size + 1)  # the last coordinate is the bias, which L1 doesn't touch

    def weights(at: np.ndarray) -> np.ndarray:
        zs = z[at]
        w = -(zs - np.sign(zs) * s.l1) / ((s.beta + np.sqrt(n[at])) / s.alpha + s.l2)
        w[np.abs(zs) <= s.l1] = 0
        bias = at == size
        w[bias] = -zs[bias] / ((s.beta + np.sqrt(n[size])) / s.alpha)
        return w

    for _ in range(s.epochs):
        for buckets, label in rows:
            at = np.append(buckets, size)
            w = weights(at)
            g = (1 / (1 + np.exp(-np.clip(w.sum(), -35, 35))) - label) * (s.positive if label else 1.0)
            before = n[at]
            z[at] += g - (np.sqrt(before + g * g) - np.sqrt(before)) / s.alpha * w
            n[at] = before + g * g
    live = np.flatnonzero(np.abs(z[:size]) > s.l1)
    return float(weights(np.array([size]))[0]), live, weights(live)


def training_rows(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS, most_bytes: int = TRAIN_BYTES) -> DataFrame:
    """(doc_id, label, text) of the labelled documents to learn from: crc32 of the id modulo 3 isn't 1; at most so many rows
    and bytes, whole texts in order of the hash until one would go beyond.

    An id that is labelled more than once counts once, as toxic if any label says so; null labels don't count.
    """
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & (crc_bucket(F.col("doc_id"), 3) != 1))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    known = stored(known, "toxicity-labels")
    sizes = docs.select("doc_id", F.octet_length("text").alias("size")).join(F.broadcast(known.select("doc_id")), "doc_id")  # most ids bound the broadcast
    sizes = stored(sizes.groupBy("doc_id").agg(F.sum("size").alias("size")), "toxicity-sizes")
    if (sizes.agg(F.sum("size")).first()[0] or 0) > most_bytes:
        upto = F.sum("size").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, 0))  # most rows
        known = known.join(sizes.withColumn("upto", upto).where(F.col("upto") <= most_bytes).select("doc_id"), "doc_id", "left_semi")
    return docs.select("doc_id", "text").join(F.broadcast(known), "doc_id")


def train(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS, settings: Settings = Settings()) -> tuple[float, np.ndarray, np.ndarray] | None:
    """The model, fitted in one task on the bounded sample; None if there is nothing to learn from."""
    bits = settings.bits

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            doc, feature = distinct(*features(texts_of(part.column(2)), bits), bits)
            cuts = np.searchsorted(doc, np.arange(part.num_rows + 1))
            lists = pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array(feature, pa.int32()))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), lists], ["doc_id", "label", "buckets"])

    def learn(table: pa.Table) -> pa.Table:
        table = table.sort_by([("doc_id", "ascending")])
        ids = table.column("doc_id").to_numpy().astype(np.uint64)
        order = np.argsort(mix(ids + STEP[3]), kind="stable")
        buckets, label = table.column("buckets").combine_chunks(), table.column("label").to_numpy()
        starts, values = buckets.offsets.to_numpy(), buckets.values.to_numpy()
        rows = [(values[starts[i] : starts[i + 1]], int(label[i])) for i in order.tolist()]
        bias, live, w = fit(rows, settings)
        return pa.table({"bucket": pa.array([-1, *live.tolist()], pa.int32()), "weight": pa.array([bias, *w.tolist()], pa.float64())})

    importable(docs.sparkSession)
    rows = training_rows(docs, labels, most).select(F.col("doc_id").cast("long"), F.col("label").cast("int"), "text")
    found = rows.mapInArrow(extract, "doc_id long, label int, buckets array<int>").groupBy(F.lit(0).alias("all")).applyInArrow(lambda t: learn(t), "bucket int, weight double").toPandas()
    if found.empty:
        return None
    bias = float(found.loc[found.bucket < 0, "weight"].iloc[0])
    rest = found[found.bucket >= 0]
    return bias, rest.bucket.to_numpy(), rest.weight.to_numpy()


def score_texts(texts: Texts, dense: np.ndarray, bias: float, bits: int = BITS) -> np.ndarray:
    doc, feature = features(texts, bits)
    live = np.flatnonzero(dense[feature])
    doc, feature = distinct(doc[live], feature[live], bits)
    total = bias + np.bincount(doc, dense[feature], minlength=len(texts))[: len(texts)]
    return 1 / (1 + np.exp(-np.clip(total, -35, 35)))


def with_scores(docs: DataFrame, model: tuple[float, np.ndarray, np.ndarray] | None, columns: list[str], bits: int = BITS) -> DataFrame:
    """The given columns and toxicity_score, 0 to 1; 0 for all where no model could be fitted. A null text is empty."""
    if model is None:
        return docs.select(*columns, F.lit(0.0).alias("toxicity_score"))
    spark = docs.sparkSession
    importable(spark)
    sent = spark.sparkContext.broadcast(model)
    kept = docs.select(*columns, F.col("text").alias("_text"))
    schema = docs.select(*columns, F.lit(0.0).alias("toxicity_score")).schema
    names = schema.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bias, buckets, weights = sent.value
        dense = np.zeros(1 << bits)
        dense[buckets] = weights
        for part in slices(batches, "_text"):
            scores = score_texts(texts_of(part.column(len(names) - 1)), dense, bias, bits)
            yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(names) - 1)), pa.array(scores)], names)

    return kept.mapInArrow(run, schema)


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score and predicted of every row of docs; see training_rows() for what is learned from.

    Repeated rows are scored alike, a null id stays null (and isn't held out), and other columns aren't read.
    """
    scored = with_scores(docs.select(F.col("doc_id").cast("long"), "text"), train(docs, labels), ["doc_id"])
    return scored.select("doc_id", (crc_bucket(F.col("doc_id"), 3) == 1).alias("held_out"), F.col("toxicity_score").alias("score"),
                         (F.col("toxicity_score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs whose score is below the threshold, with their own columns."""
    names = docs.columns
    return with_scores(docs, train(docs, labels), names).where(F.col("toxicity_score") < threshold).select(names)


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
