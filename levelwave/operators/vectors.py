"""Nearest vectors by cosine, among all or within blocks of a label."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import importable

#: Queries that a task holds at most on average, and of these the ones that are multiplied at a time.
QUERIES_A_TASK, AT_A_TIME = 1 << 15, 1 << 11


def nearest(embeddings: DataFrame, k: int, queries_a_task: int = 1 << 11) -> DataFrame:
    """(vec_id, other, similarity): the k nearest of the same label, ties by id.

    Exact within a label, so quadratic in a label's size, but in products of matrices: the queries of a label are dealt into
    parts, and the label's vectors stream past each.
    """
    rows = embeddings.where("embedding IS NOT NULL AND label IS NOT NULL").select(F.col("vec_id").cast("long").alias("vec_id"), "embedding", "label")
    sizes = rows.groupBy("label").agg(F.count("*").alias("n")).withColumn("parts", F.ceil(F.col("n") / queries_a_task))
    # Parts of all labels are numbered through.
    offset = F.sum("parts").over(Window.orderBy("label").rowsBetween(Window.unboundedPreceding, -1))  # a row a label
    numbered = sizes.select("label", "parts", F.coalesce(offset, F.lit(0)).cast("long").alias("first"))
    placed, total = rows.join(F.broadcast(numbered), "label"), sizes.agg(F.coalesce(F.sum("parts"), F.lit(1))).first()[0]
    asked = placed.select((F.col("first") + F.pmod(F.xxhash64("vec_id"), "parts")).alias("part"), F.lit(0).alias("kind"), "vec_id", "embedding")
    met = placed.select(F.explode(F.sequence("first", F.col("first") + F.col("parts") - 1)).alias("part"), F.lit(1).alias("kind"), "vec_id", "embedding")
    return _met(asked, met, k, int(total))


def _unit(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors of length 1), by id; a vector without a direction gives NaN."""
    ids = batch.column("vec_id").to_numpy(zero_copy_only=False)
    flat = batch.column("embedding").flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    rows, order = flat.reshape(len(ids), -1), np.argsort(ids)
    with np.errstate(invalid="ignore", divide="ignore"):
        return ids[order], (rows / np.sqrt((rows * rows).sum(axis=1, keepdims=True)))[order]


def _best(queries: np.ndarray, others: np.ndarray, similarity: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(others, similarity) of the k best of each row, both (row, k), ties by id; others -1 stands for none."""
    with_self = (others == queries[:, None]) | (others < 0)
    value = np.where(with_self, -np.inf, np.where(np.isnan(similarity), -2.0, similarity))
    least = np.partition(value, -k, axis=1)[:, -k] if value.shape[1] > k else np.full(len(value), -np.inf)
    row, col = np.nonzero((value >= least[:, None]) & ~with_self)
    order = np.lexsort((others[row, col], -value[row, col], row))
    row, col = row[order], col[order]
    rank = np.arange(len(row)) - np.searchsorted(row, row)
    row, col, rank = row[rank < k], col[rank < k], rank[rank < k]
    to, best = np.full((len(value), k), -1, np.int64), np.full((len(value), k), np.nan)
    to[row, rank], best[row, rank] = others[row, col], similarity[row, col]
    return to, best


def nearest_of_all(embeddings: DataFrame, k: int, queries_a_task: int = QUERIES_A_TASK) -> DataFrame:
    """(vec_id, other, similarity): the k nearest of all vectors, ties by id. Exact, so each vector meets every other one.

    Queries are dealt into parts; all vectors stream past each part, whose best so far are all that is kept of them.
    Similarities are rounded to 9 places; one with a vector of length 0 is NaN and comes last.
    """
    spark = embeddings.sparkSession
    rows = embeddings.where("embedding IS NOT NULL").select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    count = rows.count()
    parts = max(-(-count // queries_a_task), min(spark.sparkContext.defaultParallelism, -(-count // 256)), 1)
    asked = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(parts)).alias("part"), F.lit(0).alias("kind"), "vec_id", "embedding")
    met = rows.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))).alias("part"), F.lit(1).alias("kind"), "vec_id", "embedding")

    return _met(asked, met, k, parts)


def _met(asked: DataFrame, met: DataFrame, k: int, parts: int) -> DataFrame:
    """The k nearest among met of each vector of asked, both (part, kind, vec_id, embedding), within a part."""

    def found(ids: np.ndarray, to: np.ndarray, best: np.ndarray) -> pa.RecordBatch:
        row, col = np.nonzero(to >= 0)
        return pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(to[row, col]), pa.array(best[row, col])], ["vec_id", "other", "similarity"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held, ids = None, [], None
        for batch in batches:
            key = batch.column("part").to_numpy() * 2 + batch.column("kind").to_numpy()
            cuts = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a == b:
                    continue
                of, kind = divmod(int(key[a]), 2)
                if of != part:
                    if ids is not None:
                        yield found(ids, to, best)
                    part, held, ids = of, [], None
                some, unit = _unit(batch.slice(a, b - a))
                if kind == 0:
                    held.append((some, unit))
                    continue
                if not held:
                    continue  # a part that no query was dealt to
                if ids is None:
                    ids, queries = (np.concatenate(x) for x in zip(*held, strict=True))
                    to, best = np.full((len(ids), k), -1, np.int64), np.full((len(ids), k), np.nan)
                for i in range(0, len(ids), AT_A_TIME):
                    at = slice(i, i + AT_A_TIME)
                    near = np.round(queries[at] @ unit.T, 9)
                    others = np.concatenate((to[at], np.broadcast_to(some, near.shape)), axis=1)
                    to[at], best[at] = _best(ids[at], others, np.concatenate((best[at], near), axis=1), k)
        if ids is not None:
            yield found(ids, to, best)

    importable(asked.sparkSession)
    dealt = asked.unionByName(met).repartition(parts, "part").sortWithinPartitions("part", "kind")
    return dealt.mapInArrow(run, "vec_id long, other long, similarity double")
