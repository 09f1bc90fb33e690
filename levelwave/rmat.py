"""Recursive-matrix random graphs: each edge picks a quadrant for every bit of its ends, by hashes of its number."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import Graph
from .prep import symmetrize
from .session import importable

# --- fixed values: multipliers of the integer hash, and the quadrants' weights ----------------------------------------
FIRST, SECOND, SHIFT, MODULUS = 739982445, 695872825, 374761393, 1 << 31
WEIGHTS = (59, 19, 19, 5)
# ----------------------------------------------------------------------------------------------------------------------


def _hash(edge: Column, bit: Column, seed: int) -> Column:
    h = (edge * FIRST + bit * SECOND + SHIFT + seed * 1013904223) % MODULUS
    h = (h.bitwiseXOR(F.shiftright(h, 15)) * FIRST) % MODULUS
    h = (h.bitwiseXOR(F.shiftright(h, 12)) * SECOND) % MODULUS
    return h.bitwiseXOR(F.shiftright(h, 15))


def shuffled(vertex: Column, seed: int = 0) -> Column:
    """A hash of an id by the same arithmetic, which any SQL engine can repeat; for orders that look random."""
    return _hash(vertex % MODULUS, F.shiftright(vertex, 31), seed)


def edges_of(edge: np.ndarray, scale: int, weights: tuple[int, int, int, int] = WEIGHTS, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(src, dst) of raw edges by their numbers, a bit of all at a time."""
    a, b, c, d = weights
    src, dst, edge = np.zeros_like(edge), np.zeros_like(edge), edge % MODULUS
    for bit in range(scale):
        h = (edge * FIRST + bit * SECOND + SHIFT + seed * 1013904223) % MODULUS
        h = ((h ^ (h >> 15)) * FIRST) % MODULUS
        h = ((h ^ (h >> 12)) * SECOND) % MODULUS
        x = (h ^ (h >> 15)) % (a + b + c + d)
        src |= (x >= a + b).astype(np.int64) << bit
        dst |= (((x >= a) & (x < a + b)) | (x >= a + b + c)).astype(np.int64) << bit
    return src, dst


def rmat_edges(spark: SparkSession, scale: int, edge_factor: int = 16, weights: tuple[int, int, int, int] = WEIGHTS, seed: int = 0) -> DataFrame:
    """edge_factor * 2**scale raw edges over 2**scale ids, repeats and loops kept: a row each, made where it is used."""
    importable(spark)

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in edges_of(batch.column("id").to_numpy(), scale, weights, seed)], ["src", "dst"])

    return spark.range(edge_factor << scale).mapInArrow(lambda b: made(b), "src long, dst long")


def rmat(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 0) -> Graph:
    """The undirected simple graph of those edges."""
    return Graph(symmetrize(rmat_edges(spark, scale, edge_factor, seed=seed)))
