"""Scalar, aggregate and table functions, and their registration for SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType

from ..serial import adjacency, serial_levels


def link_host(url: Column) -> Column:
    return F.parse_url(url, F.lit("HOST"))


def norm_line(text: Column) -> Column:
    return F.trim(F.lower(text))


def event_key(props: Column) -> Column:
    return F.get_json_object(props, "$.k")


def edge_day(ts: Column) -> Column:
    return F.date_trunc("day", ts)


def gap_seconds(a: Column, b: Column) -> Column:
    return F.unix_seconds(b) - F.unix_seconds(a)


def grid_side(p: Column) -> Column:
    return F.floor(F.sqrt(p.cast("double"))).cast("int")


def feistel_id(bits: int, seed: int = 0, rounds: int = 4) -> Callable[[Column], Column]:
    """The relabelling of prep.feistel for ids that come through Python, as a scalar function over batches: a keyed bijection
    of the integers under 2**(2 * bits), by another round function than the SQL form."""
    mask = np.uint64((1 << bits) - 1)

    @pandas_udf(LongType())
    def run(ids: pd.Series) -> pd.Series:
        x = ids.to_numpy(np.uint64)
        left, right = x >> np.uint64(bits), x & mask
        for number in range(rounds):
            mixed = (right + np.uint64(number * 7919 + seed + 1)) * np.uint64(0x9E3779B97F4A7C15)
            left, right = right, left ^ ((mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(64 - bits))
        return pd.Series(((left << np.uint64(bits)) | right).astype(np.int64))

    return run


@udtf(returnType=StructType([StructField("tree", LongType()), StructField("step", IntegerType()), StructField("vertex", LongType())]))
class UnfoldPath:
    """The way down from a tree's root to a target: TABLE (tree, vertex, parent, target) PARTITION BY tree, all rows of a tree
    with the same target. No rows if the target isn't in the tree."""

    def __init__(self) -> None:
        self.parent: dict[int, int] = {}
        self.tree, self.target = None, None

    def eval(self, row) -> None:  # noqa: ANN001
        self.tree, self.target = row["tree"], row["target"]
        self.parent[row["vertex"]] = row["parent"]

    def terminate(self) -> Iterator[tuple]:
        path, at = [], self.target
        while at in self.parent and (not path or path[-1] != at):
            path.append(at)
            at = self.parent[at]
        for step, vertex in enumerate(reversed(path)):
            yield self.tree, step, vertex


@pandas_udf(DoubleType())
def imbalance_of(counts: pd.Series) -> float:
    """Greatest over mean of a group's loads."""
    return float(counts.max() / counts.mean()) if len(counts) else float("nan")


@udtf(returnType=StructType([StructField("graph_id", LongType()), StructField("vertex", LongType()), StructField("dist", IntegerType()), StructField("parent", LongType())]))
class BfsSmall:
    """Traversal of many small graphs side by side: TABLE (graph_id, src, dst) PARTITION BY graph_id, from its least vertex."""

    def __init__(self) -> None:
        self.arcs: list[tuple[int, int]] = []
        self.graph_id = None

    def eval(self, row) -> None:  # noqa: ANN001
        self.graph_id = row["graph_id"]
        self.arcs.append((row["src"], row["dst"]))

    def terminate(self) -> Iterator[tuple]:
        if self.arcs:
            source = min(min(a) for a in self.arcs)
            for vertex, (dist, parent) in serial_levels(adjacency(self.arcs), source).items():
                yield self.graph_id, vertex, dist, parent


def register(spark: SparkSession) -> None:
    """SQL names: levelwave_tag, levelwave_owner, levelwave_kind (temporary functions), bfs_small and unfold_path (table
    functions)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION levelwave_tag(key BIGINT, kind INT) RETURNS BIGINT RETURN key * 16 + kind")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION levelwave_kind(vertex BIGINT) RETURNS INT RETURN CAST(vertex % 16 AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION levelwave_owner(vertex BIGINT, places INT) RETURNS INT RETURN CAST(pmod(xxhash64(vertex), places) AS INT)")
    spark.udtf.register("bfs_small", BfsSmall)
    spark.udtf.register("unfold_path", UnfoldPath)
