"""The level loop: a frontier grows into the next one until none is left.

State between levels is checkpointed in the shared folder, each vertex in the partition of its owner, so a level costs its
own exchanges and nothing is dealt out twice. On an undirected graph a neighbour of level k is in level k-1, k or k+1, so
candidates are only held against the last two levels; directed graphs need all levels, which are put together now and then,
so that plans do not grow with the depth.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .session import aligned, kept

LEVELS = "vertex long, dist int, parent long"
TRACE = "level int, frontier long, scanned long, candidates long, shipped long, expanded long, folded long, redundant long, seconds double"
LOADS = "level int, place int, rows long"
#: Levels of a directed graph that are masked one by one before they are put together.
APART = 8
#: A step takes the frontier (owner, keys, vertex, parent) and gives candidates of the same columns, each vertex once and at
#: its owner, and counts; "loads" among them is a list of (place, rows).
Step = Callable[[DataFrame], tuple[DataFrame, dict[str, object]]]


@dataclass(frozen=True)
class Traversal:
    """levels: (vertex, dist, parent) of what was reached; trace: one row for each level; loads: rows that each place merged
    in each level, where they were counted; met: (vertex, dist, searches), how many searches reached it there, where several
    went in lanes."""

    levels: DataFrame
    trace: DataFrame
    loads: DataFrame
    met: DataFrame | None = None


@dataclass(frozen=True)
class Placement:
    """So many partitions, and which of them owns a vertex. keys stand beside the vertex where searches share supersteps."""

    partitions: int
    owner: Callable[[Column], Column]
    keys: tuple[str, ...] = ()

    @property
    def by(self) -> list[str]:
        return ["owner", *self.keys, "vertex"]

    def put(self, pairs: DataFrame) -> DataFrame:
        """(owner, keys, vertex, parent), each row in its owner's partition: one exchange."""
        return pairs.select(self.owner(F.col("vertex")).alias("owner"), *self.keys, "vertex", "parent").repartitionById(self.partitions, "owner")

    def merged(self, pairs: DataFrame, place: str) -> DataFrame:
        """The greatest parent of each vertex: combined at the place where it was found, sent to the owner, combined there."""
        return self.combined(self.put(self.local(pairs, place)))

    def local(self, pairs: DataFrame, place: str) -> DataFrame:
        return pairs.groupBy(place, *self.keys, "vertex").agg(F.max("parent").alias("parent"))

    def combined(self, sent: DataFrame) -> DataFrame:
        return sent.groupBy(*self.by).agg(F.max("parent").alias("parent"))


def mask_new(candidates: DataFrame, visited: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Candidates that were not visited."""
    by = by or ["vertex"]
    return candidates.join(visited.select(*by).hint("shuffle_hash"), by, "left_anti")


def run_levels(spark: SparkSession, seeds: int | DataFrame, step: Step, place: Placement, directed: bool = False, mask: str = "auto", max_level: int | None = None,
               target: int | None = None, on_visit: Callable[[DataFrame, int], None] | None = None) -> Traversal:
    """seeds: a vertex, or rows (keys, vertex, parent) of several. mask: two (the last two levels; undirected graphs only),
    all, or auto. max_level and target end the loop early."""
    if mask == "two" and directed:
        raise ValueError("a directed graph is masked with all levels")
    recent_only = mask == "two" or (mask == "auto" and not directed)
    first = spark.createDataFrame([(seeds, seeds)], "vertex long, parent long") if isinstance(seeds, int) else seeds
    with aligned(spark, place.partitions):
        levels = [kept(place.put(first))]
        older: list[DataFrame] = []
        trace, loads, level, size = [], [], 0, levels[0].count()
        if on_visit:
            on_visit(levels[0], 0)
        found = target is not None and target == seeds
        while size and not found and (max_level is None or level < max_level):
            began = time.perf_counter()
            candidates, counts = step(levels[-1])
            known = levels[-2:] if recent_only else [*older, levels[-1]]
            new = kept(reduce(lambda df, old: mask_new(df, old, place.by), known, candidates))
            level, before, size = level + 1, size, new.count()
            loads += [(level, *x) for x in counts.get("loads", [])]
            trace.append((level, before, *(counts.get(k) for k in ("scanned", "candidates", "shipped", "expanded", "folded", "redundant")), time.perf_counter() - began))
            if not recent_only:
                older.append(levels[-1])
                if len(older) > APART:
                    older = [kept(reduce(DataFrame.unionAll, older).repartitionById(place.partitions, "owner"))]
            if size:
                levels.append(new)
                if on_visit:
                    on_visit(new, level)
                found = target is not None and not new.where(F.col("vertex") == target).isEmpty()
        parts = [df.select(*place.keys, "vertex", F.lit(k).cast("int").alias("dist"), "parent") for k, df in enumerate(levels)]
        return Traversal(reduce(DataFrame.unionAll, parts), spark.createDataFrame(trace, TRACE), spark.createDataFrame(loads, LOADS))


def seeds_of(spark: SparkSession, sources: list[int]) -> DataFrame:
    """(source, vertex, parent) of several searches, told apart by the key source."""
    if not sources:
        raise ValueError("no sources")
    return spark.createDataFrame([(s, s, s) for s in sources], "source long, vertex long, parent long")
