"""Traversal of a graph of checked size inside one task: many small graphs, or one with very many levels.

A distributed level costs a round trip however few vertices it has, so a graph of some 140 levels that fits in a task is
collapsed into one. The check is on the number of arcs; larger graphs stay with rows or grid. Ids are made dense and arcs
sorted by all tasks, and the one task gets 4 bytes an arc, block by block, and puts each where it belongs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .graphs import Graph
from .layout import PLACE_ARCS, places_for
from .loop import LEVELS
from .prep import degrees, dense_ranks
from .serial import csr_levels, serial_rows
from .session import importable, stored

#: Arcs that a task may hold, 4 bytes each, beside some 40 bytes for each vertex and 4 for each vertex and thread.
MOST_ARCS = 1 << 27
#: Ids that may be broadcast for their dense numbers.
BROADCAST_IDS = 2_000_000
#: Arcs of a block, some 40 kB.
BLOCK_ARCS = 10_000
_BLOCK = "part int, at long, vertices array<int>, degrees array<int>, targets array<int>"


def fits(graph: Graph, most: int = MOST_ARCS) -> bool:
    return graph.arcs.count() <= most


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks of the arcs (s, d) of a place, sorted: distinct starts, how many arcs each has, and all ends, with the place in
    the task."""
    part = TaskContext.get().partitionId()
    both = np.concatenate([np.empty(0, np.int64), *(b.column("s").to_numpy().astype(np.int64) << 32 | b.column("d").to_numpy() for b in batches)])
    both.sort()
    for at in range(0, len(both), BLOCK_ARCS):
        some = both[at : at + BLOCK_ARCS]
        distinct, degrees = np.unique(some >> 32, return_counts=True)
        lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x.astype(np.int32), pa.int32())) for x in (distinct, degrees, some & 0xFFFFFFFF)]
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([at], pa.int64()), *lists], ["part", "at", "vertices", "degrees", "targets"])


@dataclass(frozen=True)
class _Packed:
    """Blocks of a graph on dense numbers: (old, new) of n ids, where each task's blocks begin, and all arcs."""

    ids: DataFrame
    n: int
    blocks: DataFrame
    first: dict[int, int]
    total: int

    def numbers(self, sources: DataFrame) -> dict[int, int]:
        return {r["old"]: r["new"] for r in self.ids.join(F.broadcast(sources), F.col("old") == F.col("vertex")).select("old", "new").collect()}  # a row a source


def _pack(graph: Graph, more: DataFrame | None = None) -> _Packed:
    """more: ids (vertex) that may have no arcs."""
    arcs = graph.arcs.select("src", "dst")
    importable(graph.spark)
    found = degrees(arcs)
    others = [arcs.select(F.col("dst").alias("vertex"))] * graph.directed + [more] * (more is not None)  # else every id is a start
    if others:
        found = reduce(DataFrame.unionAll, [found, *(df.select("vertex", F.lit(0).alias("degree")) for df in others)]).groupBy("vertex").agg(F.sum("degree").alias("degree"))
    ids = stored(dense_ranks(stored(found, "local-vertices"), ["vertex"]).select(F.col("vertex").alias("old"), F.col("rank").alias("new"), "degree"), "local-ids")
    n = ids.count()
    known = F.broadcast(ids) if n <= BROADCAST_IDS else ids
    bounds, most = _bounds(ids, n)
    part = reduce(Column.__add__, [(F.col("new") >= b).cast("int") for b in bounds], F.lit(0))
    dense = arcs.join(known.select(F.col("old").alias("src"), F.col("new").cast("int").alias("s"), part.alias("part")), "src").join(known.select(F.col("old").alias("dst"), F.col("new").cast("int").alias("d")), "dst").select("part", "s", "d")
    dealt = dense.repartitionById(len(bounds) + 1, "part") if most <= 2 * PLACE_ARCS else dense.repartitionByRange(places_for(graph.arcs.count()), "s", "d")  # cuts hubs
    blocks = stored(dealt.select("s", "d").mapInArrow(lambda b: _runs(b), _BLOCK), "local-blocks")
    sizes = {r["part"]: r["n"] for r in blocks.groupBy("part").agg(F.sum(F.size("targets")).alias("n")).collect()}  # a row a task
    return _Packed(ids.select("old", "new"), n, blocks, {part: sum(m for p, m in sizes.items() if p < part) for part in sizes}, sum(sizes.values()))


def _bounds(ids: DataFrame, n: int) -> tuple[list[int], int]:
    """Dense numbers at which the places of the arcs begin, but for the first, and the most arcs of a place: some PLACE_ARCS / 2
    or what a group of starts has, of at most 4,096."""
    width, out, held, most = -(-n // 4096) or 1, [], 0, 0
    for r in ids.groupBy(F.expr(f"new div {width}").alias("at")).agg(F.sum("degree").alias("n")).orderBy("at").collect():
        if held and held + r["n"] > PLACE_ARCS // 2:
            out.append(r["at"] * width)
            held = 0
        held += r["n"]
        most = max(most, held)
    return out, most


#: What was packed of arcs that are still in use.
_packed: WeakKeyDictionary[DataFrame, _Packed] = WeakKeyDictionary()


def _in_one_task(graph: Graph, sources: list[int], most: int, search: Callable[[np.ndarray, np.ndarray, list[int]], Iterator[pa.RecordBatch]], schema: str) -> tuple[DataFrame, DataFrame]:
    """(what search(offsets, targets, roots) gives in the one task, (old, new): dense numbers of the ids, in their order)."""
    if not (_packed[graph.arcs].total <= most if graph.arcs in _packed else fits(graph, most)):
        raise ValueError(f"more than {most} arcs: use bfs_rows or bfs_grid")
    spark = graph.spark
    seeds = spark.createDataFrame([(s,) for s in set(sources)], "vertex long")
    if graph.arcs not in _packed:
        _packed[graph.arcs] = _pack(graph)
    packed = _packed[graph.arcs]
    number = packed.numbers(seeds)
    if len(number) < len(set(sources)):  # sources without arcs
        packed = _pack(graph, seeds)
        number = packed.numbers(seeds)
    ids, n, blocks, first, total, roots = packed.ids, packed.n, packed.blocks, dict(packed.first), packed.total, [number[s] for s in sources]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        targets, offsets = np.empty(total, np.int32), np.zeros(n + 1, np.int64)
        for batch in batches:
            columns = [batch.column(name) for name in ("vertices", "degrees", "targets")]
            for k, (part, at) in enumerate(zip(batch.column("part").to_pylist(), batch.column("at").to_pylist(), strict=True)):
                some, degrees, ends = (c[k].values.to_numpy() for c in columns)
                targets[first[part] + at : first[part] + at + len(ends)] = ends
                offsets[some + 1] += degrees  # a block has a start once
        np.cumsum(offsets, out=offsets)
        yield from search(offsets, targets, roots)

    # A row without arcs gives the task its sources where the graph has none.
    none = spark.createDataFrame([(0, 0, [], [], [])], _BLOCK) if not total else blocks
    first |= {} if total else {0: 0}
    # A block is some 40 kB, so few of them are handed over at a time.
    return none.coalesce(1).mapInArrow(run, schema), ids


_FOUND = "source long, v int, dist int, p int"


def _rows(source: int, v: np.ndarray, dist: np.ndarray, p: np.ndarray, at_a_time: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    for i in range(0, len(v), at_a_time):
        to = slice(i, i + at_a_time)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v[to]), source), pa.int64()), *(pa.array(x[to], pa.int32()) for x in (v, dist, p))], ["source", "v", "dist", "p"])


def _named(found: DataFrame, ids: DataFrame, several: bool) -> DataFrame:
    """(vertex, dist, parent) with the ids that the dense numbers stand for."""
    found = stored(found, "local-levels")  # the search runs once
    known = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    named = found.join(known.select(F.col("new").alias("v"), F.col("old").alias("vertex")), "v").join(known.select(F.col("new").alias("p"), F.col("old").alias("parent")), "p")
    return named.select(*["source"][: int(several)], "vertex", "dist", "parent")


def bfs_local(graph: Graph, source: int | list[int], threads: int = 4, frontier_store: str = "local", visit_check: str = "benign", most_arcs: int = MOST_ARCS, max_level: int | None = None) -> DataFrame:
    """(vertex, dist, parent), with source before it for several; frontier_store local, shared or bag; visit_check benign or
    atomic."""
    sources = source if isinstance(source, list) else [source]

    def search(offsets: np.ndarray, targets: np.ndarray, roots: list[int]) -> Iterator[pa.RecordBatch]:
        for s, root in zip(sources, roots, strict=True):
            yield from _rows(s, *csr_levels(offsets, targets, root, threads, frontier_store, visit_check, max_level)[:3])

    return _named(*_in_one_task(graph, sources, most_arcs, search, _FOUND), isinstance(source, list))


def bfs_serial(graph: Graph, source: int, frontier: str = "stacks", most_arcs: int = MOST_ARCS) -> DataFrame:
    """The serial method, in one task: stacks or queue."""

    def search(offsets: np.ndarray, targets: np.ndarray, roots: list[int]) -> Iterator[pa.RecordBatch]:
        yield from _rows(source, *serial_rows(offsets, targets, roots[0], frontier))

    return _named(*_in_one_task(graph, [source], most_arcs, search, _FOUND), False)


def redundancy(graph: Graph, source: int, threads: int = 6, frontier_store: str = "local", most_arcs: int = MOST_ARCS) -> DataFrame:
    """One row: pushes, redundant, levels of a run with unsynchronised checks."""

    def search(offsets: np.ndarray, targets: np.ndarray, roots: list[int]) -> Iterator[pa.RecordBatch]:
        *_, counts = csr_levels(offsets, targets, roots[0], threads, frontier_store)
        yield pa.RecordBatch.from_arrays([pa.array([counts[k]], pa.int64()) for k in ("pushes", "redundant", "levels")], ["pushes", "redundant", "levels"])

    return _in_one_task(graph, [source], most_arcs, search, "pushes long, redundant long, levels long")[0]
