"""Connected components, the largest of them, and a sample of sources inside it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graphs import Graph
from .layout import PLACE_ARCS
from .session import importable, stored

#: Labels that may be broadcast, 16 bytes each.
BROADCAST_IDS = 3_000_000
#: Edges that a task may put together, some 100 bytes each, as a share of a place's arcs.
SHARE = 1.5
#: Vertices that a task may put together by two arcs each, some 60 bytes a vertex.
MOST_VERTICES = 12_000_000


def components(graph: Graph) -> DataFrame:
    """(vertex, component): the least vertex reachable, arcs taken both ways.

    Of a large graph, one task first puts together what a share of the edges joins, by their hash, and every edge between
    what was put together goes on, which are few where vertices have many edges. Where vertices have few, or where over half
    of the edges are left, each vertex is put together with the least and the greatest of its neighbours, by one task that gets these two arcs a vertex. Of
    more vertices than a task may have, each is put together with the least of its neighbours only, as long as that at least
    halves the vertices. What then fits in a place is done in one task. Of more, labels spread along arcs, and each is
    replaced by its own label, so long chains take logarithmically many rounds.
    """
    importable(graph.spark)
    arcs = stored(graph.arcs.select("src", "dst").union(graph.arcs.select("dst", "src")).distinct(), "component-arcs") if graph.directed else graph.arcs.select("src", "dst")
    return _labels(arcs, arcs.count())


def least_reachable(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertices, the least that each reaches) of edges."""
    flat = np.concatenate((src, dst))
    order = np.argsort(flat)
    flat = flat[order]
    first = np.diff(flat, prepend=flat[:1] - 1) != 0
    names, number = flat[first], np.empty(len(flat), np.int32)
    number[order] = np.cumsum(first, dtype=np.int32) - 1
    del flat, order, first
    return names, names[_least(len(names), [(number[: len(src)], number[len(src) :])])]


def _least(n: int, edges: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The least of the numbers below n that each reaches: the greater end of an edge between trees hangs its tree below the
    other, all trees become flat, and what lies inside of one is not looked at again."""
    label = np.arange(n, dtype=np.int32)
    for a, b in edges:
        while len(a):
            x, y = label[a], label[b]
            apart = x != y
            x, y = x[apart], y[apart]
            a, b = np.minimum(x, y), np.maximum(x, y)
            np.minimum.at(label, b, a)
            while not np.array_equal(label, shorter := label[label]):
                label = shorter
    return label


def _by_two_arcs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Labels by the arcs of each vertex to its least (low) and its greatest neighbour (high)."""
    held = list(batches)
    column = lambda name: np.concatenate([np.empty(0, np.int64), *(b.column(name).to_numpy() for b in held)])
    names, edges = column("vertex"), []
    order = np.argsort(names).astype(np.int32)
    names = names[order]
    for name in ("low", "high"):  # looked up in their order, which stays in the cache
        wanted = column(name)
        by, at = np.argsort(wanted).astype(np.int32), np.empty(len(names), np.int32)
        for i in range(0, len(by), 1 << 20):
            at[by[i : i + (1 << 20)]] = np.searchsorted(names, wanted[by[i : i + (1 << 20)]])
        edges.append((np.arange(len(names), dtype=np.int32), at[order]))
    held.clear()
    del order, wanted, by, at
    label = _least(len(names), edges)
    for i in range(0, len(names), 1 << 20):
        some = slice(i, i + (1 << 20))
        yield pa.RecordBatch.from_arrays([pa.array(names[some], pa.int64()), pa.array(names[label[some]], pa.int64())], ["vertex", "component"])


def _in_one_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = list(batches)
    ends = [np.concatenate([np.empty(0, np.int64), *(b.column(c).to_numpy() for b in held)]) for c in ("src", "dst")]
    held.clear()
    found = least_reachable(*ends)
    for i in range(0, len(found[0]), 1 << 20):
        yield pa.RecordBatch.from_arrays([pa.array(x[i : i + (1 << 20)], pa.int64()) for x in found], ["vertex", "component"])


def _between(arcs: DataFrame, labels: DataFrame, n: int) -> DataFrame:
    """(src, dst) of the labels that an edge joins, each once. A vertex without a label is its own."""
    known = F.broadcast(labels) if n <= BROADCAST_IDS else labels
    ends = [known.select(F.col("vertex").alias(v), F.col("component").alias(c)) for v, c in (("src", "a"), ("dst", "b"))]
    found = arcs.where("src < dst").join(ends[0], "src", "left").join(ends[1], "dst", "left").select(F.coalesce("a", "src").alias("a"), F.coalesce("b", "dst").alias("b"))
    return stored(found.where("a <> b").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct(), "contracted")


def _both(half: DataFrame) -> DataFrame:
    return half.union(half.select("dst", "src"))


def _by_share(arcs: DataFrame, count: int) -> DataFrame | None:
    """Labels by a share of the edges that a task holds, then of what those leave apart. None if these edges have so many
    ends that they would join few and their labels could not be broadcast."""
    share = int(SHARE * PLACE_ARCS / (count / 2) * (1 << 20))
    some = stored(arcs.where("src < dst").where(F.pmod(F.xxhash64("src", "dst", F.lit(41)), F.lit(1 << 20)) < share), "some")
    if share < 1 << 20 and sum(some.agg(F.approx_count_distinct("src"), F.approx_count_distinct("dst")).first()) > BROADCAST_IDS:
        return None
    labels = stored(some.coalesce(1).mapInArrow(lambda b: _in_one_task(b), "vertex long, component long"), "labels")
    if share >= 1 << 20:
        return labels
    half = _between(arcs, labels, labels.count())
    left = 2 * half.count()
    if not left:
        return labels
    beyond = _labels(_both(half), left, 2 * left <= count)
    moved = labels.join(beyond.toDF("component", "beyond"), "component", "left").select("vertex", F.coalesce("beyond", "component").alias("component"))
    return stored(moved.unionByName(beyond.join(labels.select("vertex"), "vertex", "left_anti")), "labels")


def _labels(arcs: DataFrame, count: int, share: bool = True) -> DataFrame:
    if count <= PLACE_ARCS:
        return stored(arcs.where("src <= dst").coalesce(1).mapInArrow(lambda b: _in_one_task(b), "vertex long, component long"), "labels")
    if share and PLACE_ARCS and (found := _by_share(arcs, count)) is not None:
        return found
    near = stored(arcs.groupBy(F.col("src").alias("vertex")).agg(F.min("dst").alias("low"), F.max("dst").alias("high")), "near")
    n = near.count()
    if n <= MOST_VERTICES:
        labels, put = stored(near.coalesce(1).mapInArrow(lambda b: _by_two_arcs(b), "vertex long, component long"), "labels"), 0
    else:
        labels = stored(near.select("vertex", F.least("vertex", "low").alias("component")), "labels")
        put = labels.agg(F.countDistinct("component")).first()[0]
    if 2 * put <= n:  # always so by two arcs
        half = _between(arcs, labels, n)
        left = 2 * half.count()
        if not left:
            return labels
        # An arc goes from what a vertex is put together with to what that is put together with, so none is cut off.
        beyond = _labels(_both(half), left).toDF("component", "beyond")
        return stored(labels.join(beyond, "component", "left").select("vertex", F.coalesce("beyond", "component").alias("component")), "labels")
    while True:
        near = arcs.join(labels.withColumnRenamed("vertex", "dst"), "dst").groupBy(F.col("src").alias("vertex")).agg(F.min("component").alias("near"))
        best = labels.join(near, "vertex").select("vertex", "component", F.least("component", "near").alias("least"))
        # What a label as a whole has learned, and what that label's own vertex has, reach all that carry it.
        learned = best.groupBy("component").agg(F.min("least").alias("root"))
        jump = labels.select(F.col("vertex").alias("root"), F.col("component").alias("beyond"))
        learned = learned.join(jump, "root", "left").select("component", F.least("root", F.coalesce("beyond", "root")).alias("root"))
        fresh = stored(best.join(learned, "component").select("vertex", F.least("least", "root").alias("to"), "component"), "labels")
        labels = fresh.select("vertex", F.col("to").alias("component"))
        if fresh.where("to < component").isEmpty():
            return labels


def largest_component(graph: Graph) -> DataFrame:
    """Vertices of the component with most vertices (the least label of several)."""
    return largest_of(components(graph))


def largest_of(found: DataFrame) -> DataFrame:
    top = found.groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").limit(1)
    return found.join(F.broadcast(top.select("component")), "component").select("vertex")


def sample_sources(graph: Graph, k: int = 16, seed: int = 0, largest: DataFrame | None = None) -> list[int]:
    """k vertices of the largest component, by hash order: the same at any partitioning. largest: its vertices, if known."""
    from .rmat import shuffled

    found = largest_component(graph) if largest is None else largest
    return [r[0] for r in found.orderBy(shuffled(F.col("vertex"), seed), "vertex").limit(k).collect()]
