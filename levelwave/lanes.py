"""Several searches of an undirected graph in one: a row carries a bit (lane) for each search that it is of, so what searches
share is read, sent and held once, and rows don't grow with their number.

Level by level the four forms are as in rows and grid; a vertex has its greatest parent for each lane. Candidates are put
together with the last two levels in one aggregate, which spills, so no side has to fit in memory.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import Graph
from .kernels import entries_of, lists_of, pieces
from .layout import GridLayout, RowLayout
from .loop import LOADS, TRACE, Traversal
from .session import aligned, kept, size

#: Searches at a time, each a bit and a column, and the parent of a lane that a row isn't of.
LANES, NONE = 32, -(1 << 63) + 1
FOUND = "vertex long, parent long, lanes long"
#: Takes a frontier (owner, vertex, lanes, a parent a lane) and gives candidates with the same parents at their owners.
Step = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class Searches:
    """So many lanes, the partitions of their state, and which of them owns a vertex."""

    count: int
    partitions: int
    owner: Callable[[Column], Column]

    @property
    def parents(self) -> list[str]:
        return [f"p{i}" for i in range(self.count)]

    @cached_property
    def greatest(self) -> list[Column]:
        return [F.expr(f"max({c}) AS {c}") for c in self.parents]

    def put(self, rows: DataFrame) -> DataFrame:
        """Each row in its owner's partition: one exchange."""
        return rows.withColumn("owner", self.owner(F.col("vertex"))).repartitionById(self.partitions, "owner")

    def spread(self, pairs: DataFrame, *by: str) -> DataFrame:
        """A column a lane from (lanes, parent)."""
        return pairs.selectExpr(*by, *[f"if(lanes & {1 << i}L = 0, {NONE}, parent) AS {c}" for i, c in enumerate(self.parents)])

    def combined(self, pairs: DataFrame, place: str) -> DataFrame:
        """The greatest parent of each vertex and lane at the place where they were found."""
        return self.spread(pairs, place, "vertex").groupBy(place, "vertex").agg(*self.greatest)

    def fresh(self, sent: DataFrame, known: list[DataFrame]) -> DataFrame:
        """(owner, vertex, lanes, parents) of candidates at their owners in lanes that have not seen the vertex."""
        nothing = [f"{NONE} AS {c}" for c in self.parents]
        both = reduce(DataFrame.unionAll, [df.selectExpr("owner", "vertex", *nothing, "lanes AS seen") for df in known], sent.selectExpr("owner", "vertex", *self.parents, "0L AS seen"))
        merged = both.groupBy("owner", "vertex").agg(*self.greatest, F.expr("bit_or(seen) AS seen"))
        new = merged.selectExpr("owner", "vertex", *[f"if(seen & {1 << i}L = 0, {c}, {NONE}) AS {c}" for i, c in enumerate(self.parents)])
        lanes = " + ".join(f"if({c} = {NONE}, 0L, {1 << i}L)" for i, c in enumerate(self.parents))
        return new.selectExpr("owner", "vertex", f"{lanes} AS lanes", *self.parents).where("lanes <> 0")


def _run(spark: SparkSession, sources: list[int], searches: Searches, step: Step, max_level: int | None = None) -> Traversal:
    seeds = spark.createDataFrame([(s, 1 << i, s) for i, s in enumerate(sources)], FOUND.replace("parent long, lanes long", "lanes long, parent long"))
    with aligned(spark, searches.partitions):
        levels, trace, level = [kept(searches.put(searches.spread(seeds, "vertex", "lanes")).select("owner", "vertex", "lanes", *searches.parents))], [], 0
        found = size(levels[0])
        while found and (max_level is None or level < max_level):
            began = time.perf_counter()
            new = kept(searches.fresh(step(levels[-1]), levels[-2:]))
            level, before, found = level + 1, found, size(new)
            trace.append((level, before, *[None] * 6, time.perf_counter() - began))
            if found:
                levels.append(new)
        each = ", ".join(f"struct({s}L AS source, {c} AS parent)" for s, c in zip(sources, searches.parents, strict=True))
        parts = [df.selectExpr("vertex", f"{k} AS dist", f"inline(filter(array({each}), x -> x.parent <> {NONE}))").select("source", "vertex", "dist", "parent") for k, df in enumerate(levels)]
        met = [df.selectExpr("vertex", f"{k} AS dist", "bit_count(lanes) AS searches") for k, df in enumerate(levels)]
        return Traversal(reduce(DataFrame.unionAll, parts), spark.createDataFrame(trace, TRACE), spark.createDataFrame([], LOADS), reduce(DataFrame.unionAll, met))


def together(run: Callable[[list[int]], Traversal], sources: list[int]) -> Traversal:
    """All searches, LANES at a time."""
    distinct = list(dict.fromkeys(sources))
    if not distinct:
        raise ValueError("no sources")
    done = [run(distinct[k : k + LANES]) for k in range(0, len(distinct), LANES)]
    return Traversal(*(reduce(DataFrame.unionAll, [getattr(d, name) for d in done]) for name in ("levels", "trace", "loads", "met")))


def can(graph: Graph, source: object, trace: bool, limits: dict[str, object]) -> bool:
    """Whether searches go in lanes: several, of an undirected graph, with no more asked for than a last level."""
    return isinstance(source, list) and not graph.directed and not trace and limits.keys() <= {"max_level", "chunk"}


def rows_flat(graph: Graph, sources: list[int], layout: RowLayout, **limits: object) -> Traversal:
    with aligned(graph.spark, layout.p):  # sorted once, so that a level only sorts its frontier
        arcs = kept(layout.place(graph.arcs).repartitionById(layout.p, "owner").sortWithinPartitions("owner", "src"))

    def run(some: list[int]) -> Traversal:
        searches = Searches(len(some), layout.p, layout.owner)

        def step(frontier: DataFrame) -> DataFrame:
            near = frontier.select("owner", F.col("vertex").alias("src"), "lanes").hint("merge")
            pairs = arcs.join(near, ["owner", "src"]).select(F.col("owner").alias("sender"), F.col("dst").alias("vertex"), F.col("src").alias("parent"), "lanes")
            return searches.put(searches.combined(pairs, "sender").drop("sender"))

        return _run(graph.spark, some, searches, step, **limits)

    return together(run, sources)


def grid_flat(graph: Graph, sources: list[int], layout: GridLayout, **limits: object) -> Traversal:
    with aligned(graph.spark, layout.p):
        cells = kept(layout.place(graph.arcs).repartitionById(layout.p, "cell").sortWithinPartitions("cell", "col"))

    def run(some: list[int]) -> Traversal:
        searches = Searches(len(some), layout.p, layout.owner)

        def step(frontier: DataFrame) -> DataFrame:
            sent = expanded(frontier, layout).repartitionById(layout.p, "cell").hint("merge")
            pairs = cells.join(sent, ["cell", "col"]).select("cell", F.col("row").alias("vertex"), F.col("col").alias("parent"), "lanes")
            return searches.put(searches.combined(pairs, "cell").drop("cell"))

        return _run(graph.spark, some, searches, step, **limits)

    return together(run, sources)


def expanded(frontier: DataFrame, layout: GridLayout) -> DataFrame:
    """(cell, col, lanes): each entry at all cells of its grid column."""
    cells = F.transform(F.sequence(F.lit(0), F.lit(layout.p_r - 1)), lambda i: i * layout.p_c + F.col("j"))
    return frontier.select(F.col("vertex").alias("col"), layout.column(F.col("vertex")).alias("j"), "lanes").select(F.explode(cells).alias("cell"), "col", "lanes")


def rows_hybrid(graph: Graph, sources: list[int], layout: RowLayout, threads: int, visit_check: str = "benign", chunk: int = 4_000_000, **limits: object) -> Traversal:
    from .rows import pack_csr

    blocks = max(layout.p // threads, 1)
    wide = RowLayout(blocks, layout.n)
    packed, slots, count = pack_csr(graph.arcs, wide, chunk)
    with aligned(graph.spark, count):
        packed = kept(packed.repartitionById(count, "slot"))

    def near(frontier: DataFrame) -> DataFrame:
        """A block's part of the frontier goes to each of its pieces."""
        pieces = F.sequence("first", F.col("first") + F.col("pieces") - 1)
        return frontier.join(F.broadcast(slots), F.col("owner") == F.col("block")).select(F.explode(pieces).alias("slot"), F.col("vertex").alias("col"), "lanes")

    return _packed(graph.spark, sources, packed, count, near, ("vertices", "offsets", "targets"), (blocks, wide.owner), threads, visit_check == "atomic", limits)


def grid_hybrid(graph: Graph, sources: list[int], layout: GridLayout, threads: int, chunk: int, **limits: object) -> Traversal:
    from .grid import cell_parts, pack_dcsc, part_of

    spark, parts = graph.spark, cell_parts(graph.arcs, layout, chunk)
    found = sorted(tuple(r) for r in parts.collect())  # a row a cell
    first = spark.createDataFrame([(cell, n, sum(m for _, m in found[:k])) for k, (cell, n) in enumerate(found)], "cell int, parts int, first int")
    count = max(sum(n for _, n in found), 1)
    packed = pack_dcsc(graph.arcs, layout, threads, chunk, parts).join(F.broadcast(first), "cell").withColumn("slot", F.col("first") + F.col("part"))
    with aligned(spark, count):
        packed = kept(packed.select("slot", "jc", "cp", "ir", "rows").repartitionById(count, "slot"))

    def near(frontier: DataFrame) -> DataFrame:
        """A cell's part of the frontier goes to the parts that have its columns."""
        sent = expanded(frontier, layout).join(F.broadcast(first), "cell")
        return sent.select((F.col("first") + part_of(layout)).alias("slot"), "col", "lanes")

    return _packed(spark, sources, packed, count, near, ("jc", "cp", "ir", "rows"), (layout.p, layout.owner), threads, False, limits)


def _packed(spark: SparkSession, sources: list[int], packed: DataFrame, count: int, near: Callable[[DataFrame], DataFrame], names: tuple[str, ...], place: tuple[int, Callable[[Column], Column]], threads: int, atomic: bool,
            limits: dict[str, object]) -> Traversal:
    """Blocks (slot, names) multiplied by a pool of threads, each slot in a task of its own."""

    def expand(left: pa.Table, right: pa.Table) -> pa.Table:
        col, lanes = (right.column(c).to_numpy() for c in ("col", "lanes"))
        order = np.argsort(col)
        col, lanes, found = col[order], lanes[order], []
        with ThreadPoolExecutor(threads) as pool:
            for keys, offsets, values, *rows in lists_of(left, *names):
                if rows:  # pieces of disjoint rows: one a thread
                    found.append(pool.submit(_times, keys, offsets, values, col, lanes, rows[0]))
                else:  # parts of the frontier: one a thread
                    found += [pool.submit(_times, keys, offsets, values, col[some], lanes[some]) for some in pieces(np.arange(len(col)), threads)]
            got = [f.result() for f in found]
        vertex, parent, of = (np.concatenate([np.empty(0, np.int64), *(g[k] for g in got)]) for k in range(3))
        if atomic:
            vertex, number = np.unique(vertex, return_inverse=True)
            vertex, parent, of = _greatest(vertex, number, parent, of)
        return pa.table({"vertex": pa.array(vertex, pa.int64()), "parent": pa.array(parent, pa.int64()), "lanes": pa.array(of, pa.int64())})

    def run(some: list[int]) -> Traversal:
        searches = Searches(len(some), *place)

        def step(frontier: DataFrame) -> DataFrame:
            sent = near(frontier).repartitionById(count, "slot")
            pairs = packed.groupBy("slot").cogroup(sent.groupBy("slot")).applyInArrow(lambda a, b: expand(a, b), FOUND)
            return searches.spread(searches.put(pairs), "owner", "vertex")

        return _run(spark, some, searches, step, **limits)

    return together(run, sources)


def _times(keys: np.ndarray, offsets: np.ndarray, values: np.ndarray, wanted: np.ndarray, lanes: np.ndarray, rows: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vertex, parent, lanes) that the wanted keys, sorted, reach; rows: what the values number, or none if they are ids."""
    if not len(keys) or not len(wanted):
        return (np.empty(0, np.int64),) * 3
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    hit = keys[at] == wanted
    at, size = at[hit], offsets[at[hit] + 1] - offsets[at[hit]]
    source, value = entries_of(keys, offsets, values, at)
    rows, number = np.unique(value, return_inverse=True) if rows is None else (rows, value)
    return _greatest(rows, number, source, np.repeat(lanes[hit], size))


def _greatest(rows: np.ndarray, number: np.ndarray, source: np.ndarray, lanes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of entries in the order of their sources, those that are the last of their row in a lane, with the lanes in which they
    are: a dense accumulator a lane."""
    of = np.zeros(len(source), np.int64)
    for i in range(int(np.bitwise_or.reduce(lanes)).bit_length() if len(lanes) else 0):
        some = np.flatnonzero(lanes & (1 << i))
        last = np.full(len(rows), -1, np.int64)
        last[number[some]] = some
        of[last[last >= 0]] |= 1 << i
    some = np.flatnonzero(of)
    return rows[number[some]], source[some], of[some]
