"""Grid-partitioned ("2D") traversal: a level is a product of the cells of the adjacency matrix with the sparse frontier.

The frontier is sent from its owners to every cell of its vertices' grid column (transpose and expand in one exchange), each
cell keeps the greatest column of each row it reaches, and rows go to their owner, combined before they leave (fold).
Owners are cells too: all of them, those of the diagonal, or the first of each row, as the layout's vector says.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import lanes
from .graphs import Graph
from .kernels import by_source, csr_cell_table, dcsc_table, gather, gather_dense, lists_of, merge, spmsv_cell
from .layout import GridLayout, block_bounds
from .loop import Placement, Traversal, run_levels, seeds_of
from .rows import BROADCAST_FRONTIER
from .session import aligned, kept

DCSC = "cell int, part int, piece int, jc array<long>, cp array<long>, ir array<long>, rows array<long>"
CSR = "cell int, part int, base long, cp array<long>, jc array<long>, past array<long>, ir array<long>, rows array<long>"
#: Arcs of a cell's part where cells are packed, each part in a task of its own.
PART_ARCS = 2_000_000
#: And where cells are packed for one product: a part is then in a task with its share of the frontier, and is read once.
PRODUCT_ARCS = 500_000
FOUND = "source long, vertex long, parent long"
#: How a frontier meets its cell: as it comes, by hash, or as a sorted sparse vector, by merging.
FORMS = {"stack": "shuffle_hash", "sorted": "merge"}


def transpose_vector(frontier: DataFrame, layout: GridLayout) -> DataFrame:
    """Row-owned entries with the grid column that needs them next."""
    keys = [c for c in frontier.columns if c == "source"]
    return frontier.select(*keys, F.col("vertex").alias("col"), layout.column(F.col("vertex")).alias("j"))


def expand(frontier: DataFrame, layout: GridLayout, filled: DataFrame | None = None) -> DataFrame:
    """(cell, col): each entry at all cells of its grid column, or with filled at those where the column has arcs.

    filled (owner, vertex, cells) lies with the frontier's owners, so what no cell needs isn't sent.
    """
    if filled is not None:
        keys = [c for c in frontier.columns if c == "source"]
        return frontier.join(filled.hint("shuffle_hash"), ["owner", "vertex"]).select(F.explode("cells").alias("cell"), *keys, F.col("vertex").alias("col"))
    moved = transpose_vector(frontier, layout)
    cells = F.transform(F.sequence(F.lit(0), F.lit(layout.p_r - 1)), lambda i: i * layout.p_c + F.col("j"))
    return moved.select(F.explode(cells).alias("cell"), *moved.columns[:-1])


def multiply(cells: DataFrame, expanded: DataFrame) -> DataFrame:
    """(cell, vertex, parent) of every arc from an expanded column, where the arc lies."""
    keys = [c for c in expanded.columns if c == "source"]
    return cells.join(expanded, ["cell", "col"]).select("cell", *keys, F.col("row").alias("vertex"), F.col("col").alias("parent"))


def fold(pairs: DataFrame) -> DataFrame:
    """The greatest parent of each row, wherever it is wanted."""
    return pairs.groupBy("vertex").agg(F.max("parent").alias("parent"))


def placed_cells(graph: Graph, layout: GridLayout) -> DataFrame:
    """(cell, row, col), each cell a partition of its own, sorted by column."""
    with aligned(graph.spark, layout.p):
        return kept(layout.place(graph.arcs).repartitionById(layout.p, "cell").sortWithinPartitions("cell", "col"))


def filled_columns(graph: Graph, layout: GridLayout) -> DataFrame:
    """(owner, vertex, cells): which cells of its grid column a vertex has arcs in, at most p_r, with the vertex's owner."""
    found = layout.place(graph.arcs).groupBy(F.col("col").alias("vertex")).agg(F.collect_set("cell").alias("cells"))
    with aligned(graph.spark, layout.p):
        return kept(found.select(layout.owner(F.col("vertex")).alias("owner"), "vertex", "cells").repartitionById(layout.p, "owner"))


def cell_parts(arcs: DataFrame, layout: GridLayout, chunk: int) -> DataFrame:
    """(cell, parts): in how many parts each cell is packed, by its arcs."""
    sizes = layout.place(arcs).groupBy("cell").agg(F.count("*").alias("n")).collect()  # a row a cell
    return arcs.sparkSession.createDataFrame([(r["cell"], -(-r["n"] // chunk)) for r in sizes], "cell int, parts int")


def part_of(layout: GridLayout) -> Column:
    """The part, of so many (parts), in which a cell (cell) has a column (col): by hash, or where ids go by range the part of
    the block's range, and by hash past it."""
    hashed = F.pmod(F.xxhash64("col", F.lit(31)), F.col("parts"))
    if layout.n is None:
        return hashed.cast("int")
    first = F.element_at(F.array(*[F.lit(a) for a, _ in block_bounds(layout.n, layout.p_c)]), F.col("cell") % layout.p_c + 1)
    end = F.element_at(F.array(*[F.lit(b) for _, b in block_bounds(layout.n, layout.p_c)]), F.col("cell") % layout.p_c + 1)
    return F.when(F.col("col") < end, F.floor((F.col("col") - first) / F.ceil((end - first) / F.col("parts")))).otherwise(hashed).cast("int")


def placed_parts(arcs: DataFrame, layout: GridLayout, parts: DataFrame) -> DataFrame:
    """(cell, parts, part, row, col) of all arcs."""
    placed = layout.place(arcs).join(F.broadcast(parts), "cell")  # a row a cell
    return placed.select("cell", "parts", part_of(layout).alias("part"), "row", "col")


def pack_dcsc(arcs: DataFrame, layout: GridLayout, threads: int = 1, chunk: int = PART_ARCS, parts: DataFrame | None = None) -> DataFrame:
    """Cells in DCSC form. A cell of more than chunk arcs is cut by columns in parts, so no array grows with the graph, and a
    part by rows in as many pieces as threads; piece sizes follow the grid, not the graph's hubs."""
    placed = placed_parts(arcs, layout, cell_parts(arcs, layout, chunk) if parts is None else parts)
    piece = F.pmod(F.xxhash64("row", F.lit(29)), F.lit(threads)).cast("int")
    return placed.select("cell", "part", piece.alias("piece"), "row", "col").groupBy("cell", "part", "piece").applyInArrow(lambda t: dcsc_table(t), DCSC)


def pack_csr_cells(arcs: DataFrame, layout: GridLayout, chunk: int = PART_ARCS, parts: DataFrame | None = None) -> DataFrame:
    """Cells with a pointer for every column of their block, empty or not: what the doubly compressed form does without.
    Parts of a cell share its columns out."""
    if layout.n is None:
        raise ValueError("pointers for all columns need a layout by range")
    bounds, columns = block_bounds(layout.n, layout.p_c), layout.p_c
    parts = cell_parts(arcs, layout, chunk) if parts is None else parts
    each = parts.select("cell", "parts", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(None).cast("long").alias("row"), F.lit(None).cast("long").alias("col"))
    placed = placed_parts(arcs, layout, parts).unionByName(each)  # a part without arcs has its pointers, too
    return placed.groupBy("cell", "part").applyInArrow(lambda t: csr_cell_table(t, bounds, columns), CSR)


def _table(source: np.ndarray, vertex: np.ndarray, parent: np.ndarray) -> pa.Table:
    return pa.table({"source": pa.array(source, pa.int64()), "vertex": pa.array(vertex, pa.int64()), "parent": pa.array(parent, pa.int64())})


def _multiplier(kernel: str, threads: int, places: int):  # noqa: ANN202
    """A cell in pieces (left) times its part of the frontier (right)."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        parts = list(lists_of(left, "jc", "cp", "ir", "rows"))
        return _table(*by_source(right, "col", lambda frontier: spmsv_cell(parts, frontier, kernel, threads, places)))

    return run


def bfs_grid(graph: Graph, source: int | list[int], layout: GridLayout = GridLayout(), threads: int = 1, kernel: str = "auto", mode: str = "replicate", only_nonempty: bool = False, frontier_form: str = "stack",
             trace: bool = False, **limits: object) -> Traversal:
    """threads > 1: cells in DCSC pieces of disjoint rows, multiplied by a pool of threads (the hybrid form).

    source: a vertex, or several whose searches share the supersteps (flat form; levels then have a column source). kernel:
    heap, spa, or auto (by places and size). mode broadcast sends a frontier of checked size to all places. only_nonempty
    sends entries only to cells that have arcs for them. frontier_form: stack, or sorted.
    """
    layout, spark = layout if layout.p_r else layout.sized(graph.arcs.count()), graph.spark
    if lanes.can(graph, source, trace, limits) and (kernel, mode, only_nonempty, frontier_form) == ("auto", "replicate", False, "stack"):
        return lanes.grid_hybrid(graph, source, layout, threads, PART_ARCS, **limits) if threads > 1 else lanes.grid_flat(graph, source, layout, **limits)
    p, seeds, keys = layout.p, *((seeds_of(graph.spark, source), ("source",)) if isinstance(source, list) else (source, ()))
    place = Placement(p, layout.owner, keys)
    filled = filled_columns(graph, layout) if only_nonempty else None
    if threads > 1:
        with aligned(spark, p):
            packed = kept(pack_dcsc(graph.arcs, layout, threads).repartitionById(p, "cell"))
        run = _multiplier(kernel, threads, p)

        def hybrid(frontier: DataFrame) -> tuple[DataFrame, dict[str, object]]:
            sent = expand(frontier, layout, filled).repartitionById(p, "cell")
            pairs = packed.groupBy("cell").cogroup(sent.groupBy("cell")).applyInArrow(lambda a, b: run(a, b), FOUND)
            return place.combined(place.put(pairs)), {}

        return run_levels(spark, seeds, hybrid, place, graph.directed, **limits)

    cells = placed_cells(graph, layout)

    def step(frontier: DataFrame) -> tuple[DataFrame, dict[str, object]]:
        if mode == "broadcast" and frontier.count() <= BROADCAST_FRONTIER:
            sent = F.broadcast(expand(frontier, layout, filled))
        else:
            sent = expand(frontier, layout, filled).repartitionById(p, "cell").hint(FORMS[frontier_form])
        pairs = multiply(cells, sent)
        counts = {}
        if trace:
            each = kept(pairs.groupBy("cell", *keys, "vertex").agg(F.count("*").alias("n"), F.max("parent").alias("parent")))
            away = F.count(F.when(F.col("cell") != layout.owner(F.col("vertex")), 1))
            got = each.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*"), away).first()
            arrived = kept(place.put(each))
            loads = arrived.groupBy(F.spark_partition_id().alias("place")).count().collect()  # a row a place
            counts = {"scanned": got[0], "candidates": got[1], "folded": got[2], "expanded": expand(frontier, layout, filled).count(), "loads": [tuple(r) for r in loads]}
            return place.combined(arrived), counts
        return place.merged(pairs, "cell"), counts

    return run_levels(spark, seeds, step, place, graph.directed, **limits)


def spmsv(arcs: DataFrame, frontier: DataFrame, layout: GridLayout, kernel: str = "auto", threads: int = 1, storage: str = "dcsc", chunk: int | None = None) -> DataFrame:
    """One product over the (select, max) semiring: (vertex, parent) of all rows that the frontier (vertex) reaches.

    kernel sql leaves it to a hash aggregate, which spills; heap, spa and auto run on packed cells: dcsc, or csr with a
    pointer for every column (layouts by range). A cell of more than chunk arcs is multiplied in parts, each by its own
    columns of the frontier.
    """
    sent, chunk = expand(frontier, layout), chunk or PRODUCT_ARCS
    if kernel == "sql":
        return fold(multiply(layout.place(arcs), sent))
    parts, run, places = cell_parts(arcs, layout, chunk), _multiplier(kernel, threads, layout.p), layout.p
    if storage == "csr":
        packed = pack_csr_cells(arcs, layout, chunk, parts)

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            def times(frontier: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
                frontier, found = np.unique(frontier), []
                for base, (cp, jc, past, ir, rows) in zip(left.column("base").to_pylist(), lists_of(left, "cp", "jc", "past", "ir", "rows"), strict=True):
                    both = zip(gather_dense(base, cp, ir, frontier), gather(jc, past, ir, frontier), strict=True)
                    at, best = merge(*map(np.concatenate, both), kernel, len(rows), places)
                    found.append((rows[at], best))
                return tuple(np.concatenate([np.empty(0, np.int64), *(f[k] for f in found)]) for k in range(2))

            return _table(*by_source(right, "col", times))
    else:
        packed = pack_dcsc(arcs, layout, threads, chunk, parts)

    needed = sent.join(F.broadcast(parts), "cell").withColumn("part", part_of(layout)).drop("parts")  # a row a cell
    return fold(packed.groupBy("cell", "part").cogroup(needed.groupBy("cell", "part")).applyInArrow(lambda a, b: run(a, b), FOUND))
