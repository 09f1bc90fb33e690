"""Row-partitioned ("1D") traversal: arcs lie with the owner of their source, candidates go to the owner of their target.

All of a vertex's arcs are one place's in the flat form, so the place of the greatest hub bounds it from below; the hybrid
form cuts a block of many arcs into pieces, and the grid spreads every vertex over its cells.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lanes
from .graphs import Graph
from .kernels import BlockCsr, by_source, csr_table, lists_of
from .layout import RowLayout
from .loop import Placement, Traversal, run_levels, seeds_of
from .session import aligned, kept

#: Frontiers of at most so many vertices (16 bytes each) may be broadcast instead of shuffled.
BROADCAST_FRONTIER = 1_000_000
PACKED = "block int, piece int, slot int, vertices array<long>, offsets array<long>, targets array<long>"


def placed_arcs(arcs: DataFrame, layout: RowLayout) -> DataFrame:
    """(owner, src, dst), dealt out by the owner of the source once, before any level."""
    with aligned(arcs.sparkSession, layout.p):
        return kept(layout.place(arcs).repartitionById(layout.p, "owner"))


def bfs_rows(graph: Graph, source: int | list[int] | DataFrame, layout: RowLayout = RowLayout(), threads: int = 1, strategy: str = "shuffle_hash", storage: str = "arcs", visit_check: str = "benign", trace: bool = False,
             **limits: object) -> Traversal:
    """threads > 1: fewer, larger blocks, each expanded by a pool of threads over pieces of its rows (the hybrid form).

    source: a vertex, or several whose searches share the supersteps; levels then have a column source. Rows (vertex, parent)
    are one search from all of them. strategy: how the frontier meets the arcs (shuffle_hash, merge or broadcast). storage "triangle" keeps each edge of an undirected graph
    once and joins it from both ends. trace adds counts to every level, at the price of extra jobs.
    """
    layout, spark = layout if layout.p else layout.sized(graph.arcs.count()), graph.spark
    if lanes.can(graph, source, trace, limits) and strategy == "shuffle_hash" and storage == "arcs":
        return lanes.rows_hybrid(graph, source, layout, threads, visit_check, **limits) if threads > 1 else lanes.rows_flat(graph, source, layout, **limits)
    if threads > 1:
        return _hybrid(graph, source, layout, threads, visit_check, trace, **limits)
    seeds, keys = (seeds_of(spark, source), ("source",)) if isinstance(source, list) else (source, ())
    place = Placement(layout.p, layout.owner, keys)
    half = graph.arcs.where("src < dst") if storage == "triangle" else graph.arcs
    sides = [placed_arcs(half.select(F.col(a).alias("src"), F.col(b).alias("dst")), layout) for a, b in (("src", "dst"), ("dst", "src"))[: 2 if storage == "triangle" else 1]]

    def step(frontier: DataFrame) -> tuple[DataFrame, dict[str, object]]:
        near = frontier.select("owner", *keys, F.col("vertex").alias("src"))
        if strategy == "broadcast" and near.count() <= BROADCAST_FRONTIER:
            near = F.broadcast(near)
        elif strategy != "broadcast":
            near = near.hint(strategy)
        pairs = [arcs.join(near, ["owner", "src"]).select(F.col("owner").alias("sender"), *keys, F.col("dst").alias("vertex"), F.col("src").alias("parent")) for arcs in sides]
        sent = place.put(reduce(DataFrame.unionAll, [place.local(p, "sender") for p in pairs]))
        return place.combined(sent), _counts(reduce(DataFrame.unionAll, pairs), layout) if trace else {}

    return run_levels(spark, seeds, step, place, graph.directed, **limits)


def _counts(pairs: DataFrame, layout: RowLayout) -> dict[str, object]:
    """Arcs scanned, candidates after each sender combined its own, those that leave their sender, and what owners merge."""
    sent = kept(pairs.groupBy("sender", *[k for k in pairs.columns if k == "source"], "vertex").agg(F.count("*").alias("n")).withColumn("owner", layout.owner(F.col("vertex"))))
    got = sent.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*"), F.count(F.when(F.col("sender") != F.col("owner"), 1))).first()
    return {"scanned": got[0], "candidates": got[1], "shipped": got[2], "loads": [tuple(r) for r in sent.groupBy("owner").count().collect()]}  # a row a place


def pack_csr(arcs: DataFrame, layout: RowLayout, chunk: int = 2_000_000) -> tuple[DataFrame, DataFrame, int]:
    """(PACKED, slots, number of slots): sorted rows of each block. A block of more than chunk arcs, such as a hub's, is cut
    into pieces by a hash of the arc, each in a slot (and task) of its own, so no array grows with the graph. slots has
    one row (block, first, pieces) for each block."""
    spark = arcs.sparkSession
    sizes = {r["block"]: r["n"] for r in arcs.groupBy(layout.owner(F.col("src")).alias("block")).agg(F.count("*").alias("n")).collect()}  # a row a block
    cuts = [-(-sizes.get(b, 1) // chunk) for b in range(layout.p)]
    slots = spark.createDataFrame([(b, sum(cuts[:b]), n) for b, n in enumerate(cuts)], "block int, first int, pieces int")
    placed = arcs.select(layout.owner(F.col("src")).alias("block"), "src", "dst").join(F.broadcast(slots), "block")  # a row a block
    piece = F.pmod(F.xxhash64("src", "dst", F.lit(5)), F.col("pieces")).cast("int")
    placed = placed.select("block", piece.alias("piece"), (F.col("first") + piece).alias("slot"), "src", "dst")
    return placed.groupBy("block", "piece", "slot").applyInArrow(lambda t: csr_table(t), PACKED), slots, sum(cuts)


def _hybrid(graph: Graph, source: int, layout: RowLayout, threads: int, visit_check: str, trace: bool, on_visit: Callable | None = None, chunk: int = 4_000_000, **limits: object) -> Traversal:
    blocks = max(layout.p // threads, 1)
    wide, spark = RowLayout(blocks, layout.n), graph.spark
    packed, slots, count = pack_csr(graph.arcs, wide, chunk)
    with aligned(spark, count):
        packed = kept(packed.repartitionById(count, "slot"))
    seeds, keys = (seeds_of(spark, source), ("source",)) if isinstance(source, list) else (source, ())
    place = Placement(blocks, wide.owner, keys)

    def expand(left: pa.Table, right: pa.Table) -> pa.Table:
        packs = [BlockCsr(*arrays) for arrays in lists_of(left, "vertices", "offsets", "targets")]  # one, or none
        found = [by_source(right, "src", lambda part, pack=pack: pack.neighbours(part, threads, visit_check)) for pack in packs]
        out = [np.concatenate([np.empty(0, np.int64), *(f[k] for f in found)]) for k in range(3)]
        return pa.table({name: pa.array(x, pa.int64()) for name, x in zip(("source", "vertex", "parent"), out, strict=True)})

    def step(frontier: DataFrame) -> tuple[DataFrame, dict[str, object]]:
        # A block's part of the frontier goes to each of its pieces.
        near = frontier.join(F.broadcast(slots), F.col("owner") == F.col("block")).select(F.explode(F.sequence("first", F.col("first") + F.col("pieces") - 1)).alias("slot"), *keys, F.col("vertex").alias("src"))
        pairs = packed.groupBy("slot").cogroup(near.repartitionById(count, "slot").groupBy("slot")).applyInArrow(lambda a, b: expand(a, b), "source long, vertex long, parent long")
        counts = {}
        if trace:
            pairs = kept(pairs)
            got = pairs.agg(F.count("*"), F.countDistinct("source", "vertex")).first()
            counts = {"candidates": got[0], "redundant": got[0] - got[1]}
        return place.combined(place.put(pairs)), counts

    return run_levels(spark, seeds, step, place, graph.directed, on_visit=on_visit, **limits)
