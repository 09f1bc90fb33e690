"""The experiments, on the given tables and generated graphs: each gives a table of runs or counts.

p is a logical number of places. On one machine the counts (volume, balance, levels, redundancy) are the evidence; seconds
are measured too, and compare methods on equal footing only. Rates are those of 16 sources of the largest component, whose
searches share their supersteps; construction is not timed.
"""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, components, cost_model, graphs, grid, kernels, local, metrics, prep, rmat, rows
from .graphs import Graph
from .layout import PLACE_ARCS, GridLayout, RowLayout, closest_square
from .loop import Traversal
from .session import kept, stored

#: Searches of a rate, threads of a process on the two machines, and places of the scaling runs.
SEARCHES, FEW_THREADS, MORE_THREADS, PLACES = 16, 4, 6, (1, 4, 9, 16, 36)
#: Graphs of the strong scaling runs, and their places with more threads: the same, and two blocks of six.
STRONG, MORE_PLACES = ("rmat:14", "purchase", "supply"), (1, 4, 9, 12, 16, 36)
FOUR = ("rows_flat", "rows_hybrid", "grid_flat", "grid_hybrid")
#: Points of equal edges and falling density: scale and edge factor.
DENSITIES = ((13, 64), (15, 16), (17, 4))
SEARCHES_OF: dict[str, Callable[[Graph, list[int], int, int], Traversal]] = {
    "rows_flat": lambda g, s, p, t: rows.bfs_rows(g, s, RowLayout(p)),
    "rows_hybrid": lambda g, s, p, t: rows.bfs_rows(g, s, RowLayout(p), threads=t),
    "grid_flat": lambda g, s, p, t: grid.bfs_grid(g, s, GridLayout(*closest_square(p))),
    "grid_hybrid": lambda g, s, p, t: grid.bfs_grid(g, s, GridLayout(*closest_square(max(p // t, 1))), threads=t),
}
METHODS: dict[str, Callable[[Graph, list[int], int, int], DataFrame]] = {
    **{name: lambda g, s, p, t, f=f: f(g, s, p, t).levels for name, f in SEARCHES_OF.items()},
    "reference": lambda g, s, p, t: _each(g, s, lambda one: baselines.bfs_reference(g, one, p).levels),
    "messages": lambda g, s, p, t: baselines.bfs_messages(g, s, p),
    "local": lambda g, s, p, t: local.bfs_local(g, s, t),
    "local_shared": lambda g, s, p, t: local.bfs_local(g, s, t, "shared"),
    "local_bag": lambda g, s, p, t: local.bfs_local(g, s, t, "bag"),
}
RUNS = "graph string, method string, p int, threads int, searches int, reached long, farthest int, edges long, mean_seconds double, teps double"
_loaded: dict[tuple, Graph] = {}


def _each(graph: Graph, sources: list[int], run: Callable[[int], DataFrame]) -> DataFrame:
    out = None
    for s in sources:
        one = run(s).select(F.lit(s).cast("long").alias("source"), "*")
        out = one if out is None else out.unionAll(one)
    return out


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A table graph by name, or rmat:scale or rmat:scale:edge_factor; its arcs are stored once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _loaded:
        made = rmat.rmat(spark, *map(int, name.split(":")[1:])) if name.startswith("rmat:") else graphs.GRAPHS[name](spark, sf_dir)
        _loaded[key] = Graph(stored(made.arcs, "arcs"), made.directed)
    return _loaded[key]


_sampled: dict[tuple, list[int]] = {}
_largest: dict[tuple, tuple[DataFrame, int, int]] = {}
_searched: dict[tuple, Graph] = {}


def largest(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, int, int]:
    """Vertices of the largest component, stored once a session, how many they are, and how many all are."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _largest:
        found = components.components(load(spark, sf_dir, name))
        inside = stored(components.largest_of(found), "largest")
        _largest[key] = inside, inside.count(), found.count()
    return _largest[key]


def sources(spark: SparkSession, sf_dir: str, name: str, k: int = SEARCHES) -> list[int]:
    key = (spark.sparkContext.applicationId, sf_dir, name, k)
    if key not in _sampled:
        _sampled[key] = components.sample_sources(load(spark, sf_dir, name), k, largest=largest(spark, sf_dir, name)[0])
    return _sampled[key]


def searched(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """What the searches from the sources can reach: all arcs of the largest component, or of a graph of which that is over
    half of the vertices, or which is small, the graph itself."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _searched:
        g, (inside, n, of) = load(spark, sf_dir, name), largest(spark, sf_dir, name)
        if 2 * n <= of and g.arcs.count() > PLACE_ARCS:
            known = F.broadcast(inside) if n <= components.BROADCAST_IDS else inside
            g = Graph(stored(g.arcs.join(known.withColumnRenamed("vertex", "src"), "src", "left_semi"), "arcs"), g.directed)
        _searched[key] = g
    return _searched[key]


def runs(spark: SparkSession, sf_dir: str, names: list[str], methods: tuple[str, ...], places: tuple[int, ...], threads: int = 2, searches: int = SEARCHES) -> DataFrame:
    """RUNS: for each graph, method and number of places what all searches reached together, and their mean time and rate."""
    out = []
    for name in names:
        g, found = searched(spark, sf_dir, name), sources(spark, sf_dir, name, searches)
        degree = kept(prep.degrees(g.arcs))
        for method in methods:
            for p in places:
                began = time.perf_counter()
                met = SEARCHES_OF[method](g, found, p, threads).met if method in SEARCHES_OF else None  # levels are stored
                if met is None:
                    met = kept(METHODS[method](g, found, p, threads)).select("vertex", "dist", F.lit(1).alias("searches"))
                seconds = (time.perf_counter() - began) / len(found)
                reached, farthest, arcs = met.join(degree, "vertex", "left").agg(F.coalesce(F.sum("searches"), F.lit(0)), F.max("dist"), F.coalesce(F.sum(F.col("searches") * F.col("degree")), F.lit(0))).first()
                edges = arcs if g.directed else arcs // 2
                out.append((name, method, p, threads, len(found), reached, farthest, edges, seconds, metrics.teps(edges / len(found), seconds)))
    return spark.createDataFrame(out, RUNS)


def strong_rows_vs_grid(spark: SparkSession, sf_dir: str, places: tuple[int, ...] = PLACES) -> DataFrame:
    return runs(spark, sf_dir, list(STRONG), FOUR, places, FEW_THREADS)


def strong_six_threads(spark: SparkSession, sf_dir: str, places: tuple[int, ...] = MORE_PLACES) -> DataFrame:
    return runs(spark, sf_dir, list(STRONG), FOUR, places, MORE_THREADS)


def one_search(spark: SparkSession, sf_dir: str, name: str) -> tuple[Graph, DataFrame]:
    """A graph and the levels from the first of its sources."""
    g = load(spark, sf_dir, name)
    return g, kept(rows.bfs_rows(g, sources(spark, sf_dir, name)[0]).levels)


def strong_comm(spark: SparkSession, sf_dir: str, name: str = "purchase", places: tuple[int, ...] = (4, 16, 64)) -> DataFrame:
    """(p, rows_shipped, grid_expanded, grid_folded): words that leave their place in a whole search, ids dealt in turn."""
    (g, levels), out = one_search(spark, sf_dir, name), []
    g, levels, n = dense(g, levels)
    for p in places:
        shipped = metrics.volume_rows(g, levels, RowLayout(p, n)).agg(F.sum("shipped")).first()[0]
        split = metrics.phase_split(metrics.volume_grid(g, levels, GridLayout(*closest_square(p), n))).first()
        out.append((p, shipped, split["expanded"], split["folded"]))
    return spark.createDataFrame(out, "p int, rows_shipped long, grid_expanded long, grid_folded long")


def dense(graph: Graph, levels: DataFrame) -> tuple[Graph, DataFrame, int]:
    """Both on shuffled dense ids, so that layouts go by range, and the number of ids."""
    arcs, mapping = prep.relabel(graph.arcs, "shuffle")
    mapping = kept(mapping)
    moved = levels.join(mapping.withColumnRenamed("old", "vertex"), "vertex").select(F.col("new").alias("vertex"), "dist")
    return Graph(kept(arcs), graph.directed), kept(moved), mapping.count()


def comm_share(spark: SparkSession, sf_dir: str, name: str = "rmat:12", places: tuple[int, ...] = (4, 16)) -> DataFrame:
    """(method, p, megabytes, run_seconds, comm_seconds, share) by the tasks' own metrics: what was written to and read from
    shuffles, and how long tasks wrote and waited for it. Work of the level loop only."""
    g, out = load(spark, sf_dir, name), []
    source = sources(spark, sf_dir, name)[0]
    for p in places:
        for method in ("rows_flat", "grid_flat", "grid_hybrid"):
            with metrics.TaskMeter(spark) as meter:
                kept(METHODS[method](g, [source], p, 2))
            out.append((method, p, meter.megabytes, meter.run_seconds, meter.comm_seconds, meter.comm_seconds / max(meter.run_seconds, 1e-9)))
    return spark.createDataFrame(out, "method string, p int, megabytes double, run_seconds double, comm_seconds double, share double")


def comm_share_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n, m, p, method, share): the model's communication share at the published sizes, and for as many vertices with the
    density of a graph of the tables."""
    vertices, arcs = graphs.counts(graphs.supply(spark, sf_dir))
    out, table = [], (1 << 32, (arcs << 32) // max(vertices, 1))
    for p, (n, m) in [(p, point) for point in ((1 << 32, 1 << 36), table) for p in (1024, 4096, 10_000, 20_000, 40_000)]:
        cost = cost_model.predict(n, m, p)
        out += [(n, m, p, "rows", cost["rows_comm"] / cost["rows"]), (n, m, p, "grid", cost["grid_comm"] / cost["grid"])]
    return spark.createDataFrame(out, "n long, m long, p int, method string, share double")


def weak(spark: SparkSession, sf_dir: str, points: tuple[tuple[int, int], ...] = ((10, 1), (12, 4), (14, 16))) -> DataFrame:
    """Edges a place fixed: scale and places grow together."""
    out = None
    for scale, p in points:
        one = runs(spark, sf_dir, [f"rmat:{scale}"], FOUR, (p,))
        out = one if out is None else out.unionAll(one)
    return out


def density(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = (*(f"rmat:{s}:{f}" for s, f in DENSITIES), "sourcing", "supply", "purchase", "basket"), p: int = 9) -> DataFrame:
    return runs(spark, sf_dir, list(names), ("rows_flat", "grid_flat"), (p,))


def phase_table(spark: SparkSession, sf_dir: str, points: tuple[tuple[int, int], ...] = DENSITIES, places: tuple[int, ...] = (4, 9, 16)) -> DataFrame:
    """(scale, edge_factor, p, expanded, folded, expand_share): equal edges, density and places varied; shuffled ids."""
    out = []
    for scale, factor in points:
        g, levels, n = dense(*one_search(spark, sf_dir, f"rmat:{scale}:{factor}"))
        for p in places:
            r = metrics.phase_split(metrics.volume_grid(g, levels, GridLayout(*closest_square(p), n))).first()
            out.append((scale, factor, p, r["expanded"], r["folded"], r["expand_share"]))
    return spark.createDataFrame(out, "scale int, edge_factor int, p int, expanded long, folded long, expand_share double")


def deep_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RUNS of the deepest graph, which a task holds, and of the web graph by all forms."""
    deep = runs(spark, sf_dir, ["trail"], ("local",), (1,))
    return deep.unionAll(runs(spark, sf_dir, ["weblinks"], ("local", "grid_flat", "grid_hybrid"), (4,)))


def versus_reference(spark: SparkSession, sf_dir: str, name: str = "rmat:11", places: tuple[int, ...] = (4, 8, 16)) -> DataFrame:
    """(p, own_shipped, reference_shipped, ratio): pairs sent to owners, combined before they leave or not."""
    g, out = load(spark, sf_dir, name), []
    source = sources(spark, sf_dir, name)[0]
    for p in places:
        own = rows.bfs_rows(g, source, RowLayout(p, 1 << 11), trace=True).trace.agg(F.sum("candidates")).first()[0]
        ref = baselines.bfs_reference(g, source, p, trace=True).trace.agg(F.sum("shipped")).first()[0]
        out.append((p, own, ref, round(ref / own, 6)))
    return spark.createDataFrame(out, "p int, own_shipped long, reference_shipped long, ratio double")


def versus_library(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("rmat:12", "rmat:14"), places: tuple[int, ...] = (4, 9)) -> DataFrame:
    return runs(spark, sf_dir, list(names), ("grid_flat", "messages"), places)


def single_node(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("rmat:14", "supply", "nearvec")) -> DataFrame:
    return runs(spark, sf_dir, list(names), ("local", "local_shared", "local_bag"), (1,), FEW_THREADS)


def kernel_crossover(spark: SparkSession, sf_dir: str, columns: tuple[int, ...] = (1, 2, 4, 8, 16, 32)) -> DataFrame:
    """(p_c, cells, entries, spa_words, heap_words, heap_seconds, spa_seconds): the merges of all cells of a grid of one row,
    by every column, as the grid gets wider. Cells are cut by rows in pieces, the same at every width, so arcs are sent once
    and a task packs and merges its piece of each cell of each width."""
    g, n, out = load(spark, sf_dir, "purchase"), 1 << 15, []
    pieces = -(-g.arcs.count() // 100_000) or 1

    def timed(table: pa.Table) -> pa.Table:
        row, col = (table.column(c).to_numpy() for c in ("row", "col"))
        order = np.argsort(col, kind="stable")
        row, col, found = row[order], col[order], []
        for p_c in columns:
            for cell, packed in kernels.cells_of(row, col, n, p_c):
                jc, cp, ir, rows_ = next(kernels.lists_of(packed, "jc", "cp", "ir", "rows"))
                source, number = kernels.gather(jc, cp, ir, jc)
                seconds = []
                for kernel in ("heap", "spa"):
                    began = time.perf_counter()
                    kernels.merge(source, number, kernel, len(rows_))
                    seconds.append(time.perf_counter() - began)
                found.append((p_c, cell, len(number), len(rows_), *seconds))
        return pa.Table.from_pylist([dict(zip(made.names, f, strict=True)) for f in found], made)

    made = pa.schema([("p_c", pa.int32()), ("cell", pa.int32()), ("entries", pa.int64()), ("rows", pa.int64()), ("heap", pa.float64()), ("spa", pa.float64())])
    placed = g.arcs.select(F.pmod(F.xxhash64("dst", F.lit(29)), F.lit(pieces)).cast("int").alias("piece"), F.col("dst").alias("row"), F.col("src").alias("col"))
    merged = placed.groupBy("piece").applyInArrow(lambda t: timed(t), "p_c int, cell int, entries long, rows long, heap double, spa double")
    each = merged.groupBy("p_c").agg(F.countDistinct("cell"), F.sum("entries"), F.sum("rows"), F.sum("heap"), F.sum("spa"))
    found = {r[0]: r[1:] for r in each.collect()}  # a row a width
    for p_c in columns:
        r = found.get(p_c, (0, *[None] * 4))
        out.append((p_c, r[0], r[1], r[2], r[1], r[3], r[4]))
    return spark.createDataFrame(out, "p_c int, cells long, entries long, spa_words long, heap_words long, heap_seconds double, spa_seconds double")


def vector_placement(spark: SparkSession, sf_dir: str, name: str = "rmat:14", side: int = 16) -> DataFrame:
    """(vector, active, rows, most, imbalance): rows that each place of the grid merged, counted in a search, by where the
    vectors lie."""
    g, out, n = load(spark, sf_dir, name), [], 1 << int(name.split(":")[1])
    for vector in ("grid", "diagonal", "row_head"):
        done = grid.bfs_grid(g, sources(spark, sf_dir, name)[0], GridLayout(side, side, n, vector), trace=True)
        each = done.loads.groupBy("place").agg(F.sum("rows").alias("rows"))
        r = each.agg(F.count("*").alias("active"), F.sum("rows").alias("rows"), F.max("rows").alias("most")).first()
        out.append((vector, r["active"], r["rows"], r["most"], round(r["most"] * side * side / r["rows"], 6)))
    return spark.createDataFrame(out, "vector string, active long, rows long, most long, imbalance double")


def redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(graph, pushes, redundant, rate): an upper bound, as every thread checks the state of the level's beginning."""
    out = []
    for name in ("rmat:11", "supply", "purchase", "basket"):
        r = metrics.redundant_rate(local.redundancy(searched(spark, sf_dir, name), sources(spark, sf_dir, name)[0])).first()
        out.append((name, r["pushes"], r["redundant"], r["rate"]))
    return spark.createDataFrame(out, "graph string, pushes long, redundant long, rate double")


def relabel_balance(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("rmat:11", "supply"), blocks: int = 16) -> DataFrame:
    """(graph, mode, most, imbalance, cut, cut_share) of arcs on row blocks by range, under each labelling."""
    out = []
    for name in names:
        g = load(spark, sf_dir, name)
        for mode in ("rank", "shuffle", "locality"):
            arcs, mapping = prep.relabel(g.arcs, mode)
            arcs, layout = kept(arcs), RowLayout(blocks, mapping.count())
            cut, load_ = metrics.edge_cut(Graph(arcs), layout).first(), metrics.imbalance(layout.place(arcs), "owner", blocks).first()
            out.append((name, mode, load_["most"], load_["imbalance"], cut["cut"], round(cut["cut"] / cut["arcs"], 6)))
    return spark.createDataFrame(out, "graph string, mode string, most long, imbalance double, cut long, cut_share double")


def nonempty_expand(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("rmat:11", "basket")) -> DataFrame:
    """(graph, all_sent, nonempty_sent): entries expanded with and without the extra round, ids by range."""
    out = []
    for name in names:
        g, levels, n = dense(*one_search(spark, sf_dir, name))
        source = levels.where("dist = 0").first()["vertex"]
        sent = [grid.bfs_grid(g, source, GridLayout(3, 3, n), only_nonempty=only, trace=True).trace.agg(F.sum("expanded")).first()[0] for only in (False, True)]
        out.append((name, *sent))
    return spark.createDataFrame(out, "graph string, all_sent long, nonempty_sent long")


def headline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RUNS of the four variants on the largest graphs."""
    return runs(spark, sf_dir, ["rmat:14", "basket"], FOUR, (4,))


def model_check(spark: SparkSession, sf_dir: str, points: tuple[tuple[int, int], ...] = DENSITIES) -> DataFrame:
    """(scale, edge_factor, p, counted, predicted): expand over fold by counts and by the model; their ranks should agree."""
    counted = phase_table(spark, sf_dir, points, places=(4, 16)).collect()  # six rows
    out = []
    for r in counted:
        cost = cost_model.predict(1 << r["scale"], r["edge_factor"] << r["scale"], r["p"], cost_model.Machine(alpha_net=0.0))
        out.append((r["scale"], r["edge_factor"], r["p"], round(r["expanded"] / max(r["folded"], 1), 6), round(cost["expand"] / cost["fold"], 6)))
    return spark.createDataFrame(out, "scale int, edge_factor int, p int, counted double, predicted double")


WORKLOADS = {f.__name__: f for f in (strong_rows_vs_grid, strong_comm, strong_six_threads, comm_share, comm_share_model, weak, density, phase_table, deep_graph, versus_reference, versus_library, single_node, kernel_crossover,
                                     vector_placement, redundancy, relabel_balance, nonempty_expand, headline, model_check)}
