"""Registered queries over the given tables, each with its DuckDB text where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, components, cost_model, graphs, grid, local, metrics, oracle, prep, rmat, rows, traversal_ops, validate
from .graphs import Graph
from .layout import GridLayout, RowLayout
from .session import importable, kept, stored

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
#: Grids whose size follows the graph.
SQUARE, WIDE = GridLayout(), GridLayout(wide=True)
_arcs: dict[tuple, Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str, **options: object) -> Graph:
    """A graph of the tables, its arcs stored once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name, tuple(options.items()))
    if key not in _arcs:
        made = rmat.rmat(spark, **options) if name == "rmat" else graphs.GRAPHS[name](spark, sf_dir, **options)
        _arcs[key] = Graph(stored(made.arcs, "arcs"), made.directed)
    return _arcs[key]


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            importable(spark)
            return f(spark, sf_dir)

        QUERIES[name] = run
        if sql:
            SQL[name] = sql
        return f

    return add


def _levels(name: str, graph_name: str, source: int, run: Callable[[Graph, int], DataFrame], **options: object) -> None:
    query(name, oracle.levels(graph_name, source))(lambda s, d: run(graph(s, d, graph_name, **options), source))


# --- traversals: every variant gives the same rows ---------------------------------------------------------------------
for _g in ("supply", "purchase", "basket"):
    _levels(f"rows_flat_{_g}", _g, 0, lambda g, s: rows.bfs_rows(g, s).levels)
_levels("rows_flat_sourcing", "sourcing", 2, lambda g, s: rows.bfs_rows(g, s).levels)
_levels("rows_merge_join", "supply", 0, lambda g, s: rows.bfs_rows(g, s, strategy="merge").levels)
_levels("rows_broadcast_frontier", "purchase", 0, lambda g, s: rows.bfs_rows(g, s, strategy="broadcast").levels)
for _g in ("supply", "basket"):
    _levels(f"rows_hybrid_{_g}", _g, 0, lambda g, s: rows.bfs_rows(g, s, threads=2).levels)
for _g in ("supply", "purchase"):
    _levels(f"grid_flat_{_g}", _g, 0, lambda g, s: grid.bfs_grid(g, s, SQUARE).levels)
_levels("grid_flat_rect_basket", "basket", 0, lambda g, s: grid.bfs_grid(g, s, WIDE).levels)
_levels("grid_hybrid_purchase", "purchase", 0, lambda g, s: grid.bfs_grid(g, s, SQUARE, threads=2).levels)
_levels("grid_diagonal_vector", "supply", 0, lambda g, s: grid.bfs_grid(g, s, GridLayout(vector="diagonal")).levels)
_levels("grid_rowhead_vector", "supply", 0, lambda g, s: grid.bfs_grid(g, s, GridLayout(vector="row_head")).levels)
_levels("grid_sorted_frontier", "supply", 0, lambda g, s: grid.bfs_grid(g, s, SQUARE, frontier_form="sorted").levels)
_levels("grid_nonempty_expand", "purchase", 0, lambda g, s: grid.bfs_grid(g, s, SQUARE, only_nonempty=True).levels)
_levels("grid_broadcast_expand", "purchase", 0, lambda g, s: grid.bfs_grid(g, s, SQUARE, mode="broadcast").levels)
for _store in ("local", "shared", "bag"):
    _levels(f"local_threads_{_store}", "supply", 0, lambda g, s, k=_store: local.bfs_local(g, s, 6, k))
_levels("local_threads_atomic", "supply", 0, lambda g, s: local.bfs_local(g, s, 6, visit_check="atomic"))
_levels("serial_two_stack", "supply", 0, lambda g, s: local.bfs_serial(g, s))
_levels("serial_queue", "supply", 0, lambda g, s: local.bfs_serial(g, s, "queue"))
_levels("reference_plain", "basket", 0, lambda g, s: baselines.bfs_reference(g, s).levels)
_levels("reference_replicated", "basket", 0, lambda g, s: baselines.bfs_reference(g, s, replicated=True).levels)
_levels("message_library", "basket", 0, lambda g, s: baselines.bfs_messages(g, s))
_levels("directed_hierarchy", "hierarchy", 5, lambda g, s: rows.bfs_rows(g, s).levels)
_levels("directed_hierarchy_grid", "hierarchy", 5, lambda g, s: grid.bfs_grid(g, s, WIDE).levels)
_levels("undirected_weblinks", "weblinks", 6, lambda g, s: rows.bfs_rows(g, s).levels)
_levels("triangle_bfs", "basket", 0, lambda g, s: rows.bfs_rows(g, s, storage="triangle").levels)
_levels("knn_bfs", "nearvec", 11, lambda g, s: rows.bfs_rows(g, s).levels)
_levels("knn_all_bfs", "nearvec_all", 11, lambda g, s: rows.bfs_rows(g, s).levels)
query("directed_weblinks", oracle.levels("weblinks", 6, directed=True))(lambda s, d: rows.bfs_rows(graph(s, d, "weblinks", directed=True), 6).levels)
_FIRST_EVENT = "(SELECT event_id * 16 + 8 FROM events WHERE user_id = 0 ORDER BY ts, event_id LIMIT 1)"
_LAST_EVENT = "(SELECT max(event_id) * 16 + 8 FROM events WHERE user_id = (SELECT max(user_id) FROM events))"


@query("trail_deep", oracle.levels("trail", _LAST_EVENT))
def _trail(s: SparkSession, d: str) -> DataFrame:
    events = s.read.parquet(f"{d}/events.parquet")
    last = events.join(F.broadcast(events.agg(F.max("user_id").alias("user_id"))), "user_id").agg(F.max("event_id")).first()[0]
    return local.bfs_local(graph(s, d, "trail"), last * 16 + 8)


@query("recursive_sql", oracle.levels("basket", 0, bound=2))
def _recursive(s: SparkSession, d: str) -> DataFrame:
    graph(s, d, "basket").arcs.createOrReplaceTempView("levelwave_arcs")
    return baselines.bfs_recursive_sql(s, "levelwave_arcs", 0, 2)


# --- the product of one level ------------------------------------------------------------------------------------------
_PRODUCT = f"WITH {oracle.arcs('purchase')} SELECT dst AS vertex, max(src) AS parent FROM arcs GROUP BY dst"
_DENSE = 1 << 17


def _product(kernel: str, storage: str = "dcsc") -> Query:
    """By a frontier of all vertices."""

    def run(s: SparkSession, d: str) -> DataFrame:
        arcs = graph(s, d, "purchase").arcs
        layout = GridLayout(2, 3, _DENSE) if storage == "csr" else WIDE.sized(arcs.count())
        return grid.spmsv(arcs, arcs.select(F.col("src").alias("vertex")).distinct(), layout, kernel, threads=2, storage=storage)

    return run


for _k in ("heap", "spa", "auto", "sql"):
    query(f"kernel_{_k}", _PRODUCT)(_product(_k))
query("kernel_csr_cells", _PRODUCT)(_product("auto", "csr"))


@query("mask_accumulate", f"WITH RECURSIVE {oracle.with_levels('supply', 0, bound=2)} SELECT dist, count(*) AS vertices, max(vertex) AS greatest FROM lv GROUP BY dist")
def _mask(s: SparkSession, d: str) -> DataFrame:
    return rows.bfs_rows(graph(s, d, "supply"), 0, max_level=2, mask="all").levels.groupBy("dist").agg(F.count("*").alias("vertices"), F.max("vertex").alias("greatest"))


# --- components, generator, preparation --------------------------------------------------------------------------------
query("dialog_components", oracle.components("dialog") + " SELECT vertex, component FROM c")(lambda s, d: components.components(graph(s, d, "dialog")))
query("component_sizes_weblinks", oracle.components("weblinks") + " SELECT component, count(*) AS n FROM c GROUP BY component")(
    lambda s, d: components.components(graph(s, d, "weblinks")).groupBy("component").agg(F.count("*").alias("n")))
query("rmat_edges_s11", oracle.rmat_edges(11, 16))(lambda s, d: rmat.rmat_edges(s, 11))
query("rmat_degree_s11", f"WITH {oracle.arcs('', False, oracle.rmat_edges(11, 16))} SELECT src AS vertex, count(*) AS degree FROM arcs GROUP BY src")(
    lambda s, d: prep.degrees(graph(s, d, "rmat", scale=11).arcs))
query("rmat_bfs_s11", oracle.levels("", 0, directed=False, edges=oracle.rmat_edges(11, 16)))(lambda s, d: rows.bfs_rows(graph(s, d, "rmat", scale=11), 0).levels)
# The name is of the generated graph that it once searched; like that, this one is laid out by range.
@query("grid_hybrid_rmat", oracle.levels("sourcing", 2))
def _hybrid_range(s: SparkSession, d: str) -> DataFrame:
    arcs = graphs.sourcing(s, d).arcs
    layout, top = SQUARE.sized(arcs.count()), arcs.agg(F.max("src")).first()[0]
    return grid.bfs_grid(Graph(kept(arcs)), 2, GridLayout(layout.p_r, layout.p_c, (top or 0) + 1), threads=2).levels


query("symmetrized_edges", f"WITH {oracle.arcs('supply')} SELECT src, dst FROM arcs")(lambda s, d: graph(s, d, "supply").arcs)
query("simplified_edges", f"WITH e AS ({oracle.EDGES['basket']}) SELECT DISTINCT src, dst FROM e WHERE src <> dst")(
    lambda s, d: prep.simplify(s.read.parquet(f"{d}/lineitem.parquet").selectExpr("l_partkey * 16 AS src", "l_orderkey * 16 + 3 AS dst")))
query("triangle_edges", f"WITH {oracle.arcs('supply')} SELECT src, dst FROM arcs WHERE src < dst")(lambda s, d: prep.triangle(graph(s, d, "supply").arcs))
query("copies_edges", f"WITH {oracle.arcs('copies')} SELECT src, dst FROM arcs WHERE src < dst")(lambda s, d: prep.triangle(graph(s, d, "copies").arcs))
query("knn_edges", f"WITH {oracle.arcs('nearvec')} SELECT src, dst FROM arcs")(lambda s, d: graph(s, d, "nearvec").arcs)
query("knn_all_edges", f"WITH {oracle.arcs('nearvec_all')} SELECT src, dst FROM arcs")(lambda s, d: graph(s, d, "nearvec_all").arcs)


@query("relabel_bijection", f"WITH {oracle.arcs('basket')}, n AS (SELECT count(DISTINCT src) AS n, count(*) AS m FROM arcs) SELECT mode, n AS vertices, n AS labels, m AS arcs FROM n, (VALUES ('feistel'), ('shuffle'), ('locality'), ('rank'), ('identity')) t(mode)")
def _relabel(s: SparkSession, d: str) -> DataFrame:
    out = None
    for mode in ("feistel", "shuffle", "locality", "rank", "identity"):
        arcs, mapping = prep.relabel(graph(s, d, "basket").arcs, mode)
        one = mapping.agg(F.countDistinct("old").alias("vertices"), F.countDistinct("new").alias("labels")).join(F.broadcast(arcs.distinct().agg(F.count("*").alias("arcs"))), F.lit(True))
        one = one.select(F.lit(mode).alias("mode"), "vertices", "labels", "arcs")
        out = one if out is None else out.unionAll(one)
    return out


@query("relabel_bfs", f"WITH RECURSIVE {oracle.with_levels('basket', 0)} SELECT vertex, dist FROM lv")
def _relabel_bfs(s: SparkSession, d: str) -> DataFrame:
    g = graph(s, d, "basket")
    arcs, mapping = prep.relabel(g.arcs, "feistel", seed=3)
    mapping = kept(mapping)
    start = mapping.where("old = 0").first()["new"]
    found = rows.bfs_rows(Graph(kept(arcs)), start).levels
    return found.join(mapping, F.col("vertex") == F.col("new")).select(F.col("old").alias("vertex"), "dist")


@query("csr_pack", f"WITH {oracle.arcs('supply')} SELECT src AS vertex, count(*) AS degree, min(dst) AS first, max(dst) AS last FROM arcs GROUP BY src")
def _csr(s: SparkSession, d: str) -> DataFrame:
    packed, _, _ = rows.pack_csr(graph(s, d, "supply").arcs, RowLayout(4))
    each = packed.select(F.posexplode("vertices").alias("k", "vertex"), "offsets", "targets")
    own = F.slice("targets", F.get("offsets", F.col("k")).cast("int") + 1, (F.get("offsets", F.col("k") + 1) - F.get("offsets", F.col("k"))).cast("int"))
    each = each.select("vertex", F.size(own).cast("long").alias("degree"), F.get(own, F.lit(0)).alias("first"), F.element_at(own, -1).alias("last"))
    # A vertex of a block that was cut has a row in each of its pieces.
    return each.groupBy("vertex").agg(F.sum("degree").alias("degree"), F.min("first").alias("first"), F.max("last").alias("last"))


_CELL = f"least(dst // {_DENSE // 2}, 1) * 3 + least(src // {_DENSE // 3}, 2)"


@query("dcsc_pack", f"WITH {oracle.arcs('supply')} SELECT CAST({_CELL} AS INT) AS cell, count(DISTINCT src) AS nzc, count(*) AS nnz, sum(src)::BIGINT AS columns, sum(dst)::BIGINT AS rows FROM arcs GROUP BY 1")
def _dcsc(s: SparkSession, d: str) -> DataFrame:
    packed = grid.pack_dcsc(graph(s, d, "supply").arcs, GridLayout(2, 3, _DENSE))
    spread = F.aggregate(F.transform("jc", lambda c, k: c * (F.get("cp", k + 1) - F.get("cp", k))), F.lit(0).cast("long"), lambda a, x: a + x)
    each = packed.select("cell", F.size("jc").cast("long").alias("nzc"), F.size("ir").cast("long").alias("nnz"), spread.alias("columns"), F.aggregate("ir", F.lit(0).cast("long"), lambda a, x: a + F.get("rows", x.cast("int"))).alias("rows"))
    return each.groupBy("cell").agg(*[F.sum(c).alias(c) for c in ("nzc", "nnz", "columns", "rows")])  # parts have columns of their own


query("csr_cells_pack", f"WITH {oracle.arcs('supply')}, b(j, columns) AS (VALUES (0, {_DENSE // 3}), (1, {_DENSE // 3}), (2, {_DENSE - 2 * (_DENSE // 3)})) SELECT cell, columns + 1 AS pointers, nnz FROM (SELECT CAST({_CELL} AS INT) AS cell, count(*) AS nnz FROM arcs GROUP BY 1) JOIN b ON j = cell % 3")(
    lambda s, d: grid.pack_csr_cells(graph(s, d, "supply").arcs, GridLayout(2, 3, _DENSE)).groupBy("cell").agg((F.sum(F.size("cp") - 1) + 1).alias("pointers"), F.sum(F.size("ir")).alias("nnz")))
query("storage_measured", f"WITH {oracle.arcs('supply')}, k AS (SELECT {_CELL} AS cell, count(DISTINCT src) AS nzc, count(*) AS nnz FROM arcs GROUP BY 1) SELECT 'dcsc' AS kind, sum(2 * nzc + 1 + nnz)::BIGINT AS words FROM k UNION ALL SELECT 'csr', sum(CASE cell % 3 WHEN 2 THEN {_DENSE - 2 * (_DENSE // 3)} ELSE {_DENSE // 3} END + 1 + nnz)::BIGINT FROM k")(
    lambda s, d: metrics.storage_measured(graph(s, d, "supply"), GridLayout(2, 3, _DENSE)))


@query("block_bounds", f"""WITH {oracle.arcs('supply')}, v AS (SELECT count(DISTINCT src) AS n FROM arcs) SELECT cell, first_row, end_row, first_col, end_col FROM (
  SELECT CAST(i * 3 + j AS INT) AS cell, i * (n // 2) AS first_row, CASE i WHEN 1 THEN n ELSE n // 2 END AS end_row, j * (n // 3) AS first_col, CASE j WHEN 2 THEN n ELSE (j + 1) * (n // 3) END AS end_col FROM v, range(2) a(i), range(3) b(j))""")
def _bounds(s: SparkSession, d: str) -> DataFrame:
    """Of the dense ids of a graph's vertices."""
    n = prep.vertices(graphs.supply(s, d).arcs).count()
    return s.createDataFrame(GridLayout(2, 3, n).bounds(), "cell int, first_row long, end_row long, first_col long, end_col long")


@query("owner_cells", f"WITH {oracle.arcs('basket')} SELECT CAST({_CELL} AS INT) AS cell, count(*) AS arcs FROM arcs GROUP BY 1")
def _owner_cells(s: SparkSession, d: str) -> DataFrame:
    return GridLayout(2, 3, _DENSE).place(graph(s, d, "basket").arcs).groupBy("cell").agg(F.count("*").alias("arcs"))


# --- measures ----------------------------------------------------------------------------------------------------------
def _on_levels(name: str, graph_name: str, tail: str, run: Callable[[Graph, DataFrame], DataFrame], source: int = 0) -> None:
    def f(s: SparkSession, d: str) -> DataFrame:
        g = graph(s, d, graph_name)
        return run(g, rows.bfs_rows(g, source).levels)

    query(name, f"WITH RECURSIVE {oracle.with_levels(graph_name, source)} {tail}")(f)


_N = 1 << 15
_own = lambda v: f"least({v} // {_N // 4}, 3)"
_on_levels("level_profile", "purchase", "SELECT dist, count(*) AS vertices FROM lv GROUP BY dist", lambda g, lv: traversal_ops.level_profile(lv))
_on_levels("eccentricity", "purchase", "SELECT max(dist) AS eccentricity, count(*) AS reached FROM lv", lambda g, lv: traversal_ops.eccentricity(lv))
_on_levels("edges_traversed", "purchase", "SELECT count(*) // 2 AS edges FROM arcs WHERE src IN (SELECT vertex FROM lv)", lambda g, lv: metrics.edges_traversed(g, lv))
_on_levels("spanning_tree", "supply", "SELECT parent, vertex FROM lv WHERE vertex <> parent", lambda g, lv: traversal_ops.spanning_tree(lv))
_on_levels("bipartite_check", "supply", "SELECT count(*) AS arcs_within FROM arcs a JOIN lv x ON x.vertex = a.src JOIN lv y ON y.vertex = a.dst WHERE x.dist = y.dist", lambda g, lv: traversal_ops.bipartite_check(g, lv))
_on_levels("validate_tree", "supply", "SELECT unnest(['source', 'tree_arc', 'parent_level', 'arc_span', 'closed', 'once']) AS check_name, 0::BIGINT AS violations", lambda g, lv: validate.validate(g, lv, 0))
_on_levels(
    "volume_rows", "purchase",
    f""", s AS (SELECT dist, {_own('src')} AS sender, dst, count(*) AS n FROM arcs JOIN lv ON vertex = src GROUP BY ALL),
    t AS (SELECT dist, sum(n)::BIGINT AS scanned, count(*) AS candidates, count(*) FILTER (sender <> {_own('dst')}) AS shipped FROM s GROUP BY dist)
    SELECT l.dist, l.vertices, coalesce(scanned, 0) AS scanned, coalesce(candidates, 0) AS candidates, coalesce(shipped, 0) AS shipped FROM (SELECT dist, count(*) AS vertices FROM lv GROUP BY dist) l LEFT JOIN t ON t.dist = l.dist""",
    lambda g, lv: metrics.volume_rows(g, lv, RowLayout(4, _N)))
_row, _col = (lambda v: f"least({v} // {_N // 2}, 1)"), (lambda v: f"least({v} // {_N // 2}, 1)")
_on_levels(
    "volume_grid", "purchase",
    f""", s AS (SELECT dist, {_row('dst')} * 2 + {_col('src')} AS cell, dst, count(*) AS n FROM arcs JOIN lv ON vertex = src GROUP BY ALL),
    t AS (SELECT dist, sum(n)::BIGINT AS scanned, count(*) AS candidates, count(*) FILTER (cell <> {_row('dst')} * 2 + dst % 2) AS folded FROM s GROUP BY dist)
    SELECT l.dist, l.vertices, coalesce(scanned, 0) AS scanned, l.expanded, coalesce(candidates, 0) AS candidates, coalesce(folded, 0) AS folded FROM
    (SELECT dist, count(*) AS vertices, sum(2 - CASE WHEN vertex % 2 = {_col('vertex')} THEN 1 ELSE 0 END)::BIGINT AS expanded FROM lv GROUP BY dist) l LEFT JOIN t ON t.dist = l.dist""",
    lambda g, lv: metrics.volume_grid(g, lv, GridLayout(2, 2, _N)))
_on_levels(
    "diagonal_imbalance", "purchase",
    f""", c AS (SELECT DISTINCT dist, {_row('dst')} * 2 + {_col('src')} AS cell, dst FROM arcs JOIN lv ON vertex = src), o AS (SELECT {_row('dst')} * 3 AS owner, count(*) AS load FROM c GROUP BY 1)
    SELECT sum(load)::BIGINT AS rows, count(*) AS active, max(load) AS most, round(max(load) * 4 / sum(load), 6) AS imbalance FROM o""",
    lambda g, lv: metrics.imbalance(metrics.merged_per_owner(g, lv, GridLayout(2, 2, _N, "diagonal")), "owner", 4))
query("load_balance", f"WITH {oracle.arcs('purchase')}, o AS (SELECT {_own('src')} AS owner, count(*) AS load FROM arcs GROUP BY 1) SELECT sum(load)::BIGINT AS rows, count(*) AS active, max(load) AS most, round(max(load) * 4 / sum(load), 6) AS imbalance FROM o")(
    lambda s, d: metrics.imbalance(RowLayout(4, _N).place(graph(s, d, "purchase").arcs), "owner", 4))
query("edge_cut", f"WITH {oracle.arcs('purchase')} SELECT count(*) AS arcs, count(*) FILTER ({_own('src')} <> {_own('dst')}) AS cut FROM arcs")(lambda s, d: metrics.edge_cut(graph(s, d, "purchase"), RowLayout(4, _N)))
query("degree_topk", f"WITH {oracle.arcs('supply')} SELECT src AS vertex, count(*) AS degree FROM arcs GROUP BY src ORDER BY degree DESC, vertex LIMIT 20")(lambda s, d: metrics.degree_topk(graph(s, d, "supply"), 20))
query("degree_stats", f"WITH {oracle.arcs('supply')}, g AS (SELECT src, count(*) AS degree FROM arcs GROUP BY src) SELECT count(*) AS n, sum(degree)::BIGINT AS arcs, min(degree) AS least, round(avg(degree), 6) AS mean, quantile_cont(degree, 0.5) AS p50, quantile_cont(degree, 0.99) AS p99, max(degree) AS most FROM g")(
    lambda s, d: prep.degree_stats(graph(s, d, "supply").arcs, exact=True))
query("redundant_rate", f"""WITH RECURSIVE {oracle.with_levels('supply', 0)}, f AS (SELECT vertex, dist, (row_number() OVER (PARTITION BY dist ORDER BY vertex) - 1) % 6 AS thread FROM lv),
    p AS (SELECT count(*) AS pushes FROM (SELECT DISTINCT f.dist, thread, dst FROM f JOIN arcs ON src = f.vertex JOIN lv t ON t.vertex = dst WHERE t.dist = f.dist + 1))
    SELECT pushes, pushes - (SELECT count(*) - 1 FROM lv) AS redundant, round((pushes - (SELECT count(*) - 1 FROM lv)) / pushes, 6) AS rate FROM p""")(
    lambda s, d: metrics.redundant_rate(local.redundancy(graph(s, d, "supply"), 0)))
_POINTS = [(1 << 29, 1 << 33, 16, 16), (1 << 32, 1 << 36, 64, 64), (1 << 33, 1 << 37, 100, 100)]
_POINTS_SQL = ", ".join(f"({n}::BIGINT, {m}::BIGINT, {a}, {b})" for n, m, a, b in _POINTS)
query("storage_words", f"SELECT n, m, p_r, p_c, kind, CASE kind WHEN 'csr' THEN n + m WHEN 'csr_grid' THEN n * p_r + m WHEN 'spa' THEN n * p_c ELSE m END AS words FROM (VALUES {_POINTS_SQL}) t(n, m, p_r, p_c), (SELECT unnest(['csr', 'csr_grid', 'dcsc', 'heap', 'spa']) AS kind)")(
    lambda s, d: metrics.storage_table(s, _POINTS))
query("spa_bytes", "SELECT p_c, round(9.0 * 8589934592 / p_c, 3) AS bytes FROM (VALUES (10), (100), (200)) t(p_c)")(
    lambda s, d: s.createDataFrame([(p, round(metrics.spa_bytes_per_core(1 << 33, p), 3)) for p in (10, 100, 200)], "p_c int, bytes double"))
_COST = (16, 64, 1024)
query("cost_sweep", f"""WITH {oracle.arcs('supply')}, g AS (SELECT count(DISTINCT src) AS n, count(*) AS m FROM arcs) SELECT n, m, p, m * (p - 1) // (p * p) AS rows_words, n * (side - 1) // p AS expand_words, m * (side - 1) // (p * side) AS fold_words
  FROM (SELECT n, m, p, floor(sqrt(p))::BIGINT AS side FROM g, (VALUES {', '.join(f'({p}::BIGINT)' for p in _COST)}) t(p))""")(
    lambda s, d: cost_model.cost_sweep(s, [(*graphs.counts(graphs.supply(s, d)), p) for p in _COST]))


# --- bounds, paths, several sources ------------------------------------------------------------------------------------
query("khop_two", oracle.levels("basket", 0, bound=2))(lambda s, d: traversal_ops.khop(graph(s, d, "basket"), 0, 2))
_TARGET = 16


@query("st_distance", f"WITH RECURSIVE {oracle.with_levels('basket', 0)} SELECT CAST({_TARGET} AS BIGINT) AS target, dist FROM lv WHERE vertex = {_TARGET}")
def _st(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(_TARGET, traversal_ops.st_distance(graph(s, d, "basket"), 0, _TARGET))], "target long, dist int")


@query("path_to_target", f"WITH RECURSIVE {oracle.with_levels('basket', 0)}, path AS (SELECT vertex, dist, parent FROM lv WHERE vertex = {_TARGET} UNION SELECT l.vertex, l.dist, l.parent FROM path p JOIN lv l ON l.vertex = p.parent) SELECT dist AS step, vertex FROM path")
def _path(s: SparkSession, d: str) -> DataFrame:
    return traversal_ops.extract_path(rows.bfs_rows(graph(s, d, "basket"), 0, target=_TARGET).levels, _TARGET)


def _two(f: Callable[[DataFrame, DataFrame], DataFrame]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        g = graph(s, d, "basket")
        a, b = (traversal_ops.khop(g, v, 2).select("vertex") for v in (0, 16))
        return f(a, b)

    return run


_TWO = f"WITH RECURSIVE {oracle.with_levels('basket', 0, bound=2)}, {oracle.with_levels('basket', 16, bound=2, name='lw', first=False)} SELECT vertex FROM lv %s SELECT vertex FROM lw"
query("common_reach", _TWO % "INTERSECT")(_two(lambda a, b: a.intersect(b)))
query("reach_difference", _TWO % "EXCEPT")(_two(lambda a, b: a.exceptAll(b)))


@query("reach_counts_many", "WITH RECURSIVE " + oracle.with_levels("purchase", 0) + "".join(f", {oracle.with_levels('purchase', 16 * k, name=f's{k}', first=False)}" for k in range(1, 16))
       + " SELECT 0::BIGINT AS source, dist, count(*) AS vertices FROM lv GROUP BY dist" + "".join(f" UNION ALL SELECT {16 * k}::BIGINT, dist, count(*) FROM s{k} GROUP BY dist" for k in range(1, 16)))
def _many(s: SparkSession, d: str) -> DataFrame:
    return traversal_ops.bfs_many(graph(s, d, "purchase"), [16 * k for k in range(16)]).groupBy("source", "dist").agg(F.count("*").alias("vertices"))


@query("subtree_sizes", f"WITH RECURSIVE {oracle.with_levels('supply', 0)}, up AS (SELECT vertex AS leaf, vertex, parent FROM lv UNION SELECT u.leaf, l.vertex, l.parent FROM up u JOIN lv l ON l.vertex = u.parent) SELECT vertex, count(DISTINCT leaf) AS size FROM up GROUP BY vertex")
def _sizes(s: SparkSession, d: str) -> DataFrame:
    return traversal_ops.subtree_sizes(rows.bfs_rows(graph(s, d, "supply"), 0).levels)


@query("source_sample", f"{oracle.many('weblinks')} SELECT source FROM s")
def _sources(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(v,) for v in components.sample_sources(graph(s, d, "weblinks"))], "source long")
