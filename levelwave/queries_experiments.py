"""Queries of the experiments: what does not depend on the clock, each with its DuckDB text. Times are in workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import oracle, workloads
from .layout import closest_square
from .queries import query
from .workloads import FEW_THREADS, FOUR, MORE_PLACES, MORE_THREADS, STRONG

#: Points of equal edges, a quarter of those that the functions take by themselves.
DENSITIES = ((11, 64), (13, 16), (15, 4))
CLOCK = ("mean_seconds", "teps", "heap_seconds", "spa_seconds")


def _counts(name: str, sql: str | None, **options: object) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = workloads.WORKLOADS[name](spark, sf_dir, **options)
        return made.drop(*CLOCK)

    query(f"experiment_{name}", sql)(run)


def _runs_sql(names: list[str], methods: tuple[str, ...], places: tuple[int, ...], threads: int = 2) -> str:
    """Every method at every number of places reaches the same from the 16 sources."""
    each = " UNION ALL ".join(
        f"""SELECT * FROM ({oracle.many(name)}, g AS (SELECT src AS vertex, count(*) AS degree FROM arcs GROUP BY src)
        SELECT '{name}' AS graph, count(DISTINCT source)::INT AS searches, count(*) AS reached, max(dist)::INT AS farthest, sum(degree)::BIGINT // 2 AS edges FROM lm JOIN g USING (vertex))"""
        for name in names)
    return f"""SELECT graph, method, p, {threads}::INT AS threads, searches, reached, farthest, edges FROM ({each}),
        (VALUES {', '.join(f"('{m}')" for m in methods)}) a(method), (VALUES {', '.join(f'({p}::INT)' for p in places)}) b(p)"""


def _dense(name: str) -> str:
    """WITH text: a search from the first source on shuffled dense ids: da (src, dst), dl (vertex, dist) and n in dn."""
    return f"""{oracle.many(name, 1)}, ids AS MATERIALIZED (SELECT src AS vertex, row_number() OVER (ORDER BY {oracle.shuffled('src')}, src) - 1 AS id FROM (SELECT DISTINCT src FROM arcs)),
        da AS MATERIALIZED (SELECT a.id AS src, b.id AS dst FROM arcs JOIN ids a ON a.vertex = src JOIN ids b ON b.vertex = dst),
        dl AS MATERIALIZED (SELECT id AS vertex, dist FROM lm JOIN ids USING (vertex)), dn AS (SELECT count(*) AS n FROM ids)"""


def _block(vertex: str, blocks: int) -> str:
    return f"least({vertex} // greatest((SELECT n FROM dn) // {blocks}, 1), {blocks - 1})"


def _shipped(p: int) -> str:
    return f"(SELECT count(*) FROM (SELECT DISTINCT dist, {_block('src', p)} AS sender, dst FROM da JOIN dl ON vertex = src) WHERE sender <> {_block('dst', p)})"


def _expanded(p_r: int, p_c: int) -> str:
    return f"(SELECT sum({p_r} - CASE WHEN vertex % {p_c} = {_block('vertex', p_c)} THEN 1 ELSE 0 END)::BIGINT FROM dl)"


def _folded(p_r: int, p_c: int) -> str:
    return f"(SELECT count(*) FROM (SELECT DISTINCT dist, {_block('dst', p_r)} * {p_c} + {_block('src', p_c)} AS cell, dst FROM da JOIN dl ON vertex = src) WHERE cell <> {_block('dst', p_r)} * {p_c} + dst % {p_c})"


def _comm_sql(name: str, places: tuple[int, ...]) -> str:
    each = [f"SELECT {p}::INT AS p, {_shipped(p)} AS rows_shipped, {_expanded(*closest_square(p))} AS grid_expanded, {_folded(*closest_square(p))} AS grid_folded" for p in places]
    return f"{_dense(name)} {' UNION ALL '.join(each)}"


def _phases(points: tuple[tuple[int, int], ...], places: tuple[int, ...]) -> str:
    each = [f"SELECT * FROM ({_dense(f'rmat:{s}:{f}')} " + " UNION ALL ".join(
        f"SELECT {s}::INT AS scale, {f}::INT AS edge_factor, {p}::INT AS p, {_expanded(*closest_square(p))} AS expanded, {_folded(*closest_square(p))} AS folded" for p in places) + ")" for s, f in points]
    return " UNION ALL ".join(each)


def _placement_sql(name: str, side: int) -> str:
    n = 1 << int(name.split(":")[1])
    at = lambda v: f"least({v} // {max(n // side, 1)}, {side - 1})"
    owners = {"grid": f"{at('dst')} * {side} + dst % {side}", "diagonal": f"{at('dst')} * {side + 1}", "row_head": f"{at('dst')} * {side}"}
    each = [f"SELECT '{vector}' AS vector, {owner} AS place, count(*) AS load FROM merged GROUP BY ALL" for vector, owner in owners.items()]
    return f"""{oracle.many(name, 1)}, merged AS MATERIALIZED (SELECT DISTINCT dist, {at('dst')} * {side} + {at('src')} AS cell, dst FROM arcs JOIN lm ON vertex = src)
        SELECT vector, count(*) AS active, sum(load)::BIGINT AS rows, max(load) AS most, round(max(load) * {side * side} / sum(load), 6) AS imbalance FROM ({' UNION ALL '.join(each)}) GROUP BY vector"""


def _redundancy_sql(names: tuple[str, ...], threads: int = 6) -> str:
    each = [f"""SELECT * FROM ({oracle.many(name, 1)}, f AS MATERIALIZED (SELECT vertex, dist, (row_number() OVER (PARTITION BY dist ORDER BY vertex) - 1) % {threads} AS thread FROM lm),
        p AS (SELECT count(*) AS pushes FROM (SELECT DISTINCT f.dist, thread, dst FROM f JOIN arcs ON src = f.vertex JOIN lm t ON t.vertex = dst WHERE t.dist = f.dist + 1))
        SELECT '{name}' AS graph, pushes, pushes - (SELECT count(*) - 1 FROM lm) AS redundant, round((pushes - (SELECT count(*) - 1 FROM lm)) / pushes, 6) AS rate FROM p)""" for name in names]
    return " UNION ALL ".join(each)


def _relabel_sql(names: tuple[str, ...], blocks: int) -> str:
    each = []
    for name in names:
        for mode in ("rank", "shuffle", "locality"):
            order = {"rank": "vertex", "shuffle": f"{oracle.shuffled('vertex')}, vertex", "locality": "component, dist, parent, vertex"}[mode]
            each.append(f"""SELECT * FROM (WITH RECURSIVE {oracle.arcs('', False, oracle.named(name))}, {oracle.component_rows()},
              d(vertex, dist) USING KEY (vertex) AS (SELECT DISTINCT component AS vertex, 0 AS dist FROM c
                UNION SELECT a.dst, min(r.dist) + 1 FROM d r JOIN arcs a ON a.src = r.vertex LEFT JOIN recurring.d k ON k.vertex = a.dst WHERE k.vertex IS NULL GROUP BY a.dst),
              v AS MATERIALIZED (SELECT d.vertex, d.dist, coalesce(max(u.vertex), d.vertex) AS parent FROM d LEFT JOIN arcs a ON a.dst = d.vertex LEFT JOIN d u ON u.vertex = a.src AND u.dist = d.dist - 1 GROUP BY d.vertex, d.dist),
              ids AS MATERIALIZED (SELECT vertex, row_number() OVER (ORDER BY {order}) - 1 AS id FROM v JOIN c USING (vertex)), dn AS (SELECT count(*) AS n FROM ids),
              da AS MATERIALIZED (SELECT {_block('a.id', blocks)} AS s, {_block('b.id', blocks)} AS d FROM arcs JOIN ids a ON a.vertex = src JOIN ids b ON b.vertex = dst), m AS (SELECT count(*) AS m FROM da)
              SELECT '{name}' AS graph, '{mode}' AS mode, most, round(most * {blocks} / m, 6) AS imbalance, cut, round(cut / m, 6) AS cut_share FROM m,
                (SELECT max(load) AS most FROM (SELECT count(*) AS load FROM da GROUP BY s)), (SELECT count(*) AS cut FROM da WHERE s <> d))""")
    return " UNION ALL ".join(each)


def _nonempty_sql(names: tuple[str, ...], side: int = 3) -> str:
    return " UNION ALL ".join(
        f"SELECT * FROM ({_dense(name)} SELECT '{name}' AS graph, (SELECT count(*) * {side} FROM dl) AS all_sent, (SELECT count(*) FROM (SELECT DISTINCT src, {_block('dst', side)} FROM da JOIN dl ON vertex = src)) AS nonempty_sent)"
        for name in names)


_N, _WIDTHS = 1 << 15, (1, 2, 4, 8, 16, 32)
_counts("strong_rows_vs_grid", _runs_sql(["rmat:14", "purchase", "supply"], FOUR, (9,), FEW_THREADS), places=(9,))
_counts("strong_six_threads", _runs_sql(list(STRONG), FOUR, MORE_PLACES, MORE_THREADS))
_counts("strong_comm", _comm_sql("purchase", (4, 16, 64)))
_counts("comm_share", None)
_counts("comm_share_model", None)
_counts("weak", " UNION ALL ".join(_runs_sql([f"rmat:{s}"], FOUR, (p,)) for s, p in ((10, 1), (12, 4), (14, 16))))
_counts("density", _runs_sql([*(f"rmat:{s}:{f}" for s, f in DENSITIES), "sourcing", "supply", "purchase", "basket"], ("rows_flat", "grid_flat"), (9,)), names=(*(f"rmat:{s}:{f}" for s, f in DENSITIES), "sourcing", "supply", "purchase", "basket"))
_counts("phase_table", f"SELECT *, round(expanded / (expanded + folded), 6) AS expand_share FROM ({_phases(DENSITIES, (4, 9, 16))})", points=DENSITIES)
_counts("deep_graph", _runs_sql(["trail"], ("local",), (1,)) + " UNION ALL " + _runs_sql(["weblinks"], ("local", "grid_flat", "grid_hybrid"), (4,)))
_counts("versus_reference", f"""{oracle.many('rmat:11', 1)} SELECT p, own_shipped, reference_shipped, round(reference_shipped / own_shipped, 6) AS ratio FROM (
    {' UNION ALL '.join(f"SELECT {p}::INT AS p, (SELECT count(*) FROM (SELECT DISTINCT dist, least(src // {2048 // p}, {p - 1}) AS sender, dst FROM arcs JOIN lm ON vertex = src)) AS own_shipped, (SELECT count(*) FROM arcs WHERE src IN (SELECT vertex FROM lm)) AS reference_shipped" for p in (4, 8, 16))})""")
_counts("versus_library", _runs_sql(["rmat:12"], ("grid_flat", "messages"), (4, 9)), names=("rmat:12",))
_counts("single_node", _runs_sql(["rmat:14", "supply", "nearvec"], ("local", "local_shared", "local_bag"), (1,), FEW_THREADS))
_counts("kernel_crossover", f"WITH {oracle.arcs('purchase')} " + " UNION ALL ".join(
    f"SELECT {w}::INT AS p_c, count(DISTINCT j) AS cells, count(*) AS entries, count(DISTINCT (j, dst)) AS spa_words, count(*) AS heap_words FROM (SELECT least(src // {_N // w}, {w - 1}) AS j, dst FROM arcs)" for w in _WIDTHS))
_counts("vector_placement", _placement_sql("rmat:14", 8), side=8)
_counts("redundancy", _redundancy_sql(("rmat:11", "supply", "purchase", "basket")))
_counts("relabel_balance", _relabel_sql(("rmat:11", "supply"), 16))
_counts("nonempty_expand", _nonempty_sql(("rmat:11", "basket")))
_counts("headline", _runs_sql(["rmat:14", "basket"], FOUR, (4,)))
_counts("model_check", f"SELECT scale, edge_factor, p, round(expanded / greatest(folded, 1), 6) AS counted, round((side - 1) / (edge_factor * power(side, 1.0 / 3)), 6) AS predicted FROM (SELECT *, floor(sqrt(p)) AS side FROM ({_phases(DENSITIES, (4, 16))}))", points=DENSITIES)
