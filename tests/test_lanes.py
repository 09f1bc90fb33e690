"""Searches in lanes against serial ones."""

import pytest
from pyspark.sql import functions as F

from levelwave import components, grid, lanes, rmat, rows
from levelwave.graphs import Graph
from levelwave.layout import GridLayout, RowLayout
from levelwave.serial import adjacency, serial_levels
from levelwave.session import kept

SOURCES = [0, 5, 9, 5, 1]


@pytest.fixture(scope="module")
def graph(spark):
    return Graph(kept(rmat.rmat(spark, 6).arcs))


@pytest.mark.parametrize("run", [
    lambda g: rows.bfs_rows(g, SOURCES, RowLayout(3)),
    lambda g: rows.bfs_rows(g, SOURCES, RowLayout(4), threads=2, chunk=100, visit_check="atomic"),
    lambda g: grid.bfs_grid(g, SOURCES, GridLayout(2, 3)),
    lambda g: lanes.grid_hybrid(g, SOURCES, GridLayout(2, 1), 2, 100),
], ids=["rows_flat", "rows_hybrid", "grid_flat", "grid_hybrid"])
def test_searches_share_rows(graph, monkeypatch, run):
    monkeypatch.setattr(lanes, "LANES", 3)
    adj = adjacency([tuple(r) for r in graph.arcs.collect()])
    done, got = run(graph), {}
    for r in done.levels.collect():
        got.setdefault(r["source"], {})[r["vertex"]] = (r["dist"], r["parent"])
    assert got == {s: serial_levels(adj, s) for s in SOURCES}
    held, reached = done.met.agg(F.count("*"), F.sum("searches")).first()
    assert reached == done.levels.count() and held < reached  # a row is of several searches


def test_largest_component_by_one_search(spark, monkeypatch):
    monkeypatch.setattr(components, "PLACE_ARCS", 0)
    path = lambda a, n: [(a + k, a + k + 1) for k in range(n)]
    for edges, want in ((path(0, 9) + path(50, 3), range(10)), (path(0, 3) + path(10, 4) + path(20, 3), range(10, 15))):  # over half, or not
        g = Graph(kept(spark.createDataFrame([x for a, b in edges for x in ((a, b), (b, a))], "src long, dst long")))
        assert {r[0] for r in components.largest_component(g).collect()} == set(want)
