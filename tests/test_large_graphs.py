"""What graphs of many arcs go through, at small sizes: packing by places, contraction, searches inside a component."""

import numpy as np
import pytest

from levelwave import components, grid, local, prep, queries, rmat, workloads
from levelwave.graphs import Graph
from levelwave.layout import GridLayout
from levelwave.serial import adjacency, serial_levels, serial_rows
from levelwave.session import kept


def both_ways(edges):
    return sorted({x for a, b in edges if a != b for x in ((a, b), (b, a))})


def graph_of(spark, arcs, directed=False):
    return Graph(kept(spark.createDataFrame(arcs, "src long, dst long")), directed)


@pytest.mark.parametrize("place", [6, 60, 4_000_000])  # a hub has too many arcs, places are cut by starts, or one is enough
@pytest.mark.parametrize("directed", [False, True])
def test_packed_by_places(spark, monkeypatch, place, directed):
    monkeypatch.setattr(local, "PLACE_ARCS", place)
    rng = np.random.default_rng(8)
    edges = [*map(tuple, rng.integers(0, 90, (150, 2)).tolist()), *((7, k) for k in range(60))]
    arcs = sorted(set(edges)) if directed else both_ways(edges)
    g, want = graph_of(spark, [(a * 5, b * 5) for a, b in arcs], directed), serial_levels(adjacency(arcs), 3)
    for found in (local.bfs_local(g, 15), local.bfs_serial(g, 15)):
        assert {r["vertex"] // 5: (r["dist"], r["parent"] // 5) for r in found.collect()} == want
    packed = local._packed[g.arcs]
    assert packed.total == len(arcs) and (packed.blocks.select("part").distinct().count() > 1) == (place < len(arcs))
    assert not local.fits(g, len(arcs) - 1) and local.fits(g, len(arcs))


@pytest.mark.parametrize("place", [0, 40, 4_000_000])
def test_components_by_contraction(spark, monkeypatch, place):
    monkeypatch.setattr(components, "PLACE_ARCS", place)
    rng = np.random.default_rng(5)
    edges = [*map(tuple, rng.integers(0, 120, (70, 2)).tolist()), *((200 + k, 201 + k) for k in range(30)), *((300, 301 + k) for k in range(30))]
    arcs = both_ways(edges)
    got = {r["vertex"]: r["component"] for r in components.components(graph_of(spark, arcs)).collect()}
    adj = adjacency(arcs)
    assert got == {v: min(serial_levels(adj, v)) for v in adj}
    names, least = components.least_reachable(*np.array(arcs).T)
    assert got == dict(zip(names.tolist(), least.tolist(), strict=True))


@pytest.mark.parametrize("frontier", ["stacks", "queue"])
def test_serial_holds_arrays(frontier):
    rng = np.random.default_rng(9)
    arcs = both_ways([*map(tuple, rng.integers(0, 70, (120, 2)).tolist()), *((7, k) for k in range(60))])
    src, dst = np.array(arcs).T
    offsets = np.searchsorted(src, np.arange(71))
    found = serial_rows(offsets, dst.astype(np.int32), 3, frontier)
    assert all(isinstance(x, np.ndarray) for x in found)
    assert {v: (d, p) for v, d, p in zip(*(x.tolist() for x in found), strict=True)} == serial_levels(adjacency(arcs), 3, frontier)


@pytest.mark.parametrize("storage", ["csr", "dcsc"])
def test_products_in_parts(spark, monkeypatch, storage):
    monkeypatch.setattr(grid, "PRODUCT_ARCS", 30)
    arcs = both_ways(map(tuple, np.random.default_rng(4).integers(0, 90, (200, 2)).tolist()))
    cut, whole = [], grid.cell_parts
    monkeypatch.setattr(grid, "cell_parts", lambda a, layout, chunk: cut.append(chunk) or whole(a, layout, chunk))
    frame = spark.createDataFrame(arcs, "src long, dst long")
    got = grid.spmsv(frame, frame.selectExpr("src AS vertex").distinct(), GridLayout(2, 3, 40), storage=storage)
    assert {r["vertex"]: r["parent"] for r in got.collect()} == {d: max(a for a, b in arcs if b == d) for _, d in arcs}
    assert cut == [30]


@pytest.mark.parametrize("most", [0, 12_000_000])  # by contraction and rounds, or by two arcs a vertex in a task
def test_components_by_two_arcs(spark, monkeypatch, most):
    monkeypatch.setattr(components, "PLACE_ARCS", 20)
    monkeypatch.setattr(components, "MOST_VERTICES", most)
    rng = np.random.default_rng(6)
    # Rings of cliques: the arcs to the least and greatest neighbours don't join them all, so contracted arcs are left.
    cliques = [(10 * c + a, 10 * c + b) for c in range(12) for a in range(10) for b in range(a)]
    edges = [*cliques, *((10 * c + 5, 10 * ((c + 4) % 12) + 5) for c in range(12)), *map(tuple, rng.integers(500, 600, (60, 2)).tolist())]
    arcs = both_ways(edges)
    adj = adjacency(arcs)
    assert {r["vertex"]: r["component"] for r in components.components(graph_of(spark, arcs)).collect()} == {v: min(serial_levels(adj, v)) for v in adj}


def test_arcs_are_stored_once_an_edge(spark, small):
    lines = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (4, None), (5, 1)], "src int, dst int")
    arcs = prep.symmetrize(lines)
    assert arcs.dtypes == [("src", "bigint"), ("dst", "bigint")]
    assert sorted(map(tuple, arcs.collect())) == [(1, 2), (1, 5), (2, 1), (5, 1)]
    assert arcs._jdf.queryExecution().optimizedPlan().toString().count("Union") == 0  # an edge is sent once, not each way
    for g in (queries.graph(spark, small, "supply"), workloads.load(spark, small, "supply")):
        assert all(f.endswith(".parquet") for f in g.arcs.inputFiles()) and g.arcs.inputFiles()  # read as columns


def test_searches_read_their_component(spark, small, monkeypatch):
    monkeypatch.setattr(workloads, "PLACE_ARCS", 0)
    parts = [both_ways([(100 * c + a, 100 * c + b) for a, b in np.random.default_rng(c).integers(0, 20, (60, 2)).tolist()]) for c in range(3)]
    g = graph_of(spark, sum(parts, []))
    monkeypatch.setitem(workloads._loaded, (spark.sparkContext.applicationId, small, "three"), g)
    inside = workloads.searched(spark, small, "three")
    one = max(parts, key=lambda arcs: len({a for a, _ in arcs}))
    assert sorted(map(tuple, inside.arcs.collect())) == one
    found = workloads.runs(spark, small, ["three"], ("rows_flat", "local"), (2,), searches=3).collect()
    assert {(r["reached"], r["edges"]) for r in found} == {(3 * len({a for a, _ in one}), 3 * len(one) // 2)}


@pytest.mark.parametrize("ids", [3_000_000, 0])  # or these edges have too many ends
def test_components_by_a_share_of_the_edges(spark, monkeypatch, ids):
    monkeypatch.setattr(components, "BROADCAST_IDS", ids)
    monkeypatch.setattr(components, "PLACE_ARCS", 100)  # some 150 of 1,800 edges go first
    rng = np.random.default_rng(11)
    edges = [(1000 * c + a, 1000 * c + b) for c in range(3) for a, b in rng.integers(0, 60, (600, 2)).tolist()]
    arcs = both_ways([*edges, *((9000 + k, 9001 + k) for k in range(25)), *((8000, 8001 + k) for k in range(25))])
    written, whole = [], components.stored
    monkeypatch.setattr(components, "stored", lambda df, name: written.append((name, whole(df, name))) or written[-1][1])
    adj = adjacency(arcs)
    assert {r["vertex"]: r["component"] for r in components.components(graph_of(spark, arcs)).collect()} == {v: min(serial_levels(adj, v)) for v in adj}
    assert [name for name, _ in written[:3]] == (["some", "labels", "contracted"] if ids else ["some", "near", "labels"])
    first = dict(written[:3])
    assert 75 < first["some"].count() < 300
    assert not ids or first["contracted"].count() < len(arcs) // 4  # not the two arcs of every vertex


def test_raw_edges_are_made_by_arrays(spark):
    raw = rmat.rmat_edges(spark, 7, 4, seed=3)
    plan = raw._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "aggregate(" not in plan
    whole = rmat.edges_of(np.arange(4 << 7, dtype=np.int64), 7, seed=3)
    assert sorted(map(tuple, raw.collect())) == sorted(zip(*(x.tolist() for x in whole), strict=True))
    far = np.array([(1 << 40) + 5], dtype=np.int64)  # its product with a multiplier has more than 63 bits
    assert [x.tolist() for x in rmat.edges_of(far, 7)] == [x.tolist() for x in rmat.edges_of(far % rmat.MODULUS, 7)]
