"""All methods give the rows of the serial one, on hand-made and derived graphs; invariants, plans, trends."""

import pytest
from pyspark.sql import functions as F

from levelwave import baselines, components, graphs, grid, local, metrics, plans, prep, rmat, rows, traversal_ops, validate
from levelwave.graphs import Graph
from levelwave.layout import GridLayout, RowLayout
from levelwave.loop import Placement, mask_new
from levelwave.serial import adjacency, serial_levels
from levelwave.session import aligned, kept

MINIATURES = {
    "diamond": ([(0, 1), (0, 2), (1, 3), (2, 3)], 0),
    "line": ([(k, k + 1) for k in range(7)], 3),
    "islands": ([(0, 1), (1, 2), (10, 11)], 10),
    "loops": ([(0, 0), (0, 1), (0, 1), (1, 2), (2, 2)], 0),
    "clique": ([(a, b) for a in range(6) for b in range(a)], 5),
    "alone": ([(1, 2)], 9),
}


def frame(spark, edges, directed=False):
    df = spark.createDataFrame(edges or [], "src long, dst long")
    return Graph(kept(prep.simplify(df) if directed else prep.symmetrize(df)), directed)


def rows_of(levels):
    return {r["vertex"]: (r["dist"], r["parent"]) for r in levels.collect()}


METHODS = {
    "rows": lambda g, s: rows.bfs_rows(g, s, RowLayout(3)).levels,
    "rows_all_levels": lambda g, s: rows.bfs_rows(g, s, RowLayout(2), mask="all").levels,
    "rows_hybrid": lambda g, s: rows.bfs_rows(g, s, RowLayout(4), threads=2).levels,
    "grid": lambda g, s: grid.bfs_grid(g, s, GridLayout(2, 3)).levels,
    "grid_range": lambda g, s: grid.bfs_grid(g, s, GridLayout(3, 2, 12)).levels,
    "grid_diagonal": lambda g, s: grid.bfs_grid(g, s, GridLayout(2, 2, vector="diagonal")).levels,
    "grid_row_head": lambda g, s: grid.bfs_grid(g, s, GridLayout(2, 3, vector="row_head"), frontier_form="sorted").levels,
    "grid_nonempty": lambda g, s: grid.bfs_grid(g, s, GridLayout(2, 2), only_nonempty=True).levels,
    "grid_broadcast": lambda g, s: grid.bfs_grid(g, s, GridLayout(), mode="broadcast").levels,
    "rows_pieces": lambda g, s: rows.bfs_rows(g, s, RowLayout(4), threads=2, chunk=3).levels,
    "triangle": lambda g, s: rows.bfs_rows(g, s, storage="triangle").levels,
    "several": lambda g, s: traversal_ops.bfs_many(g, [s, 77], GridLayout(2, 2)).where(F.col("source") == s).drop("source"),
    "grid_hybrid": lambda g, s: grid.bfs_grid(g, s, GridLayout(2, 2), threads=2).levels,
    "local": lambda g, s: local.bfs_local(g, s, 3),
    "messages": lambda g, s: baselines.bfs_messages(g, s),
}


PLAIN = ("rows", "rows_hybrid", "grid", "grid_hybrid", "local", "messages")


@pytest.mark.parametrize("name", MINIATURES)
def test_methods_equal_the_serial_one(spark, name):
    edges, source = MINIATURES[name]
    g = frame(spark, edges)
    want = serial_levels(adjacency([tuple(r) for r in g.arcs.collect()]), source)
    for method, run in METHODS.items():
        if method in PLAIN or name in ("diamond", "islands"):  # the others differ in where things are only
            assert rows_of(run(g, source)) == want, method
    assert name != "diamond" or want[3] == (2, 2)


def test_directed_graphs_ignore_arcs_into_the_source(spark):
    g = frame(spark, [(0, 1), (1, 2), (3, 0)], directed=True)
    want = {0: (0, 0), 1: (1, 0), 2: (2, 1)}
    for method in ("rows", "grid", "rows_hybrid", "local"):
        assert rows_of(METHODS[method](g, 0)) == want, method
    with pytest.raises(ValueError):
        rows.bfs_rows(g, 0, mask="two")


def test_derived_graph_and_validation(spark, small):
    g = graphs.supply(spark, small)
    g = Graph(kept(g.arcs))
    done = rows.bfs_rows(g, 0, trace=True)
    assert {r["dist"]: r["vertices"] for r in traversal_ops.level_profile(done.levels).collect()} == {0: 1, 1: 10, 2: 199}
    assert all(r["violations"] == 0 for r in validate.validate(g, done.levels, 0).collect())
    wrong = done.levels.withColumn("dist", F.when(F.col("vertex") == 1, 2).otherwise(F.col("dist")))
    assert sum(r["violations"] for r in validate.validate(g, wrong, 0).collect()) > 0
    assert [r["frontier"] for r in done.trace.orderBy("level").collect()] == [1, 10, 199]


def test_level_plans_exchange_what_they_must_and_no_more(spark, small):
    g = graphs.supply(spark, small)
    layout = RowLayout(4)
    place, arcs = Placement(4, layout.owner), rows.placed_arcs(g.arcs, layout)
    with aligned(spark, 4):
        frontier = kept(place.put(arcs.select(F.col("src").alias("vertex"), F.col("src").alias("parent")).dropDuplicates(["vertex"])))
        pairs = arcs.join(frontier.select("owner", F.col("vertex").alias("src")).hint("shuffle_hash"), ["owner", "src"]).select(F.col("owner").alias("sender"), F.col("dst").alias("vertex"), F.col("src").alias("parent"))
        new = mask_new(mask_new(place.merged(pairs, "sender"), frontier, place.by), frontier, place.by)
        assert plans.exchanges(new) == 1  # candidates to their owners
    for vector, form in (("grid", "stack"), ("diagonal", "stack"), ("row_head", "sorted")):
        layout = GridLayout(3, 3, vector=vector)
        place, cells = Placement(9, layout.owner), grid.placed_cells(g, layout)
        with aligned(spark, 9):
            frontier = kept(place.put(arcs.select(F.col("src").alias("vertex"), F.col("src").alias("parent")).dropDuplicates(["vertex"])))
            sent = grid.expand(frontier, layout).repartitionById(9, "cell").hint(grid.FORMS[form])
            new = mask_new(place.merged(grid.multiply(cells, sent), "cell"), frontier, place.by)
            assert plans.exchanges(new) == 2, vector  # expand and fold
            assert ("SortMergeJoin" in plans.joins(new)) == (form == "sorted")
            at = {r["place"] for r in kept(new.unionAll(frontier)).select("owner").distinct().withColumnRenamed("owner", "place").collect()}
            assert at == {"grid": set(range(9)), "diagonal": {0, 4, 8}, "row_head": {0, 3, 6}}[vector]
            where = frontier.select("owner", F.spark_partition_id().alias("at")).distinct().collect()
            assert all(r["owner"] == r["at"] for r in where)  # an owner's state is in its own partition
            assert [tuple(r) for r in cells.select("cell", F.spark_partition_id()).distinct().orderBy("cell").collect()] == [(k, k) for k in range(9)]


def test_scans_read_two_columns(spark, small):
    lines = spark.read.parquet(f"{small}/lineitem.parquet").select("l_partkey", "l_suppkey").where("l_partkey > 5")
    assert "PartKey" not in plans.read_columns(lines)[0] and plans.read_columns(lines)[0].count(":") == 2
    assert "GreaterThan(l_partkey,5)" in plans.pushed_filters(lines)[0]


def test_generator_checksums_and_source(spark):
    from levelwave.sources import register_sources

    raw = rmat.rmat_edges(spark, 9)
    assert raw.agg(F.sum(F.col("src") * 31 + F.col("dst"))).first()[0] == 31_527_669
    assert rmat.rmat_edges(spark, 11).agg(F.sum(F.col("src") * 31 + F.col("dst"))).first()[0] == 505_364_626
    register_sources(spark)
    other = spark.read.format("rmat").option("scale", 9).load()
    assert other.exceptAll(raw).isEmpty() and raw.count() == other.count()


@pytest.mark.parametrize("mode", ["feistel", "shuffle", "locality", "identity"])
def test_relabelling_keeps_distances(spark, mode):
    g = frame(spark, [(0, 5), (5, 9), (9, 30), (30, 31), (5, 31)])
    arcs, mapping = prep.relabel(g.arcs, mode, seed=4)
    new = {r["old"]: r["new"] for r in mapping.collect()}
    assert len(set(new.values())) == len(new) == 5
    got = rows_of(rows.bfs_rows(Graph(kept(arcs)), new[0]).levels)
    assert {v: got[new[v]][0] for v in new} == {0: 0, 5: 1, 9: 2, 31: 2, 30: 3}


def test_components_of_a_long_chain(spark):
    g = frame(spark, [(k, k + 1) for k in range(1, 60)] + [(100, 101)])
    found = {r["vertex"]: r["component"] for r in components.components(g).collect()}
    assert found == {**{k: 1 for k in range(1, 61)}, 100: 100, 101: 100}
    assert set(components.sample_sources(g, 4)) <= set(range(1, 61))


def test_trees_paths_and_several_sources(spark):
    g = frame(spark, [(0, 1), (1, 2), (0, 3), (3, 2), (2, 4)])
    levels = rows.bfs_rows(g, 0).levels
    assert [tuple(r) for r in traversal_ops.extract_path(levels, 4).collect()] == [(0, 0), (1, 3), (2, 2), (3, 4)]
    assert {r["vertex"]: r["size"] for r in traversal_ops.subtree_sizes(levels).collect()} == {0: 5, 1: 1, 3: 3, 2: 2, 4: 1}
    assert traversal_ops.st_distance(g, 0, 4) == 3 and traversal_ops.st_distance(g, 0, 77) is None
    many = traversal_ops.bfs_many(g, [0, 4])
    for s in (0, 4):
        assert rows_of(many.where(F.col("source") == s).drop("source")) == rows_of(rows.bfs_rows(g, s).levels)
    path = traversal_ops.extract_path(levels, 4)
    weights = spark.createDataFrame([(0, 3, 2.0), (3, 2, 0.5), (2, 4, 1.0)], "src long, dst long, weight double")
    assert traversal_ops.path_length(path, weights).first()["length"] == 3.5
    done, seen = traversal_ops.visit_counts(g, 0)
    assert seen == [(0, 1), (1, 2), (2, 1), (3, 1)]


def test_reported_trends_on_counts(spark):
    g = rmat.rmat(spark, 9)
    g = Graph(kept(g.arcs))
    levels = rows.bfs_rows(g, 0).levels
    levels = kept(levels)
    full = metrics.imbalance(metrics.merged_per_owner(g, levels, GridLayout(4, 4)), "owner", 16).first()
    diagonal = metrics.imbalance(metrics.merged_per_owner(g, levels, GridLayout(4, 4, vector="diagonal")), "owner", 16).first()
    assert diagonal["active"] == 4 and full["active"] == 16 and diagonal["imbalance"] > 2 * full["imbalance"]
    one = metrics.volume_rows(g, levels, RowLayout(16)).agg(F.sum("shipped")).first()[0]
    two = metrics.phase_split(metrics.volume_grid(g, levels, GridLayout(4, 4))).first()
    assert two["folded"] + two["expanded"] < one  # the grid ships less at higher concurrency
    shares = []
    for scale, factor in ((7, 64), (9, 16), (11, 4)):
        h = rmat.rmat(spark, scale, factor)
        h = Graph(kept(h.arcs))
        lv = rows.bfs_rows(h, 0).levels
        shares.append(metrics.phase_split(metrics.volume_grid(h, lv, GridLayout(3, 3))).first()["expand_share"])
    assert shares == sorted(shares)  # the expand's share rises as the graph gets sparser
    ref = baselines.bfs_reference(g, 0, 4, trace=True).trace.agg(F.sum("shipped")).first()[0]
    own = rows.bfs_rows(g, 0, RowLayout(4), trace=True).trace.agg(F.sum("shipped")).first()[0]
    assert ref > 1.5 * own


def test_stream_equals_batch_in_any_order(spark, tmp_path):
    from levelwave.streaming import MaintainedLevels

    edges = [(0, 1), (1, 2), (2, 3), (3, 4), (0, 3), (9, 4), (9, 10)]
    both = edges + [(b, a) for a, b in edges]
    want = serial_levels(adjacency(both), 0)
    for k, order in enumerate((both, both[::-1], both[3:] + both[:3])):
        state = MaintainedLevels(spark, 0, str(tmp_path / str(k)))
        for version, at in enumerate(range(0, len(order), 5)):
            state.add(spark.createDataFrame(order[at : at + 5], "src long, dst long"), version)
        assert rows_of(state.levels()) == want
        state.add(spark.createDataFrame(order[-4:], "src long, dst long"), 2)  # a batch that is run again
        assert rows_of(state.levels()) == want


def test_sources_round_trip(spark, tmp_path):
    from levelwave.sources import read_edges, require_columns, save_adjacency, write_levels

    g = frame(spark, [(1, 2), (2, 3)])
    for fmt in ("parquet", "orc", "json", "csv"):
        g.arcs.write.mode("overwrite").option("header", True).format(fmt).save(str(tmp_path / fmt))
        assert read_edges(spark, str(tmp_path / fmt), fmt).exceptAll(g.arcs).isEmpty()
    (tmp_path / "t.txt").write_text("# comment\n1 2\n 2\t3 \n\n")
    assert {tuple(r) for r in read_edges(spark, str(tmp_path / "t.txt"), "text").collect()} == {(1, 2), (2, 3)}
    write_levels(rows.bfs_rows(g, 1).levels, str(tmp_path / "levels"))
    assert spark.read.parquet(str(tmp_path / "levels")).where("dist = 2").first()["vertex"] == 3
    save_adjacency(g.arcs, "kept_arcs", 4)
    assert spark.table("kept_arcs").count() == 4
    with pytest.raises(ValueError):
        require_columns(g.arcs, "weight")


def test_empty_graph(spark):
    g = frame(spark, [])
    assert rows_of(rows.bfs_rows(g, 7).levels) == {7: (0, 7)}
    assert rows_of(grid.bfs_grid(g, 7).levels) == {7: (0, 7)}
    assert components.components(g).isEmpty()


def test_replication_goes_on_past_its_bound(spark, monkeypatch):
    monkeypatch.setattr(baselines, "REPLICATED_MOST", 2)
    g = frame(spark, [(k, k + 1) for k in range(4)] + [(0, 3)])
    want = serial_levels(adjacency([tuple(r) for r in g.arcs.collect()]), 0)
    assert rows_of(baselines.bfs_reference(g, 0, 2, replicated=True).levels) == want
