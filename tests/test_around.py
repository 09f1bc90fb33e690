"""Streams, functions, measures and experiments around the traversals."""

import pytest
from pyspark.sql import functions as F

from levelwave import graphs, metrics, prep, rmat, rows, workloads
from levelwave.graphs import Graph
from levelwave.layout import GridLayout, RowLayout, places_for
from levelwave.operators import relational
from levelwave.serial import adjacency, serial_levels
from levelwave.session import kept, settings
from levelwave.streaming import MaintainedLevels, arrivals, late_rows, near_source, nearest_offers


def test_a_restarted_driver_goes_on(spark, tmp_path):
    edges = [(0, 1), (1, 2), (2, 3)]
    frame = lambda e: spark.createDataFrame(e + [(b, a) for a, b in e], "src long, dst long")
    MaintainedLevels(spark, 0, str(tmp_path)).add(frame(edges[:2]), 0)
    again = MaintainedLevels(spark, 0, str(tmp_path))
    assert again.version == 0 and {r["vertex"]: r["dist"] for r in again.levels().collect()} == {0: 0, 1: 1, 2: 2}
    again.add(frame(edges[2:]), 1)
    assert {r["vertex"]: r["dist"] for r in MaintainedLevels(spark, 0, str(tmp_path)).levels().collect()} == {0: 0, 1: 1, 2: 2, 3: 3}
    (tmp_path / "levels" / "2").mkdir()  # a batch whose writing broke off
    assert MaintainedLevels(spark, 0, str(tmp_path)).version == 1


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    schema, out = "event_id long, ts timestamp, user_id long", []
    for k, rows_ in enumerate((["10:00", "10:10"], ["15:00", "15:05"], ["10:20", "15:10"])):
        batch = [(k * 10 + i, f"2024-01-01 {t}:00", k) for i, t in enumerate(rows_)]
        spark.createDataFrame(batch, "event_id long, ts string, user_id long").withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = arrivals(spark.readStream.schema(schema).parquet(str(tmp_path / "in")))
        query = stream.writeStream.outputMode("append").foreachBatch(lambda df, k: out.extend(df.collect())).option("checkpointLocation", str(tmp_path / "at")).trigger(availableNow=True).start()
        query.awaitTermination()
    assert late_rows(query) == 1  # 10:20 came after 15:00 had been seen
    assert {(r["start"].hour, r["events"]) for r in out} == {(10, 2)}


def test_events_meet_fixed_levels(spark):
    levels = spark.createDataFrame([(9, 0, 9), (25, 2, 12)], "vertex long, dist int, parent long")
    events = spark.createDataFrame([(1, 0), (2, 1), (3, 7)], "event_id long, user_id long")
    assert {(r["event_id"], r["dist"]) for r in near_source(events, levels).collect()} == {(1, 0), (2, 2), (3, None)}


def test_state_keeps_the_best_offer(spark, tmp_path):
    out = []
    with settings(spark, spark__sql__streaming__stateStore__providerClass="org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"):
        for offers in ([(1, 3, 7), (2, 9, 7)], [(1, 2, 5), (1, 2, 6), (2, 1, 4)], [(1, 2, 5)]):
            spark.createDataFrame(offers, "vertex long, dist int, parent long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
            stream = nearest_offers(spark.readStream.schema("vertex long, dist int, parent long").parquet(str(tmp_path / "in")), radius=5)
            stream.writeStream.outputMode("update").foreachBatch(lambda df, k: out.extend(df.collect())).option("checkpointLocation", str(tmp_path / "at")).trigger(availableNow=True).start().awaitTermination()
    assert [tuple(r) for r in out if r["vertex"] == 1] == [(1, 3, 7), (1, 2, 6)] and [tuple(r) for r in out if r["vertex"] == 2] == [(2, 1, 4)]


def test_products_are_of_few_sources(spark):
    few, many = spark.range(2).withColumnRenamed("id", "vertex"), spark.range(50).withColumnRenamed("id", "vertex")
    assert relational.pairs(few, many).count() == 100
    with pytest.raises(ValueError):
        relational.pairs(many, many, most=10)
    assert relational.with_weight(spark.createDataFrame([(1, 2)], "src long, dst long")).first()["weight"] == 1.0


def test_places_follow_the_arcs():
    assert places_for(0) == 4 and places_for(40_000_001) == 11
    assert RowLayout().sized(10**9).p == 250 and GridLayout().sized(10**9).p == 256 and GridLayout(wide=True).sized(10).p_c == 3
    with pytest.raises(ValueError):
        GridLayout(2, 3, vector="diagonal")


def test_a_hub_is_split_into_tasks_of_its_own(spark):
    edges = spark.range(1, 4001).selectExpr("0L AS src", "id AS dst")
    arcs = kept(prep.symmetrize(edges))
    packed, slots, count = rows.pack_csr(arcs, RowLayout(2), chunk=500)
    sizes = packed.repartitionById(count, "slot").select(F.spark_partition_id().alias("at"), "slot", F.size("targets").alias("n")).collect()
    assert count >= 16 and all(r["at"] == r["slot"] for r in sizes) and max(r["n"] for r in sizes) < 800
    levels = rows.bfs_rows(Graph(arcs), 1, RowLayout(4), threads=2, chunk=500).levels
    assert levels.groupBy("dist").count().orderBy("dist").collect() == [(0, 1), (1, 1), (2, 3999)]


def test_deep_directed_graphs_are_masked_by_all_levels(spark):
    edges = [(k, k + 1) for k in range(24)] + [(24, 0), (20, 3), (7, 15)]
    g = Graph(kept(spark.createDataFrame(edges, "src long, dst long")), directed=True)
    got = {r["vertex"]: (r["dist"], r["parent"]) for r in rows.bfs_rows(g, 0, RowLayout(2)).levels.collect()}
    assert got == serial_levels(adjacency(edges), 0)


def test_labels_by_traversal_cut_fewer_arcs(spark):
    lines = [(1000 * k + (7919 * i) % 977, 1000 * k + (7919 * (i + 1)) % 977) for k in range(4) for i in range(200)]
    arcs = kept(prep.symmetrize(spark.createDataFrame(lines, "src long, dst long")))
    cut = {}
    for mode in ("rank", "locality"):
        moved, mapping = prep.relabel(arcs, mode)
        assert sorted(r["new"] for r in mapping.collect()) == list(range(mapping.count()))
        cut[mode] = metrics.edge_cut(Graph(kept(moved)), RowLayout(8, mapping.count())).first()["cut"]
    assert cut["locality"] * 10 < cut["rank"]


def test_sources_share_supersteps(spark):
    g = rmat.rmat(spark, 7)
    g = Graph(kept(g.arcs))
    want = {s: serial_levels(adjacency([tuple(r) for r in g.arcs.collect()]), s) for s in (0, 5, 9)}
    for method in workloads.METHODS:
        levels = workloads.METHODS[method](g, [0, 5, 9], 4, 2)
        got = {}
        for r in levels.collect():
            got.setdefault(r["source"], {})[r["vertex"]] = (r["dist"], r["parent"])
        assert got == want, method


def test_measured_and_modelled_communication(spark, small):
    got = {(r["method"], r["p"]): r for r in workloads.comm_share(spark, small, "rmat:7", (4,)).collect()}
    assert len(got) == 3 and all(r["megabytes"] > 0 and 0 < r["comm_seconds"] < r["run_seconds"] and 0 < r["share"] < 1 for r in got.values())
    model = {(r["method"], r["p"]): r["share"] for r in workloads.comm_share_model(spark, small).where(f"m = {1 << 36}").collect()}
    assert model["rows", 20_000] > model["grid", 20_000]


def test_runs_have_rates_of_all_sources(spark, small):
    got = workloads.runs(spark, small, ["rmat:6"], ("rows_flat", "local"), (1, 4), searches=5)
    found = got.collect()
    assert len(found) == 4 and all(r["searches"] == 5 and r["teps"] == pytest.approx(r["edges"] / 5 / r["mean_seconds"]) for r in found)
    table = {(r["method"], r["p"]): r for r in metrics.scaling_table(got).collect()}
    assert table["rows_flat", 1]["speedup"] == 1 and table["local", 4]["efficiency"] == pytest.approx(table["local", 4]["speedup"] / 4)
    ratio = metrics.kernel_ratio(workloads.kernel_crossover(spark, small, (1, 4))).collect()
    assert {r["p_c"] for r in ratio} == {1, 4} and all(r["ratio"] > 1 for r in ratio)  # the accumulator wins at few places


def test_one_task_gets_compact_blocks_and_needs_few_numbers_a_vertex(spark, monkeypatch):
    from levelwave import local, serial

    monkeypatch.setattr(serial, "ARCS_AT_A_TIME", 50)  # a hub's arcs and many small slices
    assert local.MOST_ARCS >= 72_000_000
    edges = [(0, k) for k in range(1, 400)] + [(k, k + 400) for k in range(1, 400)] + [(k + 400, 10**12 + k % 7) for k in range(1, 400)]
    g = Graph(kept(prep.symmetrize(spark.createDataFrame(edges, "src long, dst long"))))
    adj = adjacency([tuple(r) for r in g.arcs.collect()])
    rows_of = lambda df: {r["vertex"]: (r["dist"], r["parent"]) for r in df.collect()}
    for source in (0, 5, 10**12, 77_777):  # the last one has no arcs
        want = serial_levels(adj, source)
        assert rows_of(local.bfs_local(g, source, 3)) == want and rows_of(local.bfs_serial(g, source, "queue")) == want
    assert g.arcs in local._packed and local._packed[g.arcs].total == g.arcs.count()
    got = local.redundancy(g, 0, 6).first()
    assert got["levels"] == 4 and got["pushes"] == got["redundant"] + 399 + 399 + 7


def test_the_model_is_asked_for_a_table_graph_too(spark, small):
    g = graphs.supply(spark, small)
    n, m = g.arcs.select("src").distinct().count(), g.arcs.count()
    got = {r["m"] for r in workloads.comm_share_model(spark, small).collect()}
    assert got == {1 << 36, (m << 32) // n}


def test_six_threads_scale_over_all_places(monkeypatch):
    from levelwave import queries as traversals
    from levelwave import queries_experiments  # noqa: F401

    asked = {}
    monkeypatch.setattr(traversals, "importable", lambda spark: None)
    monkeypatch.setattr(workloads, "runs", lambda spark, sf_dir, names, methods, places, threads: asked.update(names=names, methods=methods, places=places, threads=threads) or type("Made", (), {"drop": lambda self, *c: self})())
    traversals.QUERIES["experiment_strong_six_threads"](None, "")
    assert {"rmat:14", "purchase", "supply"} == set(asked["names"]) and set(workloads.PLACES) | {12} == set(asked["places"])
    assert (asked["methods"], asked["threads"]) == (workloads.FOUR, 6)
    sql = traversals.SQL["experiment_strong_six_threads"]
    assert all(f"({p}::INT)" in sql for p in asked["places"]) and all(f"'{name}' AS graph" in sql for name in asked["names"])
