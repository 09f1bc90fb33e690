"""Graphs and products that leave nothing out, against brute force and DuckDB."""

import glob
import os

import duckdb
import numpy as np
import pytest

from levelwave import graphs, grid, queries, rows
from levelwave.operators.vectors import nearest_of_all


def equals_sql(spark, folder, name):
    con = duckdb.connect()
    for path in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    got = queries.QUERIES[name](spark, folder)
    want = con.execute(queries.SQL[name])
    names = [d[0] for d in want.description]
    rows = sorted(tuple(r[c] for c in names) for r in got.collect())
    assert rows == sorted(want.fetchall()) and rows


@pytest.mark.parametrize("name", ["knn_all_edges", "knn_all_bfs"])
def test_nearest_of_all_equals_sql(spark, small, name):
    equals_sql(spark, small, name)


@pytest.mark.parametrize("queries_a_task", [7, 1000])
def test_nearest_of_all_crosses_labels(spark, queries_a_task):
    rng = np.random.default_rng(4)
    x = rng.integers(-3, 4, (300, 5)).astype(float)
    x[:120] = x[0]  # a common vector: many ties
    x[(x == 0).all(axis=1)] = 1
    rows = [(i, v.tolist(), i % 10) for i, v in enumerate(x)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {(r["vec_id"], r["other"]): r["similarity"] for r in nearest_of_all(df, 4, queries_a_task).collect()}
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    c = np.round(unit @ unit.T, 9)
    want = {(i, j): c[i, j] for i in range(300) for j in sorted((j for j in range(300) if j != i), key=lambda j: (-c[i, j], j))[:4]}
    assert got == pytest.approx(want)
    assert nearest_of_all(df.limit(0), 4).isEmpty()


def test_copies_equal_sql(spark, small):
    equals_sql(spark, small, "copies_edges")


def test_a_large_group_of_copies_is_linked(spark, tmp_path):
    line = "a line that many documents share, word for word"
    rows = [(i, f"{line}\nof its own {i}" if i >= 10 else f"nothing shared in document {i}, which is long enough") for i in range(90)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    arcs = graphs.copies(spark, str(tmp_path)).arcs.where("src < dst").collect()
    assert sorted((r["src"] // 16, r["dst"] // 16) for r in arcs) == [(10, i) for i in range(11, 90)]


@pytest.mark.parametrize("kernel", ["heap", "spa", "auto", "sql", "csr_cells"])
def test_product_by_all_vertices_equals_sql(spark, small, kernel):
    equals_sql(spark, small, f"kernel_{kernel}")


@pytest.fixture(scope="module")
def beyond(spark, small, tmp_path_factory):
    """Tables whose keys go past the fixed ranges of the registered layouts."""
    folder = tmp_path_factory.mktemp("beyond")
    con = duckdb.connect()
    for name, keys in {"lineitem": ("l_orderkey", "l_partkey", "l_suppkey"), "orders": ("o_orderkey", "o_custkey")}.items():
        moved = ", ".join(f"{k} + k * 30011 AS {k}" for k in keys)
        con.execute(f"COPY (SELECT * REPLACE ({moved}) FROM '{small}/{name}.parquet', range(2) r(k)) TO '{folder}/{name}.parquet'")
    return str(folder)


@pytest.mark.parametrize("name", ["dcsc_pack", "csr_pack", "csr_cells_pack", "storage_measured", "kernel_csr_cells", "kernel_spa"])
@pytest.mark.parametrize("chunk", [700, 2_000_000])
def test_packing_past_the_range_and_in_parts_equals_sql(spark, beyond, monkeypatch, name, chunk):
    for module, function in ((grid, "pack_dcsc"), (grid, "pack_csr_cells"), (grid, "spmsv"), (rows, "pack_csr")):
        whole = getattr(module, function)
        monkeypatch.setattr(module, function, lambda *a, f=whole, **k: f(*a, **{"chunk": chunk} | k) if not (f.__name__.startswith("pack_") and len(a) > 3) else f(*a, **k))
    equals_sql(spark, beyond, name)


def test_nearest_of_a_label_by_parts(spark):
    from levelwave.operators.vectors import nearest

    rng = np.random.default_rng(6)
    x, label = rng.integers(-3, 4, (200, 5)).astype(float), rng.integers(0, 3, 200)
    x[(x == 0).all(axis=1)] = 1
    df = spark.createDataFrame([(i, v.tolist(), int(label[i])) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int")
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    c = np.round(unit @ unit.T, 9)
    want = {(i, j): c[i, j] for i in range(200) for j in sorted((j for j in range(200) if j != i and label[i] == label[j]), key=lambda j: (-c[i, j], j))[:4]}
    found = nearest(df, 4, 7)
    assert {(r["vec_id"], r["other"]): r["similarity"] for r in found.collect()} == pytest.approx(want)
