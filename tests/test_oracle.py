"""A part of the registered queries against DuckDB at the smallest size; the driver runs all of them."""

import glob
import os

import duckdb
import pytest

from levelwave import queries, queries_experiments, queries_relational  # noqa: F401

SOME = ["rows_flat_supply", "grid_flat_rect_basket", "grid_rowhead_vector", "directed_hierarchy", "volume_grid", "relabel_bijection", "trail_deep", "rmat_edges_s11", "dialog_udtf", "path_udtf", "asof_event",
        "storage_measured", "source_sample", "experiment_strong_comm", "experiment_redundancy", "experiment_relabel_balance", "experiment_versus_reference", "experiment_kernel_crossover"]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for path in glob.glob(f"{small}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, small, duck, name):
    got = queries.QUERIES[name](spark, small)
    names = sorted(got.columns)
    want = duck.execute(queries.SQL[name])
    order = [d[0] for d in want.description]
    assert sorted(order) == names
    rows = sorted(tuple(r[order.index(c)] for c in names) for r in want.fetchall())
    assert sorted((tuple(r[c] for c in names) for r in got.collect()), key=repr) == sorted(rows, key=repr)


def test_entry_imports_without_the_document_operators(tmp_path):
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/levelwave", tmp_path / "levelwave", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 80 and not any(k.startswith('op') for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})


@pytest.mark.parametrize("name", ["block_bounds", "cost_sweep", "grid_hybrid_rmat"])
def test_moved_onto_a_table_equals_sql(spark, small, duck, name):
    assert "lineitem" in queries.SQL[name]
    test_query_equals_sql(spark, small, duck, name)
