"""Formats, kernels, layouts and costs, by hand and by each other."""

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from levelwave import cost_model, grid, kernels, metrics, workloads
from levelwave.layout import GridLayout, block_bounds, closest_square
from levelwave.serial import adjacency, array_levels, serial_levels

SIX = {0: [0, 3], 1: [0, 1], 2: [3, 5], 3: [0, 2, 3], 4: [1], 5: [2]}
ARCS = st.lists(st.tuples(st.integers(0, 12), st.integers(0, 12)), max_size=60)


def test_dcsc_of_a_six_by_six_matrix():
    rows, cols = zip(*[(r, c) for r, cs in SIX.items() for c in cs], strict=True)
    table = pa.table({"cell": pa.array([0] * 11, pa.int32()), "piece": pa.array([0] * 11, pa.int32()), "row": rows, "col": cols})
    out = kernels.dcsc_table(table).to_pylist()[0]
    assert out["rows"] == [0, 1, 2, 3, 4, 5]
    assert out["jc"] == [0, 1, 2, 3, 5]
    assert out["cp"] == [0, 3, 5, 7, 10, 11]
    assert out["ir"] == [0, 1, 3, 1, 4, 3, 5, 0, 2, 3, 2]


@given(ARCS, st.sets(st.integers(0, 12)))
@settings(deadline=None, max_examples=60)
def test_heap_and_accumulator_agree(arcs, frontier):
    src, dst = (np.array([a[k] for a in sorted(set(arcs))], dtype=np.int64) for k in (0, 1))
    csr = kernels.BlockCsr.from_arcs(src, dst)
    source, target = kernels.gather(csr.vertices, csr.offsets, csr.targets, np.array(sorted(frontier), dtype=np.int64))
    want = {}
    for u, v in arcs:
        if u in frontier:
            want[v] = max(want.get(v, -1), u)
    for merge in (kernels.merge_spa, kernels.merge_heap):
        rows, best = merge(source, target)
        assert dict(zip(rows.tolist(), best.tolist(), strict=True)) == want
        assert rows.tolist() == sorted(want)


@given(ARCS, st.integers(0, 12))
@settings(deadline=None, max_examples=60)
def test_serial_forms_agree(arcs, source):
    adj = adjacency(sorted(set(arcs)))
    want = serial_levels(adj, source)
    assert serial_levels(adj, source, "queue") == want
    src, dst = (np.array([a[k] for a in arcs], dtype=np.int64) for k in (0, 1))
    for store in ("local", "shared", "bag"):
        for check in ("benign", "atomic"):
            v, d, p, counts = array_levels(src, dst, source, 3, store, check)
            assert {x: (y, z) for x, y, z in zip(v.tolist(), d.tolist(), p.tolist(), strict=True)} == want
            assert check == "benign" or counts["redundant"] == 0


def test_threads_expand_with_and_without_a_common_check():
    csr = kernels.BlockCsr.from_arcs(np.array([1, 1, 2, 3]), np.array([7, 8, 7, 7]))
    vertex, parent, scanned = csr.neighbours(np.array([1, 2, 3]), 3)
    assert sorted(zip(vertex, parent, strict=True)) == [(7, 1), (7, 2), (7, 3), (8, 1)] and scanned == 4
    vertex, parent, _ = csr.neighbours(np.array([1, 2, 3]), 3, "atomic")
    assert sorted(zip(vertex, parent, strict=True)) == [(7, 3), (8, 1)]


def test_pointers_for_all_columns_give_the_same_product():
    rng = np.random.default_rng(3)
    rows, cols = rng.integers(0, 50, 300), rng.integers(20, 40, 300)
    table = pa.table({"cell": pa.array([1] * 300, pa.int32()), "piece": pa.array([0] * 300, pa.int32()), "row": rows, "col": cols})
    dense = kernels.csr_cell_table(table, [(0, 20), (20, 45)], 2)
    assert dense.column("base")[0].as_py() == 20 and len(dense.column("cp")[0]) == 26
    (cp, ir, names), = kernels.lists_of(dense, "cp", "ir", "rows")
    wanted = np.array([3, 21, 25, 39, 44, 60])
    at, best = kernels.merge(*kernels.gather_dense(20, cp, ir, wanted), "spa", len(names))
    row, parent = kernels.spmsv_cell(list(kernels.lists_of(kernels.dcsc_table(table), "jc", "cp", "ir", "rows")), wanted, "heap")
    assert (names[at] == row).all() and (best == parent).all() and len(row)


def test_columns_past_the_bounds_are_held_apart():
    rng = np.random.default_rng(5)
    rows, cols = rng.integers(0, 50, 400), rng.integers(20, 900, 400)  # bounds end at 45
    found = {}
    for part in range(3):  # 9 columns each, the last one 7
        of = (np.where(cols < 45, (cols - 20) // 9, cols % 3)) == part
        table = pa.table({"cell": pa.array([1] * of.sum(), pa.int32()), "part": pa.array([part] * of.sum(), pa.int32()), "parts": pa.array([3] * of.sum(), pa.int32()), "row": rows[of], "col": cols[of]})
        dense = kernels.csr_cell_table(table, [(0, 20), (20, 45)], 2)
        base = dense.column("base")[0].as_py()
        (cp, jc, past, ir, names), = kernels.lists_of(dense, "cp", "jc", "past", "ir", "rows")
        assert base == 20 + 9 * part and len(cp) == (9, 9, 7)[part] + 1 and (jc >= 45).all() and len(ir) == of.sum()
        for col, row in [*zip(*kernels.gather_dense(base, cp, ir, np.arange(900)), strict=True), *zip(*kernels.gather(jc, past, ir, np.arange(900)), strict=True)]:
            found[int(col), int(names[row])] = found.get((int(col), int(names[row])), 0) + 1
    want = {}
    for pair in zip(cols.tolist(), rows.tolist(), strict=True):
        want[pair] = want.get(pair, 0) + 1
    assert found == want


def test_bags_carry_like_numbers():
    one, two = kernels.Bag(), kernels.Bag()
    for k in range(5):
        one.add(np.array([k]))
    for k in range(5, 12):
        two.add(np.array([k]))
    assert [t is not None for t in one.places] == [True, False, True] and sum(t is not None for t in two.places) == 3
    one.join(two)
    assert [t is not None for t in one.places] == [False, False, True, True]  # 12 blocks
    assert sorted(int(b[0]) for b in one.blocks()) == list(range(12))


def test_floor_rule_and_squares():
    assert block_bounds(7, 3) == [(0, 2), (2, 4), (4, 7)]
    assert block_bounds(2, 4) == [(0, 1), (1, 2), (2, 2), (2, 2)]
    assert [closest_square(p) for p in (1, 12, 16, 7)] == [(1, 1), (4, 3), (4, 4), (7, 1)]
    assert GridLayout(2, 3, 7).bounds()[5] == (5, 3, 7, 4, 7)
    with pytest.raises(ValueError):
        GridLayout(2, 2).bounds()


def test_kernel_choice_and_storage():
    assert kernels.choose_kernel(1_000, 1 << 20, 32) == "spa"
    assert kernels.choose_kernel(10_000, 1 << 33, 100) == "heap"
    assert 750e6 < metrics.spa_bytes_per_core(1 << 33, 100) < 800e6
    assert metrics.storage_words("csr_grid", 100, 1000, 4, 4) == 1400 > metrics.storage_words("dcsc", 100, 1000, 4, 4)


def test_cost_model_trends():
    machine = cost_model.Machine()
    dense, sparse = cost_model.predict(1 << 27, 1 << 33, 1024), cost_model.predict(1 << 31, 1 << 33, 1024)
    assert sparse["expand"] / sparse["fold"] > dense["expand"] / dense["fold"]  # expand matters more as density falls
    assert dense["grid_comm"] < dense["rows_comm"]
    assert cost_model.rows_local(1e6, 1e7, 4, machine) < cost_model.serial_cost(1e6, 1e7, machine)
    assert cost_model.threads_effect(40, 4, 1000) == (10, 100.0)
    assert cost_model.bandwidth_sweep(1 << 29, 1 << 33, 4096, [1000.0])[0][1] == "grid"


@pytest.mark.parametrize("far", [0, 1 << 61])
def test_heap_holds_numbers(far):
    rng = np.random.default_rng(3)
    entries = sorted({(int(a), int(b) + far * (b % 2)) for a, b in rng.integers(0, 40, (300, 2))})
    source, row = np.array(entries).T
    at, best = kernels.merge_heap(source, row)
    assert dict(zip(at.tolist(), best.tolist(), strict=True)) == {r: max(s for s, x in entries if x == r) for _, r in entries} and at.tolist() == sorted(set(row.tolist()))
    assert [len(x) for x in kernels.merge_heap(source[:0], row[:0])] == [0, 0]


def test_widths_share_one_exchange(spark, small, monkeypatch):
    packed, whole = [], grid.pack_dcsc
    monkeypatch.setattr(grid, "pack_dcsc", lambda *a, **k: packed.append(a) or whole(*a, **k))
    got = [tuple(r)[:5] for r in workloads.kernel_crossover(spark, small, (1, 3, 32)).collect()]
    arcs = {tuple(r) for r in workloads.load(spark, small, "purchase").arcs.collect()}
    cell = lambda col, w: min(col // ((1 << 15) // w), w - 1)
    assert got == [(w, len({cell(a, w) for a, _ in arcs}), len(arcs), len({(cell(a, w), b) for a, b in arcs}), len(arcs)) for w in (1, 3, 32)]
    assert not packed  # arcs are not sent again for each width
