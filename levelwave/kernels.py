"""Block formats and the local kernels that merge adjacency columns: CSR, DCSC, heap, sparse accumulator, thread pools."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from threading import Lock

import numpy as np
import pyarrow as pa

#: Places (cores) up to which the sparse accumulator is the faster kernel, and its bytes a row: value, flag.
SWITCH_AT, SPA_BYTES = 10_000, 9
#: Bytes that an accumulator may take in a task.
SPA_MEMORY = 512 << 20


def _compress(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys, offsets and values, sorted by key and value."""
    order = np.lexsort((values, keys))
    keys, values = keys[order], values[order]
    distinct, first = np.unique(keys, return_index=True)
    return distinct, np.append(first, len(keys)).astype(np.int64), values


def _number(table: pa.Table, name: str, otherwise: int) -> int:
    """The table's first value of a column, if it has that column."""
    return table.column(name)[0].as_py() if name in table.column_names else otherwise


def _packed(table: pa.Table, numbers: dict[str, pa.DataType], **lists: np.ndarray) -> pa.Table:
    """One row: the table's first value of each named column, then the lists."""
    out = {k: pa.array([_number(table, k, 0)], t) for k, t in numbers.items()}
    for name, values in lists.items():
        out[name] = pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), pa.array(values, pa.int64()))
    return pa.table(out)


def lists_of(table: pa.Table, *names: str) -> Iterator[tuple[np.ndarray, ...]]:
    """The named list columns of each row, as arrays on Arrow's own memory."""
    columns = [table.column(n) for n in names]
    for k in range(table.num_rows):
        yield tuple(c[k].values.to_numpy() for c in columns)


def csr_table(table: pa.Table) -> pa.Table:
    """One row (block, piece, slot, vertices, offsets, targets) from the arcs of a block's piece."""
    vertices, offsets, targets = _compress(table.column("src").to_numpy(), table.column("dst").to_numpy())
    return _packed(table, {"block": pa.int32(), "piece": pa.int32(), "slot": pa.int32()}, vertices=vertices, offsets=offsets, targets=targets)


def dcsc_table(table: pa.Table) -> pa.Table:
    """One row (cell, part, piece, jc, cp, ir, rows): non-empty columns, their pointers, row numbers within the piece, and the
    rows that these numbers stand for, sorted."""
    rows, number = np.unique(table.column("row").to_numpy(), return_inverse=True)
    jc, cp, ir = _compress(table.column("col").to_numpy(), number)
    return _packed(table, {"cell": pa.int32(), "part": pa.int32(), "piece": pa.int32()}, jc=jc, cp=cp, ir=ir, rows=rows)


def cells_of(row: np.ndarray, col: np.ndarray, n: int, columns: int) -> Iterator[tuple[int, pa.Table]]:
    """(cell, its DCSC row) of the arcs of some rows, sorted by column, in a grid of one row over ids by range."""
    cell = np.minimum(col // max(n // columns, 1), columns - 1)
    for j, part in enumerate(np.split(np.arange(len(col)), np.searchsorted(cell, np.arange(1, columns)))):
        if len(part):
            yield j, dcsc_table(pa.table({"row": row[part], "col": col[part]}))


def csr_cell_table(table: pa.Table, bounds: list[tuple[int, int]], columns: int) -> pa.Table:
    """One row (cell, part, base, cp, jc, past, ir, rows) with a pointer for every column of the part's range, empty ones too:
    what DCSC saves. bounds: first and end column of each grid column, whose parts share its range out.

    The last block also takes columns past the bounds, however many there are; those are held as non-empty columns (jc) with
    pointers (past) of their own."""
    cell, part, parts = _number(table, "cell", 0), _number(table, "part", 0), _number(table, "parts", 1)
    first, end = bounds[cell % columns]
    width = -(-(end - first) // parts)
    low, high = (min(first + k * width, end) for k in (part, part + 1))
    arcs = table.select(["row", "col"]).drop_null()  # a part may have none
    rows, number = np.unique(arcs.column("row").to_numpy(), return_inverse=True)
    jc, cp, ir = _compress(arcs.column("col").to_numpy(), number)
    inside = int(np.searchsorted(jc, end))
    pointers = np.zeros(high - low + 1, dtype=np.int64)
    pointers[jc[:inside] - low + 1] = np.diff(cp[: inside + 1])
    out = _packed(table, {"cell": pa.int32(), "part": pa.int32()}, cp=np.cumsum(pointers), jc=jc[inside:], past=cp[inside:], ir=ir, rows=rows)
    return out.add_column(2, "base", pa.array([low], pa.int64()))


def gather(keys: np.ndarray, offsets: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(key, value) of every entry of the wanted keys, wanted sorted."""
    if not len(keys) or not len(wanted):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return entries_of(keys, offsets, values, at[keys[at] == wanted])


def gather_dense(base: int, offsets: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same where every column has a pointer: no search, one read a column."""
    at = wanted[(wanted >= base) & (wanted < base + len(offsets) - 1)] - base
    source, value = entries_of(np.arange(len(offsets) - 1), offsets, values, at)
    return source + base, value


def entries_of(keys: np.ndarray, offsets: np.ndarray, values: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    begin, size = offsets[at], offsets[at + 1] - offsets[at]
    total = int(size.sum())
    index = np.arange(total) - np.repeat(np.cumsum(size) - size, size) + np.repeat(begin, size)
    return np.repeat(keys[at], size), values[index]


def merge_spa(sources: np.ndarray, rows: np.ndarray, size: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Greatest source of each row by a dense accumulator over the row numbers below size, whose indices are sorted at the end."""
    if not len(rows):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    low = 0 if size is not None else int(rows.min())
    value = np.full(size if size is not None else int(rows.max()) - low + 1, -1, dtype=np.int64)
    np.maximum.at(value, rows - low, sources)
    occupied = np.flatnonzero(value >= 0)
    return occupied + low, value[occupied]


def merge_heap(sources: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same by a priority queue over the columns, each a sorted run of rows; comes out sorted. The queue holds the next
    entry of each run as one number, row first and then place from behind, so that the greatest source of a row comes first."""
    n = len(rows)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    low = int(rows.min())
    names, number = (None, rows - low) if (int(rows.max()) - low + 1) * n < 1 << 63 else np.unique(rows, return_inverse=True)
    first = np.diff(sources, prepend=sources[0] - 1) != 0
    codes = number * n + np.arange(n - 1, -1, -1)
    queue, after = codes[first].tolist(), np.append(np.where(first[1:], -1, codes[1:]), -1).tolist()
    heapq.heapify(queue)
    out, waiting, pop, replace = [], n - len(queue), heapq.heappop, heapq.heapreplace
    while waiting:
        code = queue[0]
        out.append(code)
        following = after[n - 1 - code % n]
        if following < 0:
            pop(queue)
        else:
            replace(queue, following)
            waiting -= 1
    found = np.array(out + [pop(queue) for _ in range(len(queue))], dtype=np.int64)
    row = found // n
    found, row = found[new := np.diff(row, prepend=-1) != 0], row[new]
    return row + low if names is None else names[row], sources[n - 1 - found % n]


def choose_kernel(places: int, n: int, p_c: int, memory: int = SPA_MEMORY, switch_at: int = SWITCH_AT) -> str:
    """Accumulator at low concurrency while its dense vectors fit in memory, else the heap."""
    return "spa" if places < switch_at and SPA_BYTES * n / max(p_c, 1) <= memory else "heap"


def merge(sources: np.ndarray, rows: np.ndarray, kernel: str, size: int | None = None, places: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """kernel: spa, heap, or auto, which is chosen by the number of places and the accumulator's size."""
    if kernel == "auto":
        span = size if size is not None else int(rows.max()) - int(rows.min()) + 1 if len(rows) else 0
        kernel = choose_kernel(places, span, 1)
    return merge_spa(sources, rows, size) if kernel == "spa" else merge_heap(sources, rows)


class Bag:
    """A set of blocks as pennants: place k is empty or holds a tree of 2**k blocks. Adding and joining carry like binary
    numbers, so two bags are joined by as many steps as they have places, whatever they hold."""

    def __init__(self) -> None:
        self.places: list[object | None] = []

    def _carry(self, tree: object, k: int) -> None:
        while len(self.places) <= k:
            self.places.append(None)
        while self.places[k] is not None:
            tree, self.places[k], k = (self.places[k], tree), None, k + 1
            if k == len(self.places):
                self.places.append(None)
        self.places[k] = tree

    def add(self, block: np.ndarray) -> None:
        self._carry(block, 0)

    def join(self, other: Bag) -> None:
        for k, tree in enumerate(other.places):
            if tree is not None:
                self._carry(tree, k)

    def blocks(self) -> Iterator[np.ndarray]:
        waiting = [t for t in self.places if t is not None]
        while waiting:
            tree = waiting.pop()
            if isinstance(tree, tuple):
                waiting += tree
            else:
                yield tree


class Stacks:
    """Where threads put what they find: a list each (local), one list under a lock (shared), or a bag each, joined at the
    end (bag)."""

    def __init__(self, kind: str, threads: int):
        if kind not in ("local", "shared", "bag"):
            raise ValueError(f"no frontier store called {kind!r}")
        self.kind, self.lock, self.block = kind, Lock(), 128
        self.parts: list[list] = [[] for _ in range(threads if kind == "local" else 1)]
        self.bags = [Bag() for _ in range(threads)]

    def push(self, thread: int, values: np.ndarray) -> None:
        if self.kind == "local":
            self.parts[thread].append(values)
        elif self.kind == "shared":
            with self.lock:
                self.parts[0].extend(values.tolist())
        else:
            for k in range(0, len(values), self.block):
                self.bags[thread].add(values[k : k + self.block])

    def all(self) -> np.ndarray:
        if self.kind == "shared":
            return np.array(self.parts[0], dtype=np.int64)
        if self.kind == "bag":
            whole = Bag()
            for bag in self.bags:
                whole.join(bag)
            return np.concatenate([np.empty(0, np.int64), *whole.blocks()])
        return np.concatenate([np.empty(0, np.int64), *(x for part in self.parts for x in part)])


def pieces(items: np.ndarray, n: int) -> list[np.ndarray]:
    return [x for x in np.array_split(items, n) if len(x)]


@dataclass
class BlockCsr:
    """Rows of one block: distinct vertices, offsets, targets."""

    vertices: np.ndarray
    offsets: np.ndarray
    targets: np.ndarray

    @classmethod
    def from_arcs(cls, src: np.ndarray, dst: np.ndarray) -> BlockCsr:
        return cls(*_compress(src, dst))

    def neighbours(self, frontier: np.ndarray, threads: int = 1, visit_check: str = "benign") -> tuple[np.ndarray, np.ndarray, int]:
        """Targets of the frontier's arcs with their greatest source, and the number of arcs scanned.

        Threads merge their own part of the frontier; a target that several parts reach comes out several times unless
        visit_check is atomic, which merges the parts again.
        """
        parts = pieces(np.sort(frontier), threads)

        def expand(part: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
            source, target = gather(self.vertices, self.offsets, self.targets, part)
            return *_greatest(source, target), len(target)

        with ThreadPoolExecutor(threads) as pool:
            found = list(pool.map(expand, parts))
        vertex = np.concatenate([np.empty(0, np.int64), *(f[0] for f in found)])
        parent = np.concatenate([np.empty(0, np.int64), *(f[1] for f in found)])
        if visit_check == "atomic":
            vertex, parent = _greatest(parent, vertex)
        return vertex, parent, sum(f[2] for f in found)


def by_source(frontier: pa.Table, column: str, run: Callable[[np.ndarray], tuple[np.ndarray, ...]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(source, vertex, parent) of run() over the frontier's entries of each source; all have source 0 where there is no such
    column."""
    names, entries = frontier.column_names, frontier.column(column).to_numpy()
    source = frontier.column("source").to_numpy() if "source" in names else np.zeros(len(entries), np.int64)
    found = [(s, *run(entries[source == s])[:2]) for s in np.unique(source).tolist()]
    return tuple(np.concatenate([np.empty(0, np.int64), *(np.full(len(f[1]), f[0]) if k == 0 else f[k] for f in found)]) for k in range(3))


def _greatest(source: np.ndarray, target: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct targets with their greatest source, whatever range the ids span."""
    distinct, number = np.unique(target, return_inverse=True)
    at, best = merge_spa(source, number, len(distinct))
    return distinct[at], best


def spmsv_piece(jc: np.ndarray, cp: np.ndarray, ir: np.ndarray, rows: np.ndarray, frontier: np.ndarray, kernel: str, places: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """Rows of one DCSC piece that the frontier's columns reach, sorted, with the greatest column of each."""
    at, best = merge(*gather(jc, cp, ir, frontier), kernel, len(rows), places)
    return rows[at], best


def spmsv_cell(parts: list[tuple[np.ndarray, ...]], frontier: np.ndarray, kernel: str = "auto", threads: int = 1, places: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """One cell: its pieces (jc, cp, ir, rows) hold disjoint rows, so threads need no merge afterwards."""
    frontier = np.unique(frontier)
    with ThreadPoolExecutor(max(threads, 1)) as pool:
        found = list(pool.map(lambda a: spmsv_piece(*a, frontier, kernel, places), parts))
    return tuple(np.concatenate([np.empty(0, np.int64), *(f[k] for f in found)]) for k in range(2))
