"""Where vertices and arcs live: rows of a 1D layout, cells of a 2D grid, and the owner of a vertex's state."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Arcs of a place, where no number of places is given: 16 bytes each, so 64 MB; and the fewest places then.
PLACE_ARCS, LEAST_PLACES = 4_000_000, 4


def places_for(arcs: int) -> int:
    return max(LEAST_PLACES, -(-arcs // PLACE_ARCS))


def block(vertex: Column, blocks: int, n: int | None) -> Column:
    """Block of a vertex. With n (ids 0..n-1): equal blocks of floor(n / blocks), the last takes the rest; else by hash."""
    if n is None:
        return F.pmod(F.xxhash64(vertex), F.lit(blocks)).cast("int")
    size = max(n // blocks, 1)
    return F.least(F.floor(vertex / F.lit(size)), F.lit(blocks - 1)).cast("int")


def block_bounds(n: int, blocks: int) -> list[tuple[int, int]]:
    """[first, end) of each block under the floor rule."""
    size = max(n // blocks, 1)
    return [(min(i * size, n), min((i + 1) * size, n) if i < blocks - 1 else n) for i in range(blocks)]


def closest_square(p: int) -> tuple[int, int]:
    """The grid of p places whose sides are nearest to each other, the larger one first."""
    rows = next(r for r in range(math.isqrt(p), 0, -1) if p % r == 0)
    return p // rows, rows


@dataclass(frozen=True)
class RowLayout:
    """p owners of vertices with all their outgoing arcs. Without p it follows the number of arcs."""

    p: int | None = None
    n: int | None = None

    def sized(self, arcs: int) -> RowLayout:
        return self if self.p else replace(self, p=places_for(arcs))

    def owner(self, vertex: Column) -> Column:
        return block(vertex, self.p, self.n)

    def place(self, arcs: DataFrame) -> DataFrame:
        return arcs.select(self.owner(F.col("src")).alias("owner"), "src", "dst")


@dataclass(frozen=True)
class GridLayout:
    """p_r by p_c cells of the transposed adjacency matrix: a cell holds arcs by blocks of target (row) and source (column).

    vector says who owns a vertex's state: grid (all cells), diagonal, or row_head (the first cell of each row). Without
    sides the grid follows the number of arcs: a square, or with wide one more column than rows.
    """

    p_r: int | None = None
    p_c: int | None = None
    n: int | None = None
    vector: str = "grid"
    wide: bool = False

    def __post_init__(self) -> None:
        if self.vector not in ("grid", "diagonal", "row_head"):
            raise ValueError(f"no vector placement called {self.vector!r}")
        if self.vector == "diagonal" and self.p_r != self.p_c:
            raise ValueError("a diagonal needs a square grid")

    def sized(self, arcs: int) -> GridLayout:
        if self.p_r and self.p_c:
            return self
        side = math.isqrt(places_for(arcs) - 1) + 1
        return replace(self, p_r=side, p_c=side + self.wide)

    @property
    def p(self) -> int:
        return self.p_r * self.p_c

    def row(self, vertex: Column) -> Column:
        return block(vertex, self.p_r, self.n)

    def column(self, vertex: Column) -> Column:
        return block(vertex, self.p_c, self.n)

    def cell(self, src: Column, dst: Column) -> Column:
        return self.row(dst) * self.p_c + self.column(src)

    def owner(self, vertex: Column) -> Column:
        """The cell that owns a vertex's entry of every vector: one of the vertex's grid row."""
        row = self.row(vertex)
        if self.vector == "grid":
            within = F.pmod(F.xxhash64(vertex, F.lit(17)), F.lit(self.p_c)) if self.n is None else F.pmod(vertex, F.lit(self.p_c))
            return (row * self.p_c + within).cast("int")
        return (row * self.p_c + (row if self.vector == "diagonal" else 0)).cast("int")

    def place(self, arcs: DataFrame) -> DataFrame:
        return arcs.select(self.cell(F.col("src"), F.col("dst")).alias("cell"), F.col("dst").alias("row"), F.col("src").alias("col"))

    def bounds(self) -> list[tuple[int, int, int, int, int]]:
        """(cell, first row, end row, first column, end column) under the floor rule."""
        if self.n is None:
            raise ValueError("bounds are of layouts by range only")
        rows, cols = block_bounds(self.n, self.p_r), block_bounds(self.n, self.p_c)
        return [(i * self.p_c + j, *rows[i], *cols[j]) for i in range(self.p_r) for j in range(self.p_c)]
