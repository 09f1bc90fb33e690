"""What is built on traversals: bounds, paths, trees, several sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graphs import Graph
from .grid import bfs_grid
from .layout import GridLayout, RowLayout
from .loop import Traversal
from .rows import bfs_rows
from .session import kept


def khop(graph: Graph, source: int, k: int, layout: RowLayout = RowLayout()) -> DataFrame:
    return bfs_rows(graph, source, layout, max_level=k).levels


def st_distance(graph: Graph, source: int, target: int, layout: RowLayout = RowLayout()) -> int | None:
    """Hops from source to target; None if it can't be reached. Stops at the target's level."""
    row = bfs_rows(graph, source, layout, target=target).levels.where(F.col("vertex") == target).first()
    return None if row is None else row["dist"]


def extract_path(levels: DataFrame, target: int) -> DataFrame:
    """(step, vertex) of the tree path from the source to target, one lookup a step; no rows if target wasn't reached."""
    spark, path, at = levels.sparkSession, [], target
    levels = kept(levels.repartition("vertex"))
    while (row := levels.where(F.col("vertex") == at).first()) is not None:
        path.append((row["dist"], at))
        if row["parent"] == at:
            break
        at = row["parent"]
    return spark.createDataFrame(path[::-1], "step int, vertex long")


def path_length(path: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """One row (hops, length): with weights (src, dst, weight) the sum along the path, else the hops."""
    steps = path.select("step", "vertex", F.lag("vertex").over(Window.orderBy("step")).alias("before")).where("before is not null")  # a path is short
    if weights is None:
        return steps.agg(F.count("*").alias("hops"), F.count("*").cast("double").alias("length"))
    return steps.join(weights, (F.col("src") == F.col("before")) & (F.col("dst") == F.col("vertex"))).agg(F.count("*").alias("hops"), F.sum("weight").alias("length"))


def level_profile(levels: DataFrame) -> DataFrame:
    return levels.groupBy("dist").agg(F.count("*").alias("vertices"))


def eccentricity(levels: DataFrame) -> DataFrame:
    return levels.agg(F.max("dist").alias("eccentricity"), F.count("*").alias("reached"))


def spanning_tree(levels: DataFrame) -> DataFrame:
    return levels.where("vertex <> parent").select("parent", "vertex")


def subtree_sizes(levels: DataFrame) -> DataFrame:
    """(vertex, size): vertices of the tree below each one, itself included, added up from the deepest level."""
    sizes, deepest = None, levels.agg(F.max("dist")).first()[0] or 0
    levels = kept(levels)
    for level in range(deepest, -1, -1):
        here = levels.where(F.col("dist") == level)
        if sizes is None:
            now = here.select("vertex", "parent", F.lit(1).cast("long").alias("size"))
        else:
            below = now.groupBy(F.col("parent").alias("vertex")).agg(F.sum("size").alias("below"))
            now = here.join(below, "vertex", "left").select("vertex", "parent", (F.coalesce("below", F.lit(0)) + 1).cast("long").alias("size"))
        now = kept(now)
        sizes = now.select("vertex", "size") if sizes is None else sizes.unionAll(now.select("vertex", "size"))
    return sizes


def bipartite_check(graph: Graph, levels: DataFrame) -> DataFrame:
    """One row: arcs inside a level; none if what was reached is bipartite."""
    a, b = levels.select(F.col("vertex").alias("src"), F.col("dist").alias("x")), levels.select(F.col("vertex").alias("dst"), F.col("dist").alias("y"))
    return graph.arcs.join(a, "src").join(b, "dst").where("x = y").agg(F.count("*").alias("arcs_within"))


def bfs_many(graph: Graph, sources: list[int], layout: RowLayout | GridLayout = RowLayout(), **limits: object) -> DataFrame:
    """(source, vertex, dist, parent) of several traversals that share every superstep, on rows or a grid."""
    run = bfs_grid if isinstance(layout, GridLayout) else bfs_rows
    return run(graph, sources, layout, **limits).levels


def visit_counts(graph: Graph, source: int, layout: RowLayout = RowLayout()) -> tuple[Traversal, list[tuple[int, int]]]:
    """The visit hook at work: (level, vertices) as they are first seen."""
    seen: list[tuple[int, int]] = []
    done = bfs_rows(graph, source, layout, on_visit=lambda df, level: seen.append((level, df.count())))
    return done, seen
