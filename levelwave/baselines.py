"""What the methods are compared with: ship every pair, replicate what was visited, vertex programs, recursive SQL."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import Graph
from .layout import RowLayout, places_for
from .loop import Placement, Traversal, run_levels
from .rows import placed_arcs
from .session import kept

#: Visited vertices that the replicated variant may send everywhere.
REPLICATED_MOST = 2_000_000


def bfs_reference(graph: Graph, source: int, p: int | None = None, replicated: bool = False, trace: bool = False, **limits: object) -> Traversal:
    """Every (target, source) pair is shipped, with no combining at the sender; only owners test what was visited.

    replicated sends the visited set to all places, which drop known targets before shipping. A set of more than
    REPLICATED_MOST vertices is met by a shuffle instead, with the same rows.
    """
    layout = RowLayout(p) if p else RowLayout().sized(graph.arcs.count())
    place = Placement(layout.p, layout.owner)
    arcs = placed_arcs(graph.arcs, layout)
    seen: list[DataFrame] = []

    def step(frontier: DataFrame) -> tuple[DataFrame, dict[str, object]]:
        near = frontier.select("owner", F.col("vertex").alias("src")).hint("shuffle_hash")
        pairs = arcs.join(near, ["owner", "src"]).select(F.col("dst").alias("vertex"), F.col("src").alias("parent"))
        if replicated:
            seen.append(frontier.select("vertex"))
            visited = reduce(DataFrame.unionAll, seen)
            small = visited.count() <= REPLICATED_MOST
            pairs = pairs.join(F.broadcast(visited) if small else visited.hint("shuffle_hash"), "vertex", "left_anti")
        counts = {"scanned": pairs.count()} if trace else {}
        counts |= {"shipped": counts["scanned"]} if trace else {}
        return place.combined(place.put(pairs)), counts

    return run_levels(graph.spark, source, step, place, graph.directed, **limits)


def bfs_messages(graph: Graph, source: int | list[int], p: int | None = None) -> DataFrame:
    """A general vertex program: each superstep sends a message along every arc of an active vertex, through arcs that are
    not placed beforehand, and rewrites the state of all vertices. It ends when no vertex is active, however deep that is."""
    spark, p, sources = graph.spark, p or places_for(graph.arcs.count()), source if isinstance(source, list) else [source]
    first = spark.createDataFrame([(s, s) for s in sources], "source long, vertex long")
    ends = graph.arcs.select(F.col("src").alias("vertex")).union(graph.arcs.select(F.col("dst").alias("vertex"))).distinct()
    ends = ends.select(F.explode(F.array(*[F.lit(s).cast("long") for s in sources])).alias("source"), "vertex").union(first).distinct()
    own, key = F.col("vertex") == F.col("source"), ["source", "vertex"]
    state = kept(ends.select(*key, F.when(own, 0).cast("int").alias("dist"), F.when(own, F.col("vertex")).alias("parent")))
    arcs, level = kept(graph.arcs.select("src", "dst").repartition(p)), 0
    while not state.where(F.col("dist") == level).isEmpty():
        active, level = state.where(F.col("dist") == level).select("source", F.col("vertex").alias("src")), level + 1
        messages = arcs.join(active, "src").select("source", F.col("dst").alias("vertex"), F.col("src").alias("sender")).groupBy(*key).agg(F.max("sender").alias("sender"))
        fresh = F.col("dist").isNull() & F.col("sender").isNotNull()
        state = kept(state.join(messages, key, "full_outer").select(
            *key, F.when(fresh, F.lit(level)).otherwise(F.col("dist")).cast("int").alias("dist"), F.when(fresh, F.col("sender")).otherwise(F.col("parent")).alias("parent")))
    out = state.where("dist is not null")
    return out if isinstance(source, list) else out.drop("source")


def bfs_recursive_sql(spark: SparkSession, arcs_view: str, source: int, level_bound: int) -> DataFrame:
    """Walks by a recursive query, reduced to distances afterwards. The recursion can't drop what it has seen, so its rows
    grow with the number of walks: a contrast for bounds of a few levels only."""
    return spark.sql(f"""
        WITH RECURSIVE walk(vertex, dist, parent) AS (
          SELECT CAST({int(source)} AS BIGINT), 0, CAST({int(source)} AS BIGINT)
          UNION ALL
          SELECT a.dst, w.dist + 1, a.src FROM walk w JOIN {arcs_view} a ON a.src = w.vertex WHERE w.dist < {int(level_bound)}),
        best AS (SELECT vertex, min(dist) AS dist FROM walk GROUP BY vertex)
        SELECT w.vertex, CAST(w.dist AS INT) AS dist, max(w.parent) AS parent FROM walk w JOIN best b ON b.vertex = w.vertex AND b.dist = w.dist GROUP BY w.vertex, w.dist""")
