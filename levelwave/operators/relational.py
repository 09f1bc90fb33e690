"""Filters, joins, sums, windows, sorts and sets around arcs and levels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


# --- filters ---
def edges_between(df: DataFrame, column: str, low: str, high: str) -> DataFrame:
    """Rows with low <= column < high; pushed to the scan."""
    return df.where((F.col(column) >= F.lit(low).cast("timestamp")) & (F.col(column) < F.lit(high).cast("timestamp")))


def where_status(orders: DataFrame, *status: str) -> DataFrame:
    return orders.where(F.col("o_orderstatus").isin(*status))


def where_type(events: DataFrame, pattern: str) -> DataFrame:
    return events.where(F.col("event_type").like(pattern))


# --- joins ---
def restrict_to(arcs: DataFrame, vertices: DataFrame) -> DataFrame:
    """Arcs with both ends among vertices."""
    v = vertices.select("vertex")
    return arcs.join(v.withColumnRenamed("vertex", "src"), "src", "left_semi").join(v.withColumnRenamed("vertex", "dst"), "dst", "left_semi").select("src", "dst")


def unseen(candidates: DataFrame, visited: DataFrame) -> DataFrame:
    return candidates.join(visited.select("vertex"), "vertex", "left_anti")


def fill_unreachable(levels: DataFrame, vertices: DataFrame) -> DataFrame:
    """All vertices; dist and parent are -1 where there is no way."""
    return vertices.select("vertex").join(levels, "vertex", "left").select("vertex", F.coalesce("dist", F.lit(-1)).alias("dist"), F.coalesce("parent", F.lit(-1)).cast("long").alias("parent"))


def with_weight(edges: DataFrame, weight: Column | float = 1.0) -> DataFrame:
    """(src, dst, weight); a null weight counts as 1."""
    value = weight if isinstance(weight, Column) else F.lit(float(weight))
    return edges.select("src", "dst", F.coalesce(value.cast("double"), F.lit(1.0)).alias("weight"))


def pairs(sources: DataFrame, vertices: DataFrame, most: int = 10_000) -> DataFrame:
    """(source, vertex) of each of a few sources with every vertex. The sources are counted and refused beyond most, so the
    product grows with the vertices only."""
    if sources.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} sources")
    return vertices.select("vertex").crossJoin(F.broadcast(sources.select(F.col("vertex").alias("source")))).select("source", "vertex")


def two_hop(arcs: DataFrame, sources: DataFrame) -> DataFrame:
    """(source, vertex) two arcs away from the given vertices."""
    first = arcs.join(sources.select(F.col("vertex").alias("src")), "src", "left_semi").select(F.col("src").alias("source"), F.col("dst").alias("mid"))
    return first.join(arcs.select(F.col("src").alias("mid"), F.col("dst").alias("vertex")), "mid").where("vertex <> source").select("source", "vertex").distinct()


def level_band(levels: DataFrame, bands: DataFrame) -> DataFrame:
    """(band, vertex) where low <= dist <= high; bands (band, low, high) is a handful of rows. Levels are counted first, so
    the range join meets one row a level."""
    per = levels.select("dist").distinct().join(F.broadcast(bands), (F.col("dist") >= F.col("low")) & (F.col("dist") <= F.col("high")))
    return levels.join(F.broadcast(per.select("dist", "band")), "dist").select("band", "vertex")


def edges_within(events: DataFrame, seconds: int) -> DataFrame:
    """(src, dst) of events of one user at most so many seconds apart. Times are cut into bins of that length, and a bin is
    joined with itself and the next, so a busy user's events are only met nearby."""
    e = events.select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at")).withColumn("bin", F.expr(f"at div {seconds * 1_000_000}"))
    a = e.select("user_id", F.col("event_id").alias("src"), F.col("at").alias("a"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    b = e.select("user_id", "bin", F.col("event_id").alias("dst"), F.col("at").alias("b"))
    later = (F.col("b") > F.col("a")) | ((F.col("b") == F.col("a")) & (F.col("dst") > F.col("src")))
    return a.join(b, ["user_id", "bin"]).where(later & (F.col("b") - F.col("a") <= seconds * 1_000_000)).select("src", "dst")


def latest_before(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """As-of join: left's rows with the value of right's last row of the same key that is not later; null if there is none.

    Both sides meet in one exchange and a running last value; nothing is paired.
    """
    both = left.select(key, at, *[c for c in left.columns if c not in (key, at)], F.lit(None).cast(right.schema[value].dataType).alias("_value"), F.lit(1).alias("_side"))
    names = both.columns
    other = right.select(*[F.lit(0).alias(c) if c == "_side" else F.col(value).alias("_value") if c == "_value" else F.col(c) if c in (key, at) else F.lit(None).cast(both.schema[c].dataType).alias(c) for c in names])
    order = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.unionByName(other).withColumn("latest", F.last("_value", ignorenulls=True).over(order)).where("_side = 1").drop("_value", "_side")


# --- sums ---
def levels_by(levels: DataFrame, attributes: DataFrame, keys: list[str], how: str = "rollup") -> DataFrame:
    """Vertices and greatest distance by keys: group, rollup or cube."""
    joined = levels.join(attributes, "vertex")
    grouped = {"group": joined.groupBy, "rollup": joined.rollup, "cube": joined.cube}[how](*keys)
    return grouped.agg(F.count("*").alias("vertices"), F.max("dist").alias("farthest"))


def grouping_sets(levels: DataFrame, attributes: DataFrame, a: str, b: str) -> DataFrame:
    joined = levels.join(attributes, "vertex")
    return joined.groupingSets([[F.col(a)], [F.col(b)], []], F.col(a), F.col(b)).agg(F.count("*").alias("vertices"))


def pivot_levels(levels: DataFrame, attributes: DataFrame, key: str, dists: list[int]) -> DataFrame:
    """One row a key, one column a distance."""
    counted = levels.join(attributes, "vertex").groupBy(key).pivot("dist", dists).agg(F.count(F.lit(1)))
    return counted.select(key, *[F.coalesce(F.col(str(d)), F.lit(0)).alias(f"d{d}") for d in dists])


def top_parent(levels: DataFrame) -> DataFrame:
    """(dist, parent, children) of the parent with most children in each level, the greatest of several."""
    counted = levels.where("vertex <> parent").groupBy("dist", "parent").agg(F.count("*").alias("children"))
    return counted.groupBy("dist").agg(F.max_by("parent", F.struct("children", "parent")).alias("parent"), F.max("children").alias("children"))


def approx_reach(levels: DataFrame) -> DataFrame:
    return levels.agg(F.approx_count_distinct("vertex").alias("reach"))


# --- windows ---
def rank_in_level(levels: DataFrame, degree: DataFrame) -> DataFrame:
    """Ranks by degree within a level. A level holds up to half of all vertices, so ranks are of (level, parent) groups."""
    order = Window.partitionBy("dist", "parent").orderBy(F.desc("degree"), "vertex")
    joined = levels.join(degree, "vertex")
    return joined.select("vertex", "dist", "degree", F.rank().over(Window.partitionBy("dist", "parent").orderBy(F.desc("degree"))).alias("rank"),
                         F.dense_rank().over(Window.partitionBy("dist", "parent").orderBy(F.desc("degree"))).alias("dense"), F.row_number().over(order).alias("place"), F.ntile(4).over(order).alias("quarter"))


def running_reach(levels: DataFrame) -> DataFrame:
    """(dist, vertices, reached): vertices of a level and of all up to it. Levels are summed first; the window has one row a level."""
    per = levels.groupBy("dist").agg(F.count("*").alias("vertices"))
    return per.select("dist", "vertices", F.sum("vertices").over(Window.orderBy("dist").rowsBetween(Window.unboundedPreceding, 0)).alias("reached"))


def recent_edges(events: DataFrame, seconds: int) -> DataFrame:
    """(event_id, recent): events of the user in the seconds up to this one."""
    order = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-seconds, 0)
    return events.select("event_id", F.count("*").over(order).alias("recent"))


def successors(events: DataFrame) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("event_id", F.lead("event_id").over(order).alias("after"), F.lag("event_id").over(order).alias("before"), F.first("event_id").over(order).alias("first"))


# --- sorts and sets ---
def hubs(degree: DataFrame, k: int) -> DataFrame:
    return degree.orderBy(F.desc("degree"), "vertex").limit(k)


def page_of(df: DataFrame, by: list[str], offset: int, n: int) -> DataFrame:
    return df.orderBy(*by).offset(offset).limit(n)


def union_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b)


def common_reach(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("vertex").intersect(b.select("vertex"))


def reach_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("vertex").exceptAll(b.select("vertex"))
