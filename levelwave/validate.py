"""Rules that every right result obeys, counted as violations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graphs import Graph


def validate(graph: Graph, levels: DataFrame, source: int) -> DataFrame:
    """(check_name, violations): source at 0, parents one level up and along arcs, arcs spanning at most a level, closure."""
    at = levels.select(F.col("vertex").alias("src"), F.col("dist").alias("ds"))
    to = levels.select(F.col("vertex").alias("dst"), F.col("dist").alias("dd"))
    ends = graph.arcs.join(at, "src").join(to, "dst", "left")
    span = F.col("dd") - F.col("ds")
    wide = (span > 1) if graph.directed else (F.abs(span) > 1)
    tree = levels.where("vertex <> parent").select(F.col("parent").alias("src"), F.col("vertex").alias("dst"), "dist")
    count = lambda df, name: df.agg(F.count("*").alias("violations")).select(F.lit(name).alias("check_name"), "violations")
    checks = [
        count(levels.where((F.col("vertex") == source) != ((F.col("dist") == 0) & (F.col("vertex") == F.col("parent")))), "source"),
        count(tree.join(graph.arcs, ["src", "dst"], "left_anti"), "tree_arc"),
        count(tree.join(at, "src", "left").where(F.col("ds").isNull() | (F.col("ds") + 1 != F.col("dist"))), "parent_level"),
        count(ends.where(wide), "arc_span"),
        count(ends.where("dd is null"), "closed"),
        count(levels.groupBy("vertex").count().where("count > 1"), "once"),
    ]
    return reduce(DataFrame.unionAll, checks)
