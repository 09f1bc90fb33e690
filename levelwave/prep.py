"""Preparation of edge sets (src, dst): both directions, simple graphs, relabelling, triangle storage, degrees."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def simplify(edges: DataFrame, loops: bool = False, parallel: bool = False) -> DataFrame:
    """Without null ends, self loops and repeated edges, unless they are asked for."""
    out = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).where("src is not null and dst is not null")
    out = out if loops else out.where("src <> dst")
    return out if parallel else out.distinct()


def symmetrize(edges: DataFrame) -> DataFrame:
    """Each edge as two arcs, none twice, no self loops. Repeated edges go before there are two of each."""
    whole = edges.where("src is not null and dst is not null")
    once = simplify(whole.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))
    return once.select(F.inline(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))))


def triangle(arcs: DataFrame) -> DataFrame:
    """Half of a symmetric arc set: src < dst."""
    return arcs.where("src < dst")


def _round(half: Column, number: int, bits: int, seed: int) -> Column:
    return F.xxhash64(half, F.lit(number * 7919 + seed)).bitwiseAND(F.lit((1 << bits) - 1))


def feistel(vertex: Column, bits: int, seed: int = 0, rounds: int = 4) -> Column:
    """A keyed bijection of the integers under 2**(2 * bits), row by row and without a shuffle."""
    mask = (1 << bits) - 1
    left, right = F.shiftright(vertex, bits), vertex.bitwiseAND(F.lit(mask))
    for number in range(rounds):
        left, right = right, left.bitwiseXOR(_round(right, number, bits, seed))
    return F.shiftleft(left, bits).bitwiseOR(right)


def vertices(arcs: DataFrame) -> DataFrame:
    return arcs.select(F.col("src").alias("vertex")).union(arcs.select(F.col("dst").alias("vertex"))).distinct()


def relabel(arcs: DataFrame, mode: str = "feistel", seed: int = 0, bits: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(arcs on new ids, mapping (old, new)).

    feistel: a bijection computed in place. shuffle: dense new ids 0..n-1 in hash order, by range partitions and their
    offsets, with no global sort in one task. identity: as they are. rank: dense ids in the order of the old ones. locality:
    dense ids in the order of a traversal of each component from its least vertex (by level, then parent), so that vertices
    with a common neighbour get close ids and blocks of ids cut fewer arcs.
    """
    if mode == "identity":
        return arcs, vertices(arcs).select(F.col("vertex").alias("old"), F.col("vertex").alias("new"))
    if mode == "feistel":
        if bits is None:
            top = arcs.agg(F.max(F.greatest("src", "dst"))).first()[0] or 0
            bits = max(1, (int(top).bit_length() + 1) // 2)
        mapped = arcs.select(feistel(F.col("src"), bits, seed).alias("src"), feistel(F.col("dst"), bits, seed).alias("dst"))
        return mapped, vertices(arcs).select(F.col("vertex").alias("old"), feistel(F.col("vertex"), bits, seed).alias("new"))
    if mode == "locality":
        order, by = traversal_order(arcs), ["component", "dist", "parent", "vertex"]
    elif mode == "shuffle":
        from .rmat import shuffled

        order, by = vertices(arcs).select("vertex", shuffled(F.col("vertex"), seed).alias("a")), ["a", "vertex"]
    elif mode == "rank":
        order, by = vertices(arcs), ["vertex"]
    else:
        raise ValueError(f"no relabelling called {mode!r}")
    mapping = dense_ranks(order, by).select(F.col("vertex").alias("old"), F.col("rank").alias("new"))
    a, b = mapping.select(F.col("old").alias("src"), F.col("new").alias("s")), mapping.select(F.col("old").alias("dst"), F.col("new").alias("d"))
    return arcs.join(a, "src").join(b, "dst").select(F.col("s").alias("src"), F.col("d").alias("dst")), mapping


def traversal_order(arcs: DataFrame) -> DataFrame:
    """(vertex, dist, parent, component): one search from the least vertex of every component at once, arcs taken both ways."""
    from .components import components
    from .graphs import Graph
    from .rows import bfs_rows
    from .session import kept

    both = Graph(kept(symmetrize(arcs)))
    found = components(both)
    alone = vertices(arcs).join(found.select("vertex"), "vertex", "left_anti")  # only loops
    seeds = found.where("vertex = component").select("vertex", F.col("vertex").alias("parent"))
    order = bfs_rows(both, seeds).levels.join(found, "vertex")
    return order.unionByName(alone.select("vertex", F.lit(0).cast("int").alias("dist"), F.col("vertex").alias("parent"), F.col("vertex").alias("component")))


def dense_ranks(df: DataFrame, by: list[str]) -> DataFrame:
    """df with rank 0..n-1 in the order of the columns. Ranks within a range partition plus the sizes of those before."""
    from .session import stored

    placed = stored(df.repartitionByRange(*by).sortWithinPartitions(*by).withColumn("_part", F.spark_partition_id()).withColumn("_id", F.monotonically_increasing_id()), "ranks")
    first = placed.groupBy("_part").agg(F.count("*").alias("n"), F.min("_id").alias("first"))
    before = first.select(F.col("_part").alias("p"), F.col("n").alias("m"))  # one row a partition
    offset = first.join(before, F.col("p") < F.col("_part"), "left").groupBy("_part", "first").agg(F.coalesce(F.sum("m"), F.lit(0)).alias("offset"))
    ranked = placed.join(F.broadcast(offset), "_part")
    return ranked.withColumn("rank", F.col("_id") - F.col("first") + F.col("offset")).drop("_part", "_id", "first", "offset")


def degrees(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy(F.col("src").alias("vertex")).agg(F.count("*").alias("degree"))


def degree_stats(arcs: DataFrame, exact: bool = False) -> DataFrame:
    """One row: n, arcs, least, mean, p50, p99, most."""
    at = (lambda q: F.percentile("degree", F.lit(q))) if exact else (lambda q: F.percentile_approx("degree", q, 10_000).cast("double"))
    return degrees(arcs).agg(F.count("*").alias("n"), F.sum("degree").alias("arcs"), F.min("degree").alias("least"), F.round(F.avg("degree"), 6).alias("mean"), at(0.5).alias("p50"), at(0.99).alias("p99"), F.max("degree").alias("most"))
