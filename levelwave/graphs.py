"""Graphs over the given tables, as arcs (src, dst) of tagged ids. Undirected graphs have each arc both ways."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .ids import hashed_key, tag
from .prep import simplify, symmetrize


@dataclass(frozen=True)
class Graph:
    """arcs: (src, dst). edges: the distinct input edges that rates are counted in; each is two arcs if undirected."""

    arcs: DataFrame
    directed: bool = False

    @property
    def spark(self) -> SparkSession:
        return self.arcs.sparkSession

    def edge_count(self) -> int:
        arcs = self.arcs.count()
        return arcs if self.directed else arcs // 2


def counts(graph: Graph) -> tuple[int, int]:
    """Vertices and arcs of a graph whose arcs go both ways."""
    return graph.arcs.agg(F.countDistinct("src"), F.count("*")).first()


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _undirected(edges: DataFrame) -> Graph:
    return Graph(symmetrize(edges))


def supply(spark: SparkSession, sf_dir: str) -> Graph:
    """Part and supplier of a line."""
    lines = _table(spark, sf_dir, "lineitem")
    return _undirected(lines.select(tag("l_partkey", "part").alias("src"), tag("l_suppkey", "supplier").alias("dst")))


def purchase(spark: SparkSession, sf_dir: str) -> Graph:
    """Part of a line and the customer of its order."""
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return _undirected(lines.join(orders, "l_orderkey").select(tag("l_partkey", "part").alias("src"), tag("o_custkey", "customer").alias("dst")))


def basket(spark: SparkSession, sf_dir: str) -> Graph:
    """Part and order of a line."""
    lines = _table(spark, sf_dir, "lineitem")
    return _undirected(lines.select(tag("l_partkey", "part").alias("src"), tag("l_orderkey", "order").alias("dst")))


def sourcing(spark: SparkSession, sf_dir: str) -> Graph:
    """Customer of an order and the supplier of its lines."""
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return _undirected(lines.join(orders, "l_orderkey").select(tag("o_custkey", "customer").alias("src"), tag("l_suppkey", "supplier").alias("dst")))


def hierarchy(spark: SparkSession, sf_dir: str) -> Graph:
    """Region to nation to customers and suppliers, customer to order to part; directed."""
    t = lambda name: _table(spark, sf_dir, name)
    parts = [
        t("nation").select(tag("n_regionkey", "region").alias("src"), tag("n_nationkey", "nation").alias("dst")),
        t("customer").select(tag("c_nationkey", "nation").alias("src"), tag("c_custkey", "customer").alias("dst")),
        t("supplier").select(tag("s_nationkey", "nation").alias("src"), tag("s_suppkey", "supplier").alias("dst")),
        t("orders").select(tag("o_custkey", "customer").alias("src"), tag("o_orderkey", "order").alias("dst")),
        t("lineitem").select(tag("l_orderkey", "order").alias("src"), tag("l_partkey", "part").alias("dst")),
    ]
    arcs = parts[0]
    for more in parts[1:]:
        arcs = arcs.unionByName(more)
    return Graph(simplify(arcs), directed=True)


def page_links(pages: DataFrame) -> DataFrame:
    """(page_id, href), each pair once."""
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()


def weblinks(spark: SparkSession, sf_dir: str, directed: bool = False) -> Graph:
    """Page and what it links to."""
    arcs = page_links(_table(spark, sf_dir, "pages")).select(tag("page_id", "page").alias("src"), tag(hashed_key(F.col("href")), "link").alias("dst"))
    return Graph(simplify(arcs), directed=True) if directed else _undirected(arcs)


def trail(spark: SparkSession, sf_dir: str) -> Graph:
    """Successive events of a user, and each user's first event with that of user number / 2: a deep tree."""
    events = _table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    placed = events.withColumn("next", F.lead("event_id").over(order)).withColumn("rank", F.row_number().over(order))
    steps = placed.where("next is not null").select(tag("event_id", "event").alias("src"), tag("next", "event").alias("dst"))
    first = placed.where("rank = 1").select("user_id", "event_id")
    above = first.select(F.col("user_id").alias("parent"), F.col("event_id").alias("parent_event"))
    tree = first.where("user_id > 0").join(above, F.expr("user_id div 2") == F.col("parent")).select(tag("parent_event", "event").alias("src"), tag("event_id", "event").alias("dst"))
    return _undirected(steps.unionByName(tree))


def dialog(spark: SparkSession, sf_dir: str) -> Graph:
    """Successive turns of a conversation."""
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    key = F.col("conv_id") * 64 + F.col("turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    steps = turns.withColumn("next", after).where("next is not null")
    return _undirected(steps.select(tag(key, "turn").alias("src"), tag(F.col("conv_id") * 64 + F.col("next"), "turn").alias("dst")))


def long_lines(spark: SparkSession, sf_dir: str, least: int) -> DataFrame:
    """(doc_id, line), each once: hashes of the lines of at least so many characters."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    lines = docs.select("doc_id", F.explode(F.split(F.lower("text"), "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return lines.where(F.length("line") >= least).select("doc_id", F.md5("line").alias("line")).distinct()


def copies(spark: SparkSession, sf_dir: str, least: int = 40) -> Graph:
    """Documents that have a line of at least so many characters, however many do, and the first of them: a star a line."""
    lines = long_lines(spark, sf_dir, least)
    hubs = lines.groupBy("line").agg(F.min("doc_id").alias("hub"), F.count("*").alias("n")).where("n > 1").select("line", "hub")
    return _undirected(lines.join(hubs, "line").where("hub < doc_id").select(tag("hub", "document").alias("src"), tag("doc_id", "document").alias("dst")))


def nearvec(spark: SparkSession, sf_dir: str, k: int = 8) -> Graph:
    """Each vector and its k nearest by cosine among those of its label."""
    from .operators.vectors import nearest

    pairs = nearest(_table(spark, sf_dir, "embeddings"), k)
    return _undirected(pairs.select(tag("vec_id", "vector").alias("src"), tag("other", "vector").alias("dst")))


def nearvec_all(spark: SparkSession, sf_dir: str, k: int = 8) -> Graph:
    """Each vector and its k nearest by cosine among all."""
    from .operators.vectors import nearest_of_all

    pairs = nearest_of_all(_table(spark, sf_dir, "embeddings"), k)
    return _undirected(pairs.select(tag("vec_id", "vector").alias("src"), tag("other", "vector").alias("dst")))


GRAPHS: dict[str, Callable[..., Graph]] = {f.__name__: f for f in (supply, purchase, basket, sourcing, hierarchy, weblinks, trail, dialog, copies, nearvec, nearvec_all)}
