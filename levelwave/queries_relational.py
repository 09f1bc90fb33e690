"""Queries of the operators around traversals."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import functions, ids, oracle, prep, rows, streaming
from .operators import relational as rel
from .queries import graph, query
from .session import shared_folder
from .sources import number_range


def _levels(s: SparkSession, d: str) -> DataFrame:
    return rows.bfs_rows(graph(s, d, "purchase"), 0).levels


def _customers(s: SparkSession, d: str) -> DataFrame:
    return s.read.parquet(f"{d}/customer.parquet").selectExpr("c_custkey * 16 + 2 AS vertex", "c_mktsegment AS segment", "c_nationkey AS nation")


_LV = f"WITH RECURSIVE {oracle.with_levels('purchase', 0)}, c AS (SELECT c_custkey * 16 + 2 AS vertex, c_mktsegment AS segment, c_nationkey AS nation FROM customer), j AS (SELECT * FROM lv JOIN c USING (vertex))"
_DEG = ", g AS (SELECT src AS vertex, count(*) AS degree FROM arcs GROUP BY src)"
query("levels_by_segment_rollup", f"{_LV} SELECT segment, coalesce(dist, -1) AS dist, count(*) AS vertices, max(dist) AS farthest FROM j GROUP BY ROLLUP (segment, dist)")(
    lambda s, d: rel.levels_by(_levels(s, d).withColumn("d", F.col("dist")), _customers(s, d), ["segment", "d"]).withColumnRenamed("d", "dist").fillna(-1, ["dist"]))
query("levels_by_nation_cube", f"{_LV} SELECT coalesce(nation, -1) AS nation, segment, count(*) AS vertices, max(dist) AS farthest FROM j GROUP BY CUBE (nation, segment)")(lambda s, d: rel.levels_by(_levels(s, d), _customers(s, d), ["nation", "segment"], "cube").fillna(-1, ["nation"]))
query("levels_grouping_sets", f"{_LV} SELECT coalesce(nation, -1) AS nation, segment, count(*) AS vertices FROM j GROUP BY GROUPING SETS ((nation), (segment), ())")(lambda s, d: rel.grouping_sets(_levels(s, d), _customers(s, d), "nation", "segment").fillna(-1, ["nation"]))
query("levels_pivot", f"{_LV} SELECT segment, " + ", ".join(f"count(*) FILTER (dist = {k}) AS d{k}" for k in range(5)) + " FROM j GROUP BY segment")(lambda s, d: rel.pivot_levels(_levels(s, d), _customers(s, d), "segment", list(range(5))))
query("top_parent", f"{_LV}, p AS (SELECT dist, parent, count(*) AS children FROM lv WHERE vertex <> parent GROUP BY ALL) SELECT dist, arg_max(parent, (children, parent)) AS parent, max(children) AS children FROM p GROUP BY dist")(lambda s, d: rel.top_parent(_levels(s, d)))
query("running_reach", f"{_LV} SELECT dist, count(*) AS vertices, sum(count(*)) OVER (ORDER BY dist)::BIGINT AS reached FROM lv GROUP BY dist")(lambda s, d: rel.running_reach(_levels(s, d)))
query("rank_in_level", f"{_LV}{_DEG} SELECT vertex, dist, degree, rank() OVER w AS rank, dense_rank() OVER w AS dense, row_number() OVER v AS place, ntile(4) OVER v AS quarter FROM lv JOIN g USING (vertex) WINDOW w AS (PARTITION BY dist, parent ORDER BY degree DESC), v AS (PARTITION BY dist, parent ORDER BY degree DESC, vertex)")(
    lambda s, d: rel.rank_in_level(_levels(s, d), prep.degrees(graph(s, d, "purchase").arcs)))
query("level_bands", f"{_LV} SELECT band, vertex FROM lv JOIN (VALUES ('near', 0, 1), ('far', 2, 9)) b(band, low, high) ON dist BETWEEN low AND high")(
    lambda s, d: rel.level_band(_levels(s, d), s.createDataFrame([("near", 0, 1), ("far", 2, 9)], "band string, low int, high int")))
query("fill_unreachable", f"WITH RECURSIVE {oracle.with_levels('dialog', 12)}, v AS (SELECT DISTINCT src AS vertex FROM arcs) SELECT v.vertex, coalesce(dist, -1) AS dist, coalesce(parent, -1) AS parent FROM v LEFT JOIN lv USING (vertex)")(
    lambda s, d: rel.fill_unreachable(rows.bfs_rows(graph(s, d, "dialog"), 12).levels, prep.vertices(graph(s, d, "dialog").arcs)))
query("restrict_to_level", f"{_LV}, k AS (SELECT vertex FROM lv WHERE dist <= 2) SELECT src, dst FROM arcs WHERE src IN (SELECT vertex FROM k) AND dst IN (SELECT vertex FROM k)")(lambda s, d: rel.restrict_to(graph(s, d, "purchase").arcs, _levels(s, d).where("dist <= 2")))
query("two_hop", f"WITH {oracle.arcs('supply')} SELECT DISTINCT a.src AS source, b.dst AS vertex FROM arcs a JOIN arcs b ON b.src = a.dst WHERE a.src IN (0, 16) AND b.dst <> a.src")(
    lambda s, d: rel.two_hop(graph(s, d, "supply").arcs, s.createDataFrame([(0,), (16,)], "vertex long")))
query("edges_within_hour", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND (b.ts, b.event_id) > (a.ts, a.event_id) AND b.ts <= a.ts + INTERVAL 1 HOUR")(lambda s, d: rel.edges_within(s.read.parquet(f"{d}/events.parquet"), 3600))
query("recent_edges", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events")(lambda s, d: rel.recent_edges(s.read.parquet(f"{d}/events.parquet"), 3600))
query("successors", "SELECT event_id, coalesce(lead(event_id) OVER w, -1) AS after, coalesce(lag(event_id) OVER w, -1) AS before, first(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(lambda s, d: rel.successors(s.read.parquet(f"{d}/events.parquet")).fillna(-1))
query("asof_event", "SELECT a.event_id, b.value AS latest FROM events a ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts WHERE a.event_type <> 'purchase'")(
    lambda s, d: (lambda e: rel.latest_before(e.where("event_type <> 'purchase'").select("user_id", "ts", "event_id"), e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value")), "user_id", "ts", "value").select("event_id", "latest"))(s.read.parquet(f"{d}/events.parquet")))
query("shipped_window_edges", f"SELECT l_partkey * 16 AS src, l_suppkey * 16 + 1 AS dst FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'")(
    lambda s, d: rel.edges_between(s.read.parquet(f"{d}/lineitem.parquet"), "l_shipdate", "1996-01-01", "1997-01-01").selectExpr("l_partkey * 16 AS src", "l_suppkey * 16 + 1 AS dst"))
query("page_hosts", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")(lambda s, d: s.read.parquet(f"{d}/pages.parquet").select("page_id", functions.link_host(F.col("url")).alias("host")))
query("event_keys", "SELECT event_id, json_extract_string(props, '$.k') AS k, date_trunc('day', ts)::TIMESTAMP AS day FROM events")(lambda s, d: s.read.parquet(f"{d}/events.parquet").select("event_id", functions.event_key(F.col("props")).alias("k"), functions.edge_day(F.col("ts")).alias("day")))


@query("dialog_udtf", """WITH t AS (SELECT DISTINCT conv_id, turn FROM conversations), n AS (SELECT conv_id, turn, row_number() OVER (PARTITION BY conv_id ORDER BY turn) - 1 AS k, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before, count(*) OVER (PARTITION BY conv_id) AS m FROM t)
  SELECT conv_id AS graph_id, (conv_id * 64 + turn) * 16 + 12 AS vertex, k::INT AS dist, (conv_id * 64 + coalesce(before, turn)) * 16 + 12 AS parent FROM n WHERE m > 1""")
def _dialog_udtf(s: SparkSession, d: str) -> DataFrame:
    functions.register(s)
    graph(s, d, "dialog").arcs.selectExpr("(src div 16) div 64 AS graph_id", "src", "dst").createOrReplaceTempView("levelwave_dialogs")
    return s.sql("SELECT * FROM bfs_small(TABLE(SELECT * FROM levelwave_dialogs) PARTITION BY graph_id)")


_KIND = "(SELECT min(event_id) FROM events)"


@query("stream_levels", "SELECT user_id * 16 + 9 AS vertex, CASE WHEN user_id = 0 THEN 0 ELSE 2 END AS dist FROM (SELECT DISTINCT user_id FROM events)")
def _stream(s: SparkSession, d: str) -> DataFrame:
    """User 0 reaches every user who shares a kind of event, in two hops; events come in five files, oldest first."""
    import uuid

    base = f"{shared_folder(s)}/levelwave/stream-{uuid.uuid4().hex}"
    s.read.parquet(f"{d}/events.parquet").repartitionByRange(5, "ts").write.parquet(f"{base}/in")
    kept = streaming.MaintainedLevels(s, 9, f"{base}/state")
    kept.start(streaming.user_type_arcs(streaming.read_events(s, f"{base}/in", 2)), f"{base}/checkpoint").awaitTermination()
    return kept.levels().where("vertex % 16 = 9").select("vertex", "dist")


# --- weights, tags, products, pages, paths -----------------------------------------------------------------------------
query("weighted_edges", "SELECT l_partkey * 16 AS src, l_suppkey * 16 + 1 AS dst, coalesce(l_quantity, 1)::DOUBLE AS weight FROM lineitem")(
    lambda s, d: rel.with_weight(s.read.parquet(f"{d}/lineitem.parquet").selectExpr("l_partkey * 16 AS src", "l_suppkey * 16 + 1 AS dst", "l_quantity AS q").select("src", "dst", "q"), F.col("q")))
query("untagged_kinds", f"WITH {oracle.arcs('hierarchy')} SELECT CASE v % 16 WHEN 0 THEN 'part' WHEN 1 THEN 'supplier' WHEN 2 THEN 'customer' WHEN 3 THEN 'order' WHEN 4 THEN 'nation' ELSE 'region' END AS kind, count(*) AS n, max(v // 16) AS greatest FROM (SELECT src AS v FROM arcs UNION SELECT dst FROM arcs) GROUP BY 1")(
    lambda s, d: prep.vertices(graph(s, d, "hierarchy").arcs).select(ids.untag("vertex").alias("t")).groupBy(F.col("t.kind").alias("kind")).agg(F.count("*").alias("n"), F.max("t.key").alias("greatest")))
query("source_pairs", f"WITH RECURSIVE {oracle.with_levels('dialog', 12)}, v AS (SELECT DISTINCT src AS vertex FROM arcs) SELECT source, count(*) AS vertices, sum(vertex)::BIGINT AS total FROM (VALUES (12::BIGINT), (28::BIGINT)) t(source), v GROUP BY source")(
    lambda s, d: rel.pairs(s.createDataFrame([(12,), (28,)], "vertex long"), prep.vertices(graph(s, d, "dialog").arcs)).groupBy("source").agg(F.count("*").alias("vertices"), F.sum("vertex").alias("total")))
query("degree_page", f"WITH {oracle.arcs('supply')} SELECT src AS vertex, count(*) AS degree FROM arcs GROUP BY src ORDER BY degree, vertex OFFSET 20 LIMIT 10")(
    lambda s, d: rel.page_of(prep.degrees(graph(s, d, "supply").arcs), ["degree", "vertex"], 20, 10))
query("id_range", "SELECT count(*) AS n, sum(vertex)::BIGINT AS total FROM range(100000) t(vertex)")(lambda s, d: number_range(s, 100_000).agg(F.count("*").alias("n"), F.sum("vertex").alias("total")))


@query("feistel_udf", f"WITH {oracle.arcs('basket')} SELECT count(DISTINCT src) AS vertices, count(DISTINCT src) AS labels FROM arcs")
def _feistel_udf(s: SparkSession, d: str) -> DataFrame:
    code = functions.feistel_id(24, 5)
    return prep.vertices(graph(s, d, "basket").arcs).select("vertex", code("vertex").alias("label")).where("label >= 0 and label < 281474976710656").agg(F.count("*").alias("vertices"), F.countDistinct("label").alias("labels"))


@query("path_udtf", f"WITH RECURSIVE {oracle.with_levels('basket', 0)}, path AS (SELECT vertex, dist, parent FROM lv WHERE vertex = 16 UNION SELECT l.vertex, l.dist, l.parent FROM path p JOIN lv l ON l.vertex = p.parent) SELECT 1::BIGINT AS tree, dist AS step, vertex FROM path")
def _path_udtf(s: SparkSession, d: str) -> DataFrame:
    functions.register(s)
    rows.bfs_rows(graph(s, d, "basket"), 0).levels.selectExpr("1L AS tree", "vertex", "parent", "16L AS target").createOrReplaceTempView("levelwave_trees")
    return s.sql("SELECT * FROM unfold_path(TABLE(SELECT * FROM levelwave_trees) PARTITION BY tree)")
