"""Distances kept up to date under edges that arrive in a stream (insertions only), and windows over arrivals.

A new edge can only lower distances, so after a batch it is enough to relax from the ends of its edges until nothing
falls. State is a versioned table of levels and one of arcs in the shared folder, so a restarted driver goes on from the
last batch it finished; a batch that is run again gives the same tables.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def arrivals(events: DataFrame, late: str = "1 hour", size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by tumbling or sliding window; later ones than the watermark allows are dropped."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(window.alias("w")).agg(F.count("*").alias("events")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "events")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))


def once(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def user_type_arcs(events: DataFrame) -> DataFrame:
    """Both arcs between a user and the kind of an event (hashed into the user tag's neighbour 12)."""
    user, kind = F.col("user_id") * 16 + 9, F.pmod(F.xxhash64("event_type"), F.lit(1 << 40)) * 16 + 12
    return events.select(user.alias("src"), kind.alias("dst")).unionByName(events.select(kind.alias("src"), user.alias("dst"))).distinct()


def relax(arcs: DataFrame, levels: DataFrame, touched: DataFrame) -> DataFrame:
    """levels (vertex, dist, parent) after the arcs from touched vertices, and from all that fall, were followed."""
    from ..session import kept

    levels, frontier = kept(levels), touched
    while True:
        near = levels.join(frontier.select("vertex").distinct(), "vertex", "left_semi").select(F.col("vertex").alias("src"), "dist")
        found = arcs.join(near, "src").groupBy(F.col("dst").alias("vertex")).agg(F.min(F.struct((F.col("dist") + 1).alias("dist"), (-F.col("src")).alias("less"))).alias("best"))
        found = found.select("vertex", F.col("best.dist").alias("new"), (-F.col("best.less")).alias("by"))
        better = F.col("new").isNotNull() & (F.col("dist").isNull() | (F.col("new") < F.col("dist")) | ((F.col("new") == F.col("dist")) & (F.col("by") > F.col("parent"))))
        merged = kept(levels.join(found, "vertex", "full_outer").select("vertex", F.when(better, F.col("new")).otherwise(F.col("dist")).cast("int").alias("dist"), F.when(better, F.col("by")).otherwise(F.col("parent")).alias("parent"), (better & ~F.coalesce(F.col("new") == F.col("dist"), F.lit(False))).alias("fell")))
        levels, frontier = merged.select("vertex", "dist", "parent"), merged.where("fell")
        if frontier.isEmpty():
            return levels


class MaintainedLevels:
    """Levels from one source over all arcs seen so far."""

    def __init__(self, spark: SparkSession, source: int, folder: str):
        self.spark, self.source, self.folder = spark, source, folder
        self.version = self._last()

    def _last(self) -> int:
        """The last version whose levels are whole: a writer marks its folder when it is done. Read from the folder, so a
        restarted driver goes on from there."""
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/levels")
        files = at.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not files.exists(at):
            return -1
        done = [s.getPath() for s in files.listStatus(at)]
        mark = self.spark._jvm.org.apache.hadoop.fs.Path
        return max((int(p.getName()) for p in done if files.exists(mark(p, "_SUCCESS"))), default=-1)

    def _arcs(self, version: int) -> DataFrame | None:
        return None if version < 0 else self.spark.read.parquet(*[f"{self.folder}/arcs/{v}" for v in range(version + 1)])

    def levels(self) -> DataFrame:
        if self.version < 0:
            return self.spark.createDataFrame([(self.source, 0, self.source)], "vertex long, dist int, parent long")
        return self.spark.read.parquet(f"{self.folder}/levels/{self.version}")

    def add(self, batch: DataFrame, version: int) -> None:
        """batch (src, dst): arcs, both ways if undirected. A version that was added before is replaced."""
        self.version = version - 1
        before, levels = self._arcs(self.version), self.levels()
        fresh = batch.select("src", "dst").distinct()
        if before is not None:
            fresh = fresh.join(before, ["src", "dst"], "left_anti")
        fresh.write.mode("overwrite").parquet(f"{self.folder}/arcs/{version}")
        fresh = self.spark.read.schema("src long, dst long").parquet(f"{self.folder}/arcs/{version}")
        arcs = fresh if before is None else before.unionByName(fresh)
        out = relax(arcs, levels, fresh.select(F.col("src").alias("vertex")))
        out.write.mode("overwrite").parquet(f"{self.folder}/levels/{version}")
        self.version = version

    def start(self, arcs: DataFrame, checkpoint: str) -> StreamingQuery:
        """arcs: a streaming frame (src, dst)."""
        return arcs.writeStream.foreachBatch(lambda df, k: self.add(df, k)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def late_rows(query: StreamingQuery) -> int:
    """Rows that came later than the watermark allows and were dropped, over the batches that the query still remembers."""
    return sum(state.numRowsDroppedByWatermark for progress in query.recentProgress for state in progress.stateOperators)


def near_source(events: DataFrame, levels: DataFrame) -> DataFrame:
    """Streaming (or batch) events with the distance of their user, by a join with a fixed table of levels; null if the user
    wasn't reached. levels is read once a batch and joined on the vertex."""
    known = levels.select(F.col("vertex").alias("_vertex"), "dist")
    return events.join(known, F.col("user_id") * 16 + 9 == F.col("_vertex"), "left").drop("_vertex")


class NearestOffer(StatefulProcessor):
    """Keeps the least distance offered to a vertex, with the greatest parent that offered it, up to a radius; says so when
    it changes. Offers are (vertex, dist, parent)."""

    def __init__(self, radius: int):
        self.radius = radius

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getValueState("best", "dist int, parent long")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        offers = pd.concat(rows)
        offers = offers[offers["dist"] <= self.radius]
        known = (int(self.best.get()[0]), int(self.best.get()[1])) if self.best.exists() else None
        made = [(int(d), int(p)) for d, p in zip(offers["dist"], offers["parent"], strict=True)] + ([known] if known else [])
        if not made:
            return
        best = min(made, key=lambda x: (x[0], -x[1]))
        if best != known:
            self.best.update(best)
            yield pd.DataFrame({"vertex": [key[0]], "dist": [best[0]], "parent": [best[1]]})

    def close(self) -> None:
        pass


def nearest_offers(offers: DataFrame, radius: int) -> DataFrame:
    """(vertex, dist, parent) whenever a vertex's best offer changes, in a stream keyed by vertex. Needs a state store with
    column families: spark.sql.streaming.stateStore.providerClass set to the RocksDB provider."""
    return offers.groupBy("vertex").transformWithStateInPandas(NearestOffer(radius), "vertex long, dist int, parent long", "Update", "None")


def latest_per_user(events: DataFrame) -> DataFrame:
    """Batch yardstick of the stream: each user's events in order."""
    return events.withColumn("rank", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
