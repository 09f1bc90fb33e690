"""Exact de-duplication through a persistent digest index, bucketed and sorted by digest (DataFrame operations only).

New rows are digested and grouped in their own batch, anti-joined by sort-merge with the index, and the digests that are
new are appended. Only digests and ids are shuffled, never texts. Copies of one text meet as one pre-aggregated row for
each task; the rows of a hot digest are dealt over as many keys as it has shares of rows.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import documents, exists, removed, scratch, stored

QUERY = "op10_exact_dedup"
#: A digest is hot from this share of a batch's rows on (and HOT_ROWS rows), so at most HOT_MOST are, at 80 bytes each.
HOT_MOST, HOT_ROWS = 100_000, 256
ENTRIES = "text_sha256 string, keep_id long, first_batch string"


def digest(text: Column) -> Column:
    """Lowercase hex SHA-256 of the text after each run of ASCII white space became one space; null is the empty text."""
    return F.sha2(F.encode(F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " "), "UTF-8"), 256)


class DigestIndex:
    """A table (text_sha256, keep_id, first_batch) of every text seen, in buckets sorted by text_sha256.

    All of it is in path, so any session that sees the folder can open it again; the number of buckets is kept there too.
    A lost executor only repeats its own tasks. buckets should follow the size of the index: about 128 MB of 100-byte rows a
    bucket, so 64 for 8 GB and 65,536 for 8 TB of digests. One writer at a time.
    """

    def __init__(self, spark: SparkSession, path: str | None = None, buckets: int = 16):
        self.spark, self.path = spark, path or scratch(spark, "digest-index")
        self.name = f"levelwave_digests_{hashlib.md5(self.path.encode()).hexdigest()}"
        if exists(spark, f"{self.path}/layout"):
            buckets = spark.read.parquet(f"{self.path}/layout").first()["buckets"]
        else:
            spark.createDataFrame([(buckets,)], "buckets int").coalesce(1).write.parquet(f"{self.path}/layout")
        self.buckets = buckets
        if not spark.catalog.tableExists(self.name):
            spark.sql(f"CREATE TABLE {self.name} ({ENTRIES}) USING parquet CLUSTERED BY (text_sha256) SORTED BY (text_sha256) INTO {buckets} BUCKETS LOCATION '{self.path}/digests'")

    def table(self) -> DataFrame:
        self.spark.catalog.refreshTable(self.name)  # another session may have appended
        return self.spark.table(self.name)

    def append(self, fresh: DataFrame) -> None:
        (fresh.repartition(self.buckets, "text_sha256").write.mode("append").format("parquet")
         .bucketBy(self.buckets, "text_sha256").sortBy("text_sha256").saveAsTable(self.name))

    def drop(self) -> None:
        """Takes the table out of the catalog and removes its files."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        removed(self.spark, self.path)

    def ingest(self, docs: DataFrame) -> DataFrame:
        """Adds a batch and says, for each of its rows, which row stays.

        Adds to docs' columns keep_id, group_size (rows of this batch with the text), kept and text_sha256; columns of
        those names are replaced. A null text is the empty text. Of equal texts the smallest doc_id stays (null ids come
        last), and of rows that also share the id exactly one; a text that an earlier batch brought stays there. A batch
        is known by its ids and digests, so one that is given again, after a failure or by another session, gets the
        same answer and adds nothing. An empty batch gives no rows.
        """
        names = [c for c in docs.columns if c not in ("keep_id", "group_size", "kept", "text_sha256")]
        rows = docs.select(*names, digest(F.col("text")).alias("text_sha256"))
        if "text" in names:
            rows = rows.drop("text")
        rows = stored(rows.withColumn("_row", F.monotonically_increasing_id()), "digests")
        rank = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("_row").alias("row"))
        batch = rows.groupBy("text_sha256").agg(F.min(rank).alias("k"), F.count("*").alias("group_size"))
        batch = stored(batch.select("text_sha256", F.col("k.id").alias("keep_id"), F.col("k.row").alias("keep_row"), "group_size"), "digest-batch")
        mark = F.xxhash64("text_sha256", "keep_id", "group_size").cast("decimal(38,0)")
        total, marks = batch.agg(F.coalesce(F.sum("group_size"), F.lit(0)), F.sum(mark)).first()
        number = f"{total}:{marks}"
        known = self.table().select("text_sha256").hint("merge")
        self.append(batch.select("text_sha256", "keep_id", F.lit(number).alias("first_batch")).join(known, "text_sha256", "left_anti"))
        # One row for each text first: the rows then need one join only.
        places = self.table().join(batch.select("text_sha256", "keep_row", "group_size"), "text_sha256")
        joined = _met(rows, stored(places, "index-places"), max(HOT_ROWS, total // HOT_MOST))
        kept = (F.col("first_batch") == number) & (F.col("keep_row") == F.col("_row"))
        return joined.select(*[c for c in names if c != "text"], "keep_id", "group_size", kept.alias("kept"), "text_sha256", "_row")


def _met(rows: DataFrame, places: DataFrame, share: int) -> DataFrame:
    """rows with the one row of places for their text. A text of over share rows is dealt over several keys, so that no task
    gets more than its share of one text; there can't be more than all rows over share of such texts."""
    hot = places.where(F.col("group_size") > share).select("text_sha256", F.ceil(F.col("group_size") / share).cast("int").alias("_keys"))
    keys = F.coalesce(F.when(F.col("group_size") > share, F.ceil(F.col("group_size") / share)), F.lit(1)).cast("int")
    dealt = places.select("*", F.explode(F.sequence(F.lit(0), keys - 1)).alias("_key"))
    placed = rows.join(F.broadcast(hot), "text_sha256", "left").withColumn("_key", F.coalesce(F.pmod(F.hash("_row"), F.col("_keys")), F.lit(0)))
    return placed.join(dealt, ["text_sha256", "_key"])


def exact_dedup(docs: DataFrame, index: DigestIndex | None = None) -> DataFrame:
    """One row for each row of docs, dropped ones too: doc_id, keep_id, group_size, kept, text_sha256. See ingest()."""
    return _judged(docs, index).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def _judged(docs: DataFrame, index: DigestIndex | None) -> DataFrame:
    """By an index that is given, or by one for this batch alone, which is removed again."""
    own = index or DigestIndex(docs.sparkSession)
    out = own.ingest(docs.select("doc_id", "text"))
    if index is None:
        own.drop()  # the answer is stored apart
    return out


def drop_copies(docs: DataFrame, index: DigestIndex | None = None) -> DataFrame:
    """The rows of docs that stay, with their own columns and nothing else. Rows are told apart by id and digest, so docs
    may come in any order each time it is read; of rows that share both, any one stays."""
    names = docs.columns
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.coalesce("doc_id", F.lit(0)).alias("id"))
    judged = _judged(docs, index).groupBy(key.alias("_id"), F.col("text_sha256").alias("_sha"))
    judged = stored(judged.agg(F.max("kept").alias("stays"), F.count("*").alias("n")), "judged")
    gone = judged.where("not stays").select("_id", "_sha")
    out = docs.withColumns({"_id": key, "_sha": digest(F.col("text"))}).join(_small(gone), ["_id", "_sha"], "left_anti")
    repeated = judged.where("stays and n > 1").select("_id", "_sha")
    if not repeated.isEmpty():
        # Only these rows are dealt out, each key's copies combined before they are.
        once = out.join(_small(repeated), ["_id", "_sha"], "left_semi").dropDuplicates(["_id", "_sha"])
        out = out.join(_small(repeated), ["_id", "_sha"], "left_anti").unionByName(once)
    return out.select(names)


def _small(keys: DataFrame, most: int = 500_000) -> DataFrame:
    """Broadcast behind a count (80 bytes each); else a shuffled join."""
    return F.broadcast(keys) if keys.count() <= most else keys


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(documents(spark, sf_dir))


SQL = r"""
WITH d AS (
  SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
