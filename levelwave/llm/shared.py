"""Things that every document operator needs: the table, scratch space that all executors see, size-checked joins."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Columns of the documents table, in order.
DOCUMENT_COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Rows of a set of ids that may be broadcast: 8 bytes each, so 8 MB before hashing. Larger sets are shuffled.
BROADCAST_IDS = 1_000_000

_ROOT = str(Path(__file__).resolve().parents[2])
_ready: set[str] = set()


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


_made: list[list[str]] = []


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh folder in the place that all executors share, spark.checkpoint.dir. Only a local session may do without that
    setting: on a cluster a folder of one machine would lose what others write."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = os.path.join(tempfile.gettempdir(), "levelwave-scratch")
        spark.sparkContext.setCheckpointDir(base)
    path = f"{base.rstrip('/')}/levelwave/{name}-{uuid.uuid4().hex}"
    for folders in _made[-1:]:
        folders.append(path)
    return path


def _folder(spark: SparkSession, path: str) -> tuple[object, object]:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def exists(spark: SparkSession, path: str) -> bool:
    files, at = _folder(spark, path)
    return files.exists(at)


def removed(spark: SparkSession, path: str) -> None:
    """Deletes a folder, if it is there."""
    files, at = _folder(spark, path)
    files.delete(at, True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Writes df as Parquet in shared scratch space and reads it again: cuts lineage and outlives lost executors."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settled(spark: SparkSession, make: Callable[[], DataFrame], name: str) -> tuple[DataFrame, str]:
    """What make() gives, stored, and its folder. All other scratch folders that it made on the way are removed."""
    path = scratch(spark, name)
    _made.append([])
    try:
        df = make()
        df.write.parquet(path)
    finally:
        for folder in _made.pop():
            removed(spark, folder)
    return spark.read.schema(df.schema).parquet(path), path


def importable(spark: SparkSession) -> None:
    """Ships this package to the Python workers if they would not find it by themselves."""
    app = spark.sparkContext.applicationId
    if app in _ready:
        return
    found = [os.path.abspath(p or ".") for p in os.environ.get("PYTHONPATH", "").split(":") if p] + [os.getcwd()]
    if _ROOT not in found:
        import shutil

        place = tempfile.mkdtemp()
        spark.sparkContext.addPyFile(shutil.make_archive(f"{place}/levelwave", "zip", _ROOT, "levelwave"))
    _ready.add(app)


def crc_bucket(key: Column, modulus: int) -> Column:
    """crc32 of the key written as text, modulo a number; null keys fall in bucket 0."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % modulus, F.lit(0))


def whole_text(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def checked(ids: DataFrame, limit: int = BROADCAST_IDS) -> DataFrame:
    """ids, marked for broadcast if there are few of them; else left to a shuffled join."""
    return F.broadcast(ids) if ids.count() <= limit else ids


def row_mark() -> Column:
    """Tells rows of one id apart: a hash of the text that judges them, with language and source."""
    return F.xxhash64("text", "lang", "source")


def without_rows(docs: DataFrame, rejected: DataFrame, mark: Column) -> DataFrame:
    """docs less the rows whose doc_id (maybe null) and mark are in rejected (doc_id, mark), a stored table."""
    marked = docs.withColumn("_mark", mark)
    gone = checked(rejected.select(F.col("doc_id").alias("_gone"), F.col("mark").alias("_gone_mark")))
    return marked.join(gone, marked["doc_id"].eqNullSafe(F.col("_gone")) & (F.col("_mark") == F.col("_gone_mark")), "left_anti").select(docs.columns)
