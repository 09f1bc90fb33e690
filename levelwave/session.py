"""Settings that hold for a while, shared scratch space, and stored frames."""

from __future__ import annotations

import os
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


_ROOT = str(Path(__file__).resolve().parents[1])
_shipped: set[str] = set()


def importable(spark: SparkSession) -> None:
    """Ships this package to the Python workers, once a session, if they would not find it by themselves."""
    app = spark.sparkContext.applicationId
    found = [os.path.abspath(p or ".") for p in os.environ.get("PYTHONPATH", "").split(":") if p] + [os.getcwd()]
    if app not in _shipped and _ROOT not in found:
        place = tempfile.mkdtemp()
        spark.sparkContext.addPyFile(shutil.make_archive(f"{place}/levelwave", "zip", _ROOT, "levelwave"))
    _shipped.add(app)


@contextmanager
def settings(spark: SparkSession, **values: object) -> Iterator[None]:
    """Run-time settings, put back afterwards; names have __ for a dot."""
    before = {}
    for name, value in values.items():
        key = name.replace("__", ".")
        before[key] = spark.conf.get(key, None)
        spark.conf.set(key, str(value).lower() if isinstance(value, bool) else str(value))
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def aligned(spark: SparkSession, partitions: int):
    """What a level loop needs: exchanges of exactly so many partitions, which joins and sums then share.

    Adaptive execution forgets how a checkpoint is partitioned, so it is off in the loop and only there.
    """
    return settings(spark, spark__sql__adaptive__enabled=False, spark__sql__shuffle__partitions=partitions,
                    spark__sql__requireAllClusterKeysForCoPartition=False)


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share, spark.checkpoint.dir. Only a local session may do without that setting."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = os.path.join(tempfile.gettempdir(), "levelwave-checkpoints")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def kept(df: DataFrame) -> DataFrame:
    """df as a reliable checkpoint: its lineage is cut, its partitioning known, and lost executors do not matter."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def size(df: DataFrame) -> int:
    """Rows of a kept frame, counted where they lie: no plan, no exchange."""
    return df._jdf.queryExecution().toRdd().count()


def stored(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder."""
    path = f"{shared_folder(df.sparkSession)}/levelwave/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
