"""Reading edges, a generator as a data source, and sinks for levels and adjacency."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

EDGE_SCHEMA = "src long, dst long"


def number_range(spark: SparkSession, n: int, partitions: int | None = None) -> DataFrame:
    """(vertex) 0..n-1, made where it is used."""
    return spark.range(0, n, 1, partitions).select(F.col("id").alias("vertex"))


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst") -> DataFrame:
    """(src, dst) of parquet, orc, csv (with a header), json, or text with two numbers a line and # comments."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where("trim(value) <> '' and not startswith(trim(value), '#')")
        return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    schema = f"`{src}` long, `{dst}` long"
    reader = spark.read.option("header", True) if fmt == "csv" else spark.read
    reader = reader.schema(schema) if fmt in ("csv", "json") else reader
    df = require_columns(reader.format(fmt).load(path), src, dst)
    return df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def write_levels(levels: DataFrame, path: str, fmt: str = "parquet", by_level: bool = True) -> None:
    writer = levels.write.mode("overwrite").format(fmt)
    (writer.partitionBy("dist") if by_level else writer).save(path)


def save_adjacency(arcs: DataFrame, table: str, buckets: int) -> None:
    """Arcs in buckets by source, sorted: joins on the source then need no exchange of the arcs."""
    arcs.repartition(buckets, "src").write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(table)


def write_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


class _Part(InputPartition):
    def __init__(self, first: int, end: int):
        self.first, self.end = first, end


class _RmatReader(DataSourceReader):
    def __init__(self, options: dict):
        self.scale, self.factor = int(options.get("scale", 8)), int(options.get("edgefactor", options.get("edgeFactor", 16)))
        self.parts, self.seed = int(options.get("partitions", 4)), int(options.get("seed", 0))

    def partitions(self) -> list[InputPartition]:
        m = self.factor << self.scale
        cuts = [m * k // self.parts for k in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def read(self, partition: _Part) -> Iterator:
        import numpy as np
        import pyarrow as pa

        from ..rmat import edges_of

        for at in range(partition.first, partition.end, 1 << 16):
            src, dst = edges_of(np.arange(at, min(at + (1 << 16), partition.end), dtype=np.int64), self.scale, seed=self.seed)
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], ["src", "dst"])


class RmatSource(DataSource):
    """spark.read.format("rmat").option("scale", 10).option("edgeFactor", 16).load()"""

    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return EDGE_SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return _RmatReader(self.options)


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(RmatSource)
