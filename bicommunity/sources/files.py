"""Edge files in and out, partitioned and bucketed tables, file streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..model import EDGES


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", schema: str = EDGES) -> DataFrame:
    """Edges (or other rows) from parquet, csv, json or orc, with a declared schema."""
    options = {"header": "true"} if kind == "csv" else {}
    return spark.read.schema(schema).options(**options).format(kind).load(path)


def write_rows(df: DataFrame, path: str, kind: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(kind)
    if kind == "csv":
        writer = writer.option("header", "true")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int, sort: str | None = None) -> None:
    """A table whose joins and sums on ``key`` need no shuffle: edges by v for wedges, by u for
    hops, pairs by ui."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(sort or key).saveAsTable(name)


def stream_rows(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1, kind: str = "parquet") -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).format(kind).load(path)
