"""Cutting lineage in the folder that all executors share."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where the session names none."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="bicommunity-")
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def written(df: DataFrame, name: str = "cut") -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that are done with: its cleaner goes by what the driver has collected."""
    gc.collect()
    spark._jvm.System.gc()


class Rounds:
    """Tables of an iteration: each round's replaces that of two rounds before.

    A round that fails to settle raises; nothing is cut short silently.
    """

    def __init__(self, spark: SparkSession, name: str, most: int = 500):
        self.spark, self.most, self.n = spark, most, 0
        self.base = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"

    def keep(self, df: DataFrame) -> DataFrame:
        if self.n > self.most:
            raise RuntimeError(f"{self.base.rsplit('/', 1)[-1]} did not settle in {self.most} rounds")
        path = f"{self.base}/{self.n}"
        df.write.parquet(path)
        if self.n >= 2:
            remove(self.spark, f"{self.base}/{self.n - 2}")
        self.n += 1
        return self.spark.read.schema(df.schema).parquet(path)
