"""Connected components by alternating star contraction, as DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import remove, shared_dir
import uuid


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(a, b)`` -> ``(node, root)``: for each node that has an edge, the
    smallest node reachable. Self loops and repeats are allowed.

    Each round points every neighbour at the smallest one (larger neighbours
    first, then smaller ones); the number of rounds is logarithmic in practice. Only
    a round's count and checksum reach the driver. Hot nodes: minima are
    pre-aggregated, and the join of edges with minima has one row per node on
    one side, so that adaptive execution can split the other side.
    """
    spark = edges.sparkSession
    base = f"{shared_dir(spark)}/components-{uuid.uuid4().hex}"
    paths: list[str] = []

    def keep(df: DataFrame) -> DataFrame:
        paths.append(f"{base}/{len(paths)}")
        df.write.parquet(paths[-1])
        return spark.read.schema("u long, v long").parquet(paths[-1])

    def state(df: DataFrame) -> tuple[int, int]:
        row = df.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0)).alias("h")).first()
        return row.n, row.h

    ordered = edges.select(F.greatest("a", "b").cast("long").alias("u"), F.least("a", "b").cast("long").alias("v"))
    now = keep(ordered.filter("u <> v").distinct())
    before = state(now)
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        pointed = large.join(low, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = pointed.unionByName(low.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()
        now = keep(small)
        after = state(now)
        if after == before:
            break
        before = after
        if len(paths) > 2:
            remove(spark, paths[-3])
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
