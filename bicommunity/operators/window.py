"""Arrival ranks, count windows and time windows over interactions."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ORDER = ("ts", "seq", "u", "v")


def rank_updates(inter: DataFrame, order: Sequence[str] = ORDER, how: str = "scalable") -> DataFrame:
    """``t, ts, u, v``: arrival position from 1.

    ``scalable`` sorts by range, numbers each partition and moves it up by the sizes of the
    partitions before, a table of one row a partition. ``global`` is one window over all rows.
    """
    if how == "global":
        return inter.withColumn("t", F.row_number().over(Window.orderBy(*order)).cast("bigint")).select("t", "ts", "u", "v")
    from ..store import written

    ranged = inter.repartitionByRange(*[F.col(c) for c in order]).withColumn("part", F.spark_partition_id())
    own = written(ranged.withColumn("own", F.row_number().over(Window.partitionBy("part").orderBy(*order))), "ranked")
    sizes = own.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    return own.join(F.broadcast(before), "part").select((F.col("own") + F.col("before")).cast("bigint").alias("t"), "ts", "u", "v")


def slice_window(updates: DataFrame, at: int, s: int) -> DataFrame:
    """The last ``s`` updates up to arrival ``at``."""
    return updates.filter(F.col("t").between(at - s + 1, at))


def latest(inter: DataFrame, s: int, order: Sequence[str] = ORDER) -> DataFrame:
    """The last ``s`` interactions without ranking all: a distributed top-s."""
    return inter.orderBy(*[F.col(c).desc() for c in order]).limit(s)


def deltas(updates: DataFrame, s: int) -> DataFrame:
    """``t, u_in, v_in, u_out, v_out``: what enters and leaves at each arrival (an equi-join on the
    shifted rank, so no window over all rows)."""
    new = updates.select("t", F.col("u").alias("u_in"), F.col("v").alias("v_in"))
    old = updates.select((F.col("t") + s).alias("t"), F.col("u").alias("u_out"), F.col("v").alias("v_out"))
    return new.join(old, "t", "left")


def weight_history(updates: DataFrame, s: int, base: DataFrame | None = None) -> DataFrame:
    """``t, u, v, w``: each edge's weight after every arrival that changes it."""
    last = updates.agg(F.max("t").alias("last"))
    plus = updates.select("t", "u", "v", F.lit(1).alias("d"))
    minus = updates.select((F.col("t") + s).alias("t"), "u", "v", F.lit(-1).alias("d")).join(F.broadcast(last), F.col("t") <= F.col("last")).drop("last")
    moves = plus.unionByName(minus)
    if base is not None:
        moves = moves.unionByName(base.select(F.lit(0).cast("bigint").alias("t"), "u", "v", F.col("w").cast("int").alias("d")))
    steps = moves.groupBy("t", "u", "v").agg(F.sum("d").alias("d")).filter("d <> 0")
    run = Window.partitionBy("u", "v").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return steps.select("t", "u", "v", F.sum("d").over(run).alias("w"))


def time_slice(inter: DataFrame, at: str, span: str) -> DataFrame:
    """Interactions of the ``span`` (an interval such as '5 minutes') up to ``at``."""
    end = F.lit(at).cast("timestamp_ntz")
    return inter.filter((F.col("ts") <= end) & (F.col("ts") > end - F.expr(f"interval {span}")))


def tumbling(inter: DataFrame, span: str) -> DataFrame:
    """Edges of each tumbling window."""
    return sliding(inter, span, span)


def sliding(inter: DataFrame, span: str, step: str) -> DataFrame:
    """``start, stop, u, v, w`` of each sliding window."""
    grouped = inter.groupBy(F.window("ts", span, step).alias("win"), "u", "v").agg(F.count("*").alias("w"))
    return grouped.select(F.col("win.start").alias("start"), F.col("win.end").alias("stop"), "u", "v", "w")


def sessions(inter: DataFrame, gap: str) -> DataFrame:
    """``start, stop, u, n``: each user's runs of interactions with no longer pause."""
    grouped = inter.groupBy(F.session_window("ts", gap).alias("win"), "u").agg(F.count("*").alias("n"))
    return grouped.select(F.col("win.start").alias("start"), F.col("win.end").alias("stop"), "u", "n")
