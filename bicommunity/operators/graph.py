"""Weighted two-layer graphs and their maintenance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def build_edges(inter: DataFrame, u: str = "u", v: str = "v", weight: str = "count") -> DataFrame:
    """Interactions -> edges. ``weight``: ``count``, or a column whose whole part is summed.
    Rows without a user or an item are no interactions."""
    w = F.count("*") if weight == "count" else F.sum(F.col(weight).cast("bigint"))
    usable = inter.filter(F.col(u).isNotNull() & F.col(v).isNotNull())
    return usable.groupBy(F.col(u).cast("bigint").alias("u"), F.col(v).cast("string").alias("v")).agg(w.alias("w")).filter("w > 0")


def turned(rows: DataFrame) -> DataFrame:
    """Rows of edges (u, v, ...) with users and items changed over."""
    return rows.select(F.col("v").alias("u"), F.col("u").alias("v"), *[c for c in rows.columns if c not in ("u", "v")])


def layers(edges: DataFrame) -> DataFrame:
    """One row: users, items, edges, total weight."""
    return edges.agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items"), F.count("*").alias("edges"), F.coalesce(F.sum("w"), F.lit(0)).alias("weight"))


def degrees(edges: DataFrame, side: str) -> DataFrame:
    """Degree and weight of each vertex of a side (``user`` or ``item``)."""
    key = {"user": "u", "item": "v"}[side]
    return edges.groupBy(key).agg(F.count("*").alias("degree"), F.sum("w").alias("weight"))


def vertices(inter: DataFrame) -> DataFrame:
    """``side, id``: vertices stay when their last edge goes."""
    users = inter.select(F.lit("user").alias("side"), F.col("u").cast("string").alias("id"))
    return users.unionByName(inter.select(F.lit("item").alias("side"), F.col("v").alias("id"))).distinct()


def net_changes(inserted: DataFrame, expired: DataFrame) -> DataFrame:
    """``u, v, dw`` of unit insertions and expiries; zeros left out."""
    signed = inserted.select("u", "v", F.lit(1).cast("bigint").alias("d")).unionByName(expired.select("u", "v", F.lit(-1).cast("bigint").alias("d")))
    return signed.groupBy("u", "v").agg(F.sum("d").alias("dw")).filter("dw <> 0")


def apply_changes(edges: DataFrame, changes: DataFrame) -> DataFrame:
    """Edges after net changes: new ends make vertices, weight 0 ends an edge."""
    both = edges.join(changes, ["u", "v"], "full").select("u", "v", (F.coalesce("w", F.lit(0)) + F.coalesce("dw", F.lit(0))).alias("w"))
    return both.filter("w > 0")


def apply_updates(edges: DataFrame, inserted: DataFrame, expired: DataFrame) -> DataFrame:
    return apply_changes(edges, net_changes(inserted, expired))


def changed_weights(edges: DataFrame, changes: DataFrame) -> DataFrame:
    """``u, v, w_old, w_new`` of the changed edges (0 where there is no edge)."""
    old = edges.join(changes.select("u", "v"), ["u", "v"], "left_semi").withColumnRenamed("w", "w_old")
    return changes.join(old, ["u", "v"], "left").select("u", "v", F.coalesce("w_old", F.lit(0)).cast("bigint").alias("w_old"), F.greatest(F.coalesce("w_old", F.lit(0)) + F.col("dw"), F.lit(0)).cast("bigint").alias("w_new"))


def snapshot(base: DataFrame, updates: DataFrame, s: int, at: int) -> DataFrame:
    """Edges of the base and of the last ``s`` updates up to arrival ``at``."""
    from .window import slice_window

    live = slice_window(updates, at, s).select("u", "v", F.lit(1).cast("bigint").alias("w"))
    return base.select("u", "v", "w").unionByName(live).groupBy("u", "v").agg(F.sum("w").alias("w")).filter("w > 0")
