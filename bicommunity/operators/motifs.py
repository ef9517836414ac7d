"""Wedges, user pairs and butterflies."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import dense


def wedges(edges: DataFrame, hub_degree: int | None = None) -> DataFrame:
    """``ui, uj, v, wm`` (ui < uj): user pairs by shared item, with the lesser weight.

    With ``hub_degree``, an item of more users is spread over a grid: its users fall by hash into
    blocks of about that size, and each two blocks meet in a cell of their own. Every
    pair meets once, and no task holds all pairs of a hub.
    """
    if hub_degree is None:
        a = edges.select("v", F.col("u").alias("ui"), F.col("w").alias("wi"))
        b = edges.select("v", F.col("u").alias("uj"), F.col("w").alias("wj"))
        return a.join(b, (a["v"] == b["v"]) & (F.col("ui") < F.col("uj"))).select("ui", "uj", a["v"], F.least("wi", "wj").alias("wm"))
    blocks = edges.groupBy("v").agg(F.ceil(F.count("*") / hub_degree).cast("int").alias("blocks"))
    placed = edges.join(blocks, "v").withColumn("block", F.expr("pmod(xxhash64(u), blocks)").cast("int"))
    low = placed.select("v", F.col("u").alias("ua"), F.col("w").alias("wa"), F.col("block").alias("row"), F.explode(F.sequence(F.col("block"), F.col("blocks") - 1)).alias("col"))
    high = placed.select(F.col("v").alias("v2"), F.col("u").alias("ub"), F.col("w").alias("wb"), F.col("block").alias("col2"), F.explode(F.sequence(F.lit(0), F.col("block"))).alias("row2"))
    met = low.join(high, (F.col("v") == F.col("v2")) & (F.col("row") == F.col("row2")) & (F.col("col") == F.col("col2")) & ((F.col("row") < F.col("col")) | (F.col("ua") < F.col("ub"))))
    return met.select(F.least("ua", "ub").alias("ui"), F.greatest("ua", "ub").alias("uj"), "v", F.least("wa", "wb").alias("wm"))


def wedge_totals(edges: DataFrame) -> DataFrame:
    """``v, wedges, weight``: number and added weights of the wedges of each item that has one. A wedge has the lesser of its weights, so an item's edges
    by weight say it all: those of one weight meet each other and all heavier ones, and no wedge is listed."""
    heavier = Window.partitionBy("v").orderBy(F.desc("w")).rowsBetween(Window.unboundedPreceding, -1)
    by_weight = edges.groupBy("v", "w").agg(F.count("*").alias("c")).withColumn("above", F.coalesce(F.sum("c").over(heavier), F.lit(0)))
    met = by_weight.withColumn("n", F.expr("c * above + c * (c - 1) div 2"))
    return met.groupBy("v").agg(F.sum("n").alias("wedges"), F.sum(F.col("n") * F.col("w")).alias("weight")).filter("wedges > 0")


def item_wedges(edges: DataFrame) -> DataFrame:
    """``va, vb, u`` (va < vb): item pairs by shared user."""
    a = edges.select("u", F.col("v").alias("va"))
    b = edges.select("u", F.col("v").alias("vb"))
    return a.join(b, (a["u"] == b["u"]) & (F.col("va") < F.col("vb"))).select("va", "vb", a["u"])


def butterflies(edges: DataFrame) -> DataFrame:
    """``ui, uj, va, vb, score``: every 2x2 block. For checks on small graphs: the counts and scores
    that the engine needs come from user pairs."""
    w = wedges(edges)
    a = w.select("ui", "uj", F.col("v").alias("va"), F.col("wm").alias("wa"))
    b = w.select(F.col("ui").alias("i2"), F.col("uj").alias("j2"), F.col("v").alias("vb"), F.col("wm").alias("wb"))
    met = a.join(b, (a["ui"] == b["i2"]) & (a["uj"] == b["j2"]) & (F.col("va") < F.col("vb")))
    return met.select("ui", "uj", "va", "vb", (F.col("wa") * F.col("wb")).alias("score"))


def butterfly_pairs(edges: DataFrame) -> DataFrame:
    """``ui, uj, butterflies, score, first, last`` of a written graph: number and added scores of each user pair's butterflies, and their
    first and last item. Where the graph is dense and its matrix fits, the sums come from products of matrices; else every butterfly is listed."""
    m = dense.worth(edges)
    if dense.few_levels(m):
        rows = dense.pair_rows(edges.sparkSession, m, 2, ends=True)
        return rows.select("ui", "uj", F.expr("n * (n - 1) div 2").alias("butterflies"), F.expr("shiftright(x * x - y, 1)").alias("score"), "first", "last")
    return butterflies(edges).groupBy("ui", "uj").agg(F.count("*").alias("butterflies"), F.sum("score").alias("score"), F.min("va").alias("first"), F.max("vb").alias("last"))


def butterfly_counts(edges: DataFrame, by: str = "total", hub_degree: int | None = None) -> DataFrame:
    """Numbers of butterflies: ``total``, or by ``user``, ``item`` or ``edge``."""
    from .support import exact

    if by == "edge":
        return exact(edges, hub_degree=hub_degree).select("u", "v", F.col("sup").alias("butterflies"))
    if by == "item":
        # a butterfly puts two of its edges on each of its items
        return exact(edges, "auto", hub_degree).groupBy("v").agg(F.expr("sum(sup) div 2").alias("butterflies"))
    if by == "user":
        # and two on each of its users
        return exact(edges, "auto", hub_degree).groupBy("u").agg(F.expr("sum(sup) div 2").alias("butterflies"))
    pairs = wedges(edges, hub_degree).groupBy("ui", "uj").agg(F.count("*").alias("n")).select("ui", "uj", F.expr("n * (n - 1) div 2").alias("b"))
    return pairs.agg(F.coalesce(F.sum("b"), F.lit(0)).alias("butterflies"))
