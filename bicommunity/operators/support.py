"""Butterflies on each edge: exact, as a bound, and maintained."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import written
from . import dense
from .bounds import edge_bounds
from .motifs import item_wedges, wedges


def from_pairs(w: DataFrame, pairs: DataFrame) -> DataFrame:
    """``u, v, sup`` over wedges and the pairs counted: an edge gets, for each counted pair that
    shares its item, the pair's other shared items."""
    met = w.select("ui", "uj", "v").join(pairs.select("ui", "uj", (F.col("n") - 1).alias("b")), ["ui", "uj"])
    return met.select(F.explode(F.array("ui", "uj")).alias("u"), "v", "b").groupBy("u", "v").agg(F.sum("b").alias("sup"))


def exact(edges: DataFrame, side: str = "user", hub_degree: int | None = None) -> DataFrame:
    """``u, v, sup`` for every edge, through user pairs or item pairs.

    ``auto`` takes the side with fewer wedges (two sums of squared degrees), or products of matrices where a (written)
    graph is dense and its matrix fits.
    """
    if side == "auto":
        m = dense.worth(edges)
        if m is not None:
            return written(dense.supports(edges.sparkSession, m), "supports")

        def volume(key: str) -> int:
            return edges.groupBy(key).count().agg(F.coalesce(F.sum(F.col("count") * F.col("count")), F.lit(0))).first()[0]

        side = "user" if volume("v") <= volume("u") else "item"
    if side == "user":
        w = wedges(edges, hub_degree)
        got = from_pairs(w, w.groupBy("ui", "uj").agg(F.count("*").alias("n")))
    else:
        w = item_wedges(edges)
        n = w.groupBy("va", "vb").agg((F.count("*") - 1).alias("b"))
        got = w.join(n, ["va", "vb"]).select(F.explode(F.array("va", "vb")).alias("v"), "u", "b").groupBy("u", "v").agg(F.sum("b").alias("sup"))
    return edges.select("u", "v").join(got, ["u", "v"], "left").select("u", "v", F.coalesce("sup", F.lit(0).cast("bigint")).alias("sup"))


def upper_bound(edges: DataFrame) -> DataFrame:
    """``u, v, sup``: support in the whole (written) graph, which bounds it in every sub-graph; no wedge is shuffled."""
    return edge_bounds(edges).select("u", "v", "sup")


def maintain(old_edges: DataFrame, new_edges: DataFrame, changes: DataFrame, old_pairs: DataFrame, new_pairs: DataFrame, old_sup: DataFrame, hub_degree: int | None = None) -> DataFrame:
    """Supports after changed edges (u, v, w_old, w_new): only edges that come or go matter.

    A pair whose number of shared items changed shifts all edges on its shared items, and an item
    that gained or lost an edge shifts its own edges. Those edges are counted again from the
    new pairs; all others keep their support.
    """
    structural = changes.filter("(w_old = 0) <> (w_new = 0)")
    a = old_pairs.select("ui", "uj", F.col("n").alias("no"))
    b = new_pairs.select("ui", "uj", F.col("n").alias("nn"))
    moved = a.join(b, ["ui", "uj"], "full").filter("coalesce(no, 0) <> coalesce(nn, 0)").select("ui", "uj")
    users = moved.select(F.explode(F.array("ui", "uj")).alias("u")).distinct()
    near = new_edges.join(users, "u", "left_semi")
    shared = moved.join(near.select(F.col("u").alias("ui"), "v"), "ui").join(near.select(F.col("u").alias("uj"), "v"), ["uj", "v"])
    touched = shared.select(F.explode(F.array("ui", "uj")).alias("u"), "v")
    touched = touched.unionByName(new_edges.join(structural.select("v").distinct(), "v", "left_semi").select("u", "v")).distinct()
    items = new_edges.join(touched.select("v").distinct(), "v", "left_semi")
    again = from_pairs(wedges(items, hub_degree), new_pairs).join(touched, ["u", "v"], "left_semi")
    fresh = touched.join(again, ["u", "v"], "left").select("u", "v", F.coalesce("sup", F.lit(0).cast("bigint")).alias("sup"))
    kept = old_sup.join(touched, ["u", "v"], "left_anti").join(new_edges.select("u", "v"), ["u", "v"], "left_semi")
    return kept.select("u", "v", "sup").unionByName(fresh)
