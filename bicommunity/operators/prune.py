"""Pruning rules on items, edges, communities and users."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def keyword(edges: DataFrame, item_kw: DataFrame, keywords: Sequence[str]) -> DataFrame:
    """Edges on items that have a keyword of the query (no keywords: all edges)."""
    if not keywords:
        return edges
    return edges.join(item_kw.filter(F.col("kw").isin(*keywords)).select("v").distinct(), "v", "left_semi").select("u", "v", "w")


def support(edges: DataFrame, bounds: DataFrame, k: int) -> DataFrame:
    """Edges whose support bound reaches ``k``. Bounds that hold the weights (``bounds.edge_bounds``) need no join."""
    if "w" in bounds.columns:
        return bounds.filter(F.col("sup") >= k).select("u", "v", "w")
    return edges.join(bounds.filter(F.col("sup") >= k).select("u", "v"), ["u", "v"], "left_semi")


def layer_size(candidates: DataFrame, k: int) -> DataFrame:
    """Centres whose candidate (center, u, v) is large enough: with a users and b items an edge is
    in at most (a - 1)(b - 1) butterflies."""
    return large_layers(candidates.groupBy("center").agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items")), k)


def large_layers(sizes: DataFrame, k: int) -> DataFrame:
    """The same from sizes (center, users, items) that are known."""
    return sizes.select("center", "users", "items").filter((F.col("users") - 1) * (F.col("items") - 1) >= k)


def radius(hop: DataFrame, r: int) -> DataFrame:
    """Users within ``2 r`` graph hops of their centre."""
    return hop.filter(F.col("dist") <= 2 * r)


def score(pairs: DataFrame, sigma: int, policy: str = "pairs", centers: DataFrame | None = None) -> DataFrame:
    """Weak pairs, and what follows from them.

    ``pairs``: pairs whose score bound reaches sigma (the compatible pairs of the core).
    ``hop``: users with at least one such pair, the only ones that can be in a community.
    ``literal``: users without a weak partner. The condition holds for both ends of a weak pair, so
    this also drops users of valid communities; it is here for comparison only.
    """
    if policy == "pairs":
        return pairs.filter(F.col("score") >= sigma)
    ends = F.explode(F.array("ui", "uj")).alias("u")
    if policy == "hop":
        return pairs.filter(F.col("score") >= sigma).select(ends).distinct()
    if policy != "literal":
        raise ValueError(policy)
    return pairs.select(ends).distinct().join(pairs.filter(F.col("score") < sigma).select(ends), "u", "left_anti")
