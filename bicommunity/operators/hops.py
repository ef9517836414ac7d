"""Users and sub-graphs within so many user-to-user steps of a centre."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import written
from . import dense


def all_users(edges: DataFrame, r: int) -> DataFrame:
    """``users`` for all centres of a written graph, by products of matrices where it is dense and its matrix fits: in a
    dense graph each user has very many ways to each other one."""
    m = dense.worth(edges)
    return users(edges, r) if m is None else dense.near_users(edges.sparkSession, m, r)


def sizes(edges: DataFrame, r: int, items: str = "inner") -> DataFrame:
    """``center, users, items, n, w``: users, items, edges and their weight of each centre's sub-graph in a written graph.

    No sub-graph is listed where a matrix fits; else the edges of ``subgraph`` are counted.
    """
    m = dense.worth(edges)
    if m is not None:
        return written(dense.near_sizes(edges.sparkSession, m, r, items == "closed"), "sizes")
    listed = subgraph(edges, r, items=items).groupBy("center")
    return listed.agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items"), F.count("*").alias("n"), F.sum("w").alias("w"))


def users(edges: DataFrame, r: int, centers: DataFrame | None = None) -> DataFrame:
    """``center, u, dist`` for users within ``2 r`` hops (dist counts graph hops: 0, 2, ...).

    ``centers``: a table with a column ``center``; all users by default. Each step goes from a frontier
    through its items, so user pairs are never listed as a whole.
    """
    at = (centers.select("center") if centers is not None else edges.select(F.col("u").alias("center"))).distinct()
    at = at.join(edges.select(F.col("u").alias("center")).distinct(), "center", "left_semi")
    found = at.select("center", F.col("center").alias("u"), F.lit(0).alias("dist"))
    frontier = found
    for step in range(1, r + 1):
        items = frontier.select("center", "u").join(edges.select("u", "v"), "u").select("center", "v").distinct()
        near = items.join(edges.select("u", "v"), "v").select("center", "u").distinct()
        frontier = near.join(found.select("center", "u"), ["center", "u"], "left_anti").select("center", "u", F.lit(2 * step).alias("dist"))
        found = found.unionByName(frontier)
    return found


def subgraph(edges: DataFrame, r: int, centers: DataFrame | None = None, items: str = "inner") -> DataFrame:
    """``center, u, v, w``: edges between the users within ``2 r`` hops and their items.

    ``inner`` takes items within ``2 r - 1`` hops, as a breadth-first search finds them;
    ``closed`` also takes items that only link users at the rim (two or more of them).
    """
    near = users(edges, r, centers)
    reach = near.join(edges, "u").select("center", "u", "v", "w", "dist")
    if items == "inner":
        good = reach.filter(F.col("dist") <= 2 * r - 2).select("center", "v").distinct()
    else:
        inside = reach.groupBy("center", "v").agg(F.min("dist").alias("d"), F.count("*").alias("n"))
        good = inside.filter((F.col("d") <= 2 * r - 2) | (F.col("n") > 1)).select("center", "v")
    return reach.join(good, ["center", "v"], "left_semi").select("center", "u", "v", "w")
