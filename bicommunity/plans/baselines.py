"""What the engine is compared with."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import community, graph, prune, truss
from ..store import written
from . import snapshot


def trussness_index(edges: DataFrame, engine: str = "auto") -> DataFrame:
    """``u, v, w, number`` with each edge's bitruss number: the decomposition a per-tick rebuild needs."""
    return written(edges.join(truss.bitruss_numbers(edges, engine), ["u", "v"]).select("u", "v", "w", "number"), "trussness")


def trussness_query(index: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig()) -> DataFrame:
    """Communities through the index: users all of whose edges are below ``k`` go, then
    each user left with a query keyword is tried as a centre on what remains."""
    strong = index.filter(F.col("number") >= q.k).select("u").distinct()
    left = prune.keyword(index.join(strong, "u", "left_semi").select("u", "v", "w"), item_kw, q.keywords)
    return written(community.extract(written(left, "left"), q, None, config.engine, config.drop, config.items), "communities")


def exhaustive_snapshot(edges: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig()) -> DataFrame:
    """Every user of the filtered graph is tried, with no pruning of candidates."""
    return snapshot.run(edges, item_kw, q, replace(config, candidates="all"))


def recompute_stream(base: DataFrame, updates: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig(), until: int | None = None, by: str = "snapshot") -> list[tuple[int, DataFrame]]:
    """A new snapshot (or trussness index and query) at the end of every tick."""
    last = updates.agg(F.max("t")).first()[0] or 0
    last, out, at = last if until is None else min(last, until), [], 0
    while at < last:
        at = min(at + config.tick, last)
        now = written(graph.snapshot(base, updates, config.window, at), "edges")
        out.append((at, trussness_query(trussness_index(now), item_kw, q, config) if by == "trussness" else snapshot.run(now, item_kw, q, config)))
    return out


def bicliques(edges: DataFrame, min_users: int = 3, min_items: int = 4, max_users: int | None = None) -> DataFrame:
    """``users, items``: maximal complete blocks of ``min_users`` users or more (at most ``max_users``, if
    given) that share at least ``min_items`` items.

    Sets of users grow by one user at a time through pairs that share enough items; a set
    stays if no larger set has the same items. Without ``max_users`` they grow until none is left.
    """
    own = edges.groupBy("u").agg(F.array_sort(F.collect_set("v")).alias("vs"))
    own = written(own.filter(F.size("vs") >= min_items), "items-by-user")
    strong = edges.join(own.select("u"), "u", "left_semi")
    a = strong.select("v", F.col("u").alias("ui"))
    b = strong.select("v", F.col("u").alias("uj"))
    pairs = written(a.join(b, "v").filter("ui < uj").groupBy("ui", "uj").agg(F.array_sort(F.collect_set("v")).alias("vs")).filter(F.size("vs") >= min_items), "strong-pairs")
    level = pairs.select(F.array("ui", "uj").alias("users"), "vs")
    found = level
    size = 2
    while (max_users is None or size <= max_users) and level.limit(1).count():
        size += 1
        grown = level.join(pairs.select(F.col("ui").alias("last"), F.col("uj").alias("next"), F.col("vs").alias("more")), F.element_at("users", -1) == F.col("last"))
        level = grown.select(F.concat("users", F.array("next")).alias("users"), F.array_intersect("vs", "more").alias("vs")).filter(F.size("vs") >= min_items)
        level = written(level.select("users", F.array_sort("vs").alias("vs")), "bicliques")
        found = found.unionByName(level)
    within = found.select(F.size("users").alias("n"), "users", "vs")
    # a set is maximal if its items' common users are just its users: a larger set with the same items shows it isn't
    larger = within.select((F.col("n") - 1).alias("n"), F.col("vs"), F.col("users").alias("bigger"))
    covered = within.join(larger, ["n", "vs"]).filter(F.size(F.array_except("users", "bigger")) == 0).select("users").distinct()
    maximal = within.join(covered, "users", "left_anti").filter((F.col("n") >= min_users) & (F.col("n") <= (F.col("n") if max_users is None else max_users)))
    return maximal.select("users", F.col("vs").alias("items"))
