"""Measures: times, pruning, sizes, agreement, utility."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import mean

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import community, keywords, synopsis
from . import snapshot


def timed(fn: Callable[[], object], runs: int = 10) -> dict[str, float]:
    """Mean, least and greatest seconds of some runs."""
    took = []
    for _ in range(runs):
        t = time.perf_counter()
        fn()
        took.append(time.perf_counter() - t)
    return {"mean": mean(took), "min": min(took), "max": max(took)}


def speedup(base: dict[str, float], own: dict[str, float]) -> float:
    return base["mean"] / own["mean"]


def ablation(leaf: DataFrame, q: CommunityQuery, bits: int = 256) -> DataFrame:
    """One row: users, and how many of them each group of rules rules out as centres: support;
    support and score; support, score and keyword."""
    low_sup = F.col("ub_sup") < q.k
    low_score = F.col("ub_score") < q.sigma
    no_key = ~keywords.overlaps(F.col("bv"), keywords.query_vector(q.keywords, bits))
    return leaf.filter(F.col("r") == q.r).agg(F.count("*").alias("users"), F.count_if(low_sup).alias("by_support"), F.count_if(low_sup | low_score).alias("by_score"), F.count_if(low_sup | low_score | no_key).alias("by_keyword"))


def pruning_power(aux: snapshot.Auxiliary, q: CommunityQuery, bits: int = 256) -> DataFrame:
    """``level, entries, kept, power`` of a traversal; level -1 are users."""
    log: list = []
    synopsis.traverse(aux.leaves, aux.nodes, q, bits, log).count()
    rows = [(level, n, kept, 1 - kept / n if n else 0.0) for level, n, kept in log]
    return aux.leaves.sparkSession.createDataFrame(rows, "level int, entries bigint, kept bigint, power double")


def graph_stats(edges: DataFrame, item_kw: DataFrame) -> DataFrame:
    """One row: users, items, edges and keywords."""
    g = edges.agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items"), F.count("*").alias("edges"))
    return g.join(F.broadcast(item_kw.agg(F.countDistinct("kw").alias("keywords"))))


def maintenance(old: DataFrame, new: DataFrame, changes: DataFrame, placed: DataFrame, r_max: int = 3) -> DataFrame:
    """One row: changed edges, affected users, touched leaves."""
    users = synopsis.affected(old, new, changes, r_max)
    leaves = placed.join(users.withColumnRenamed("center", "u"), "u", "left_semi").select("leaf_id").distinct()
    return changes.agg(F.count("*").alias("changed")).join(F.broadcast(users.agg(F.count("*").alias("users")))).join(F.broadcast(leaves.agg(F.count("*").alias("leaves"))))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: centres that agree, that only one side answers, and whose answers differ."""
    x = community.fingerprints(a).select("qid", "center", F.col("fingerprint").alias("fa"))
    y = community.fingerprints(b).select("qid", "center", F.col("fingerprint").alias("fb"))
    j = x.join(y, ["qid", "center"], "full")
    return j.agg(F.count_if(F.col("fa") == F.col("fb")).alias("same"), F.count_if(F.col("fb").isNull()).alias("only_first"), F.count_if(F.col("fa").isNull()).alias("only_second"), F.count_if(F.col("fa") != F.col("fb")).alias("different"))


def purity(comm: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: user pairs that communities put together, pairs of the truth (u, label) among the
    same users, and those in both."""
    users = comm.select("qid", "center", "u").distinct()
    a, b = users.withColumnRenamed("u", "ui"), users.withColumnRenamed("u", "uj")
    put = a.join(b, ["qid", "center"]).filter("ui < uj").select("ui", "uj").distinct()
    seen = truth.join(users.select("u").distinct(), "u", "left_semi")
    x, y = seen.select("label", F.col("u").alias("ui")), seen.select("label", F.col("u").alias("uj"))
    real = x.join(y, "label").filter("ui < uj").select("ui", "uj").distinct()
    both = put.join(real, ["ui", "uj"])
    return put.agg(F.count("*").alias("put")).join(F.broadcast(real.agg(F.count("*").alias("real")))).join(F.broadcast(both.agg(F.count("*").alias("both"))))


def case_study(edges: DataFrame, comm: DataFrame, cliques: DataFrame) -> DataFrame:
    """Per community and biclique of its users: items of each, items only the community has, its greatest
    weight on those, and items it would recommend."""
    c = comm.groupBy("qid", "center").agg(F.array_sort(F.collect_set("u")).alias("members"), F.array_sort(F.collect_set("v")).alias("c_items"))
    met = c.join(cliques.withColumn("clique", F.monotonically_increasing_id()), F.size(F.array_except("users", "members")) == 0)
    missed = met.select("qid", "center", "clique", F.size("users").alias("clique_users"), F.size("members").alias("users"), F.size("c_items").alias("items"), F.size("items").alias("clique_items"), F.explode_outer(F.array_except("c_items", "items")).alias("v"))
    heavy = comm.groupBy("qid", "center", "v").agg(F.max("w").alias("heaviest"))
    extra = community.recommend(comm).groupBy("qid", "center").agg(F.count("*").alias("recommended"))
    out = missed.join(heavy, ["qid", "center", "v"], "left").groupBy("qid", "center", "clique", "users", "items", "clique_users", "clique_items").agg(F.count("v").alias("missed"), F.max("heaviest").alias("heaviest_missed"))
    return out.join(extra, ["qid", "center"], "left").withColumn("recommended", F.coalesce("recommended", F.lit(0))).drop("clique")


def collect_metrics(edges: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig()) -> dict[str, object]:
    """Rounds of the core and edges left after each, and the wedges of the first."""
    from ..operators import motifs, truss

    log: list[int] = []
    truss.core(edges, q.k, q.sigma, config.hub_degree, config.max_rounds, log)
    return {"rounds": len(log), "edges": log, "wedges": motifs.wedges(edges).count()}
