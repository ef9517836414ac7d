"""Peeling by butterflies: k-bitruss, the core of compatible pairs, bitruss numbers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import Rounds
from . import dense, prune
from .bounds import edge_bounds
from .support import exact


def _twos(edges: DataFrame) -> DataFrame:
    """Edges whose user and item both have another edge: others are in no butterfly."""
    users = edges.groupBy("u").count().filter("count > 1").select("u")
    items = edges.groupBy("v").count().filter("count > 1").select("v")
    return edges.join(users, "u", "left_semi").join(items, "v", "left_semi").select("u", "v", "w")


def core(edges: DataFrame, k: int, sigma: int, hub_degree: int | None = None, max_rounds: int = 500, log: list | None = None, engine: str = "auto", kernel_limit: int = 200_000) -> DataFrame:
    """Largest sub-graph whose edges are each in ``k`` butterflies of pairs that score ``sigma``.

    Counts and scores only fall as edges go, so the order of removal doesn't matter and every
    community lies inside. ``joins`` peels in rounds, one job each; a round's table replaces the one before.
    ``auto`` hands over to a kernel in one task as soon as what is left is small enough for its matrices.
    ``log`` gets the number of edges after each round, and keeps to joins.
    """
    rounds = Rounds(edges.sparkSession, "core", max_rounds)
    small = engine == "auto" and log is None
    now = rounds.keep(edges.select("u", "v", "w") if small or k <= 0 else _twos(edges))
    n, first = now.count(), small
    while n and k > 0:
        if small and n <= kernel_limit and dense.fits(now, kernel_limit):
            return rounds.keep(_core_kernel(now, k, sigma))
        if first:
            now, first = rounds.keep(_twos(now)), False
            n = now.count()
            continue
        counted = edge_bounds(now, sigma) if sigma > 0 else exact(now, "auto", hub_degree)
        now = rounds.keep(prune.support(now, counted, k))
        left = now.count()
        if log is not None:
            log.append(left)
        if left == n:
            break
        n = left
    return now


def _core_kernel(edges: DataFrame, k: int, sigma: int) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parts = list(batches)
        if parts:
            g = pd.concat(parts)
            m, a, b = dense.matrix(g.u.to_numpy(), g.v.to_numpy().astype(str), g.w.to_numpy())
            yield g[dense.core(m, k, sigma)[a, b]]

    return edges.select("u", "v", "w").coalesce(1).mapInPandas(run, "u bigint, v string, w bigint")


def k_bitruss(edges: DataFrame, k: int, **options) -> DataFrame:
    """Largest sub-graph whose edges are each in ``k`` of its butterflies."""
    return core(edges, k, 0, **options)


def bitruss_numbers(edges: DataFrame, engine: str = "auto", kernel_limit: int = 200_000, max_rounds: int = 10_000) -> DataFrame:
    """``u, v, number``: the largest k whose k-bitruss has the edge.

    ``kernel`` peels a graph in one task as matrices; ``joins`` peels any graph, from each level on to
    the next least support that is left. ``auto`` takes the kernel for at most ``kernel_limit`` edges whose
    matrices fit.
    """
    if engine == "auto":
        engine = "kernel" if dense.fits(edges, kernel_limit) else "joins"
    if engine == "kernel":
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            parts = list(batches)
            if parts:
                g = pd.concat(parts)
                m, a, b = dense.matrix(g.u.to_numpy(), g.v.to_numpy().astype(str), np.ones(len(g), np.int64))
                yield g[["u", "v"]].assign(number=dense.bitruss_numbers(m)[a, b])

        return edges.select("u", "v").coalesce(1).mapInPandas(run, "u bigint, v string, number bigint")
    spark = edges.sparkSession
    rounds, out = Rounds(spark, "bitruss", max_rounds), Rounds(spark, "bitruss-numbers", max_rounds)
    now = rounds.keep(edges.select("u", "v"))
    done, k = None, 0
    while True:
        sup = rounds.keep(exact(now.withColumn("w", F.lit(1).cast("bigint"))))
        low = sup.agg(F.min("sup")).first()[0]
        if low is None:
            break
        k = max(k, low)
        fallen = sup.filter(F.col("sup") <= k).select("u", "v", F.lit(k).cast("bigint").alias("number"))
        done = out.keep(fallen if done is None else done.unionByName(fallen))
        now = rounds.keep(sup.filter(F.col("sup") > k).select("u", "v"))
    return done if done is not None else spark.createDataFrame([], "u bigint, v string, number bigint")
