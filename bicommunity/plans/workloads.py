"""The experiment workloads: one row of counts for each parameter value."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import graph, prune, truss
from ..sources import generate, tables
from ..store import written
from . import snapshot

#: Values of each parameter; the defaults stand in DEFAULT and WINDOW.
WINDOWS = (50, 100, 150, 200, 300, 500, 800, 1000)
KS, RADII, SIGMAS = (3, 4, 5), (1, 2, 3), (1, 2, 3, 4, 5)
QUERY_SIZES, DOMAINS, PER_ITEM = (2, 3, 5, 8, 10), (100, 200, 500, 800, 1000), (1, 2, 3, 4, 5)
WEIGHT_CAPS, SHARES = (2, 3, 4), (2, 4, 6, 8, 10)
LAYERS, LAYER = (10_000, 15_000, 25_000, 50_000, 100_000), 25_000
DEFAULT = CommunityQuery(4, 2, 3, (), "default")
WINDOW = 500


def sample_query(item_kw: DataFrame, size: int, seed: int = 1) -> tuple[str, ...]:
    """``size`` keywords without repeats, each as likely as it is frequent: the least of
    exponential times over frequencies, with times from a hash, so a seed fixes the draw."""
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), "kw"), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
    drawn = item_kw.groupBy("kw").agg(F.count("*").alias("n")).orderBy(-F.log(u) / F.col("n"), "kw").limit(size)
    return tuple(sorted(r.kw for r in drawn.collect()))


def sample_queries(item_kw: DataFrame, size: int, n: int, seed: int = 1, base: CommunityQuery = DEFAULT) -> list[CommunityQuery]:
    return [base.but(keywords=sample_query(item_kw, size, seed + i), qid=f"q{i}") for i in range(n)]


def counts(edges: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig(), answers: bool = True) -> DataFrame:
    """One row: edges that match the keywords, edges and users of the core, centres with an answer, edges of
    all answers."""
    mine = written(prune.keyword(edges, item_kw, q.keywords), "filtered")
    core = truss.core(mine, q.k, q.sigma, config.hub_degree)
    row = mine.agg(F.count("*").alias("matching")).join(F.broadcast(core.agg(F.count("*").alias("core_edges"), F.countDistinct("u").alias("core_users"))))
    if answers:
        from ..operators import community

        found = written(community.extract(core, q, None, config.engine, config.drop, config.items), "communities")
        row = row.join(F.broadcast(found.agg(F.countDistinct("center").alias("answers"), F.count("*").alias("answer_edges"))))
    return row


def sweep(points: Sequence[tuple[object, DataFrame, DataFrame, CommunityQuery]], answers: bool = True) -> DataFrame:
    """Rows of ``counts`` by value; points are (value, edges, item keywords, query)."""
    out = None
    for value, edges, item_kw, q in points:
        row = counts(edges, item_kw, q, answers=answers).select(F.lit(str(value)).alias("value"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def pruned_share(spark: SparkSession, sf_dir: str, name: str, q: CommunityQuery, config: EngineConfig = EngineConfig()) -> DataFrame:
    from . import measures

    g = tables.graph(spark, sf_dir, name)
    aux = snapshot.initialise(written(g.edges, "edges"), g.item_kw, config)
    return measures.ablation(aux.leaf, q, config.bits).select(F.lit(name).alias("graph"), "*")


def capped(edges: DataFrame, cap: int) -> DataFrame:
    return edges.withColumn("w", F.least("w", F.lit(cap).cast("bigint")))


def synthetic_point(spark: SparkSession, value: object, q: CommunityQuery, **options) -> tuple[object, DataFrame, DataFrame, CommunityQuery]:
    edges, item_kw = generate.synthetic(spark, **options)
    return value, written(edges, "synthetic"), written(item_kw, "synthetic-kw"), q


def window_points(base: DataFrame, updates: DataFrame, item_kw: DataFrame, q: CommunityQuery, at: int, sizes: Sequence[int] = WINDOWS):
    return [(s, written(graph.snapshot(base, updates, s, at), "edges"), item_kw, q) for s in sizes]
