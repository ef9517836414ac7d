"""Experiment workloads as queries: counts by parameter value."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import community, keywords, prune, truss
from ..operators import window as win
from ..plans import baselines, continuous, measures
from ..plans import workloads as wl
from ..sources import generate, tables
from ..store import written
from . import unrolled
from .base import Registry, edges_cte, pairs_cte
from .graphs import STREAM, _ablation_sql, epoch, parts, stream
from .search import ITEM_KW, Q_C, STREAM_TICK, STREAM_WINDOW, filtered, stream_sql

reg = Registry()
QUERIES, SQL = reg.queries, reg.sql

Q_BUSY = CommunityQuery(4, 1, 3, ("d1",), "busy")
Q_NUMBERED = CommunityQuery(4, 1, 3, tuple(str(i) for i in range(20)))
Q_CAPPED = CommunityQuery(20, 1, 20, ("Brand#1",))


def _numbered(domain: int, per_item: int) -> str:
    """Graph C with integer keywords, filtered by those below 20."""
    kw = f"SELECT DISTINCT v, (CAST(v AS BIGINT) * 7919 + j * 104729) % {domain} AS kw FROM (SELECT DISTINCT v FROM edges), (SELECT unnest(range(0, {per_item})) AS j)"
    return f"{edges_cte('C')}, mine AS MATERIALIZED (SELECT * FROM edges WHERE v IN (SELECT v FROM ({kw}) WHERE kw < 20))"


def _where(name: str, keywords: tuple[str, ...], condition: str = "true", w: str = "w") -> str:
    """The filtered graph's CTEs with a condition on edges, or another weight."""
    return filtered(name, keywords).replace("SELECT u, v, w FROM edges WHERE", f"SELECT u, v, {w} AS w FROM edges WHERE {condition} AND")


def _at(window: int, at: int, keywords: tuple[str, ...]) -> str:
    names = ", ".join(f"'{k}'" for k in keywords)
    now = f"SELECT u, v, CAST(sum(w) AS BIGINT) AS w FROM (SELECT u, v, w FROM base UNION ALL SELECT u, v, 1 FROM up WHERE t > {at - window} AND t <= {at}) GROUP BY u, v"
    return f"{STREAM}, item_kw AS ({ITEM_KW['E']}), mine AS MATERIALIZED (SELECT * FROM ({now}) WHERE v IN (SELECT v FROM item_kw WHERE kw IN ({names})))"


def _graph(spark, sf, name):
    g = tables.graph(spark, sf, name)
    return written(g.edges, "edges"), written(g.item_kw, "kw")


@reg("w1_vs_baseline_e", stream_sql(Q_BUSY, 8, "SELECT CAST(count(DISTINCT center) AS BIGINT) AS same, CAST(0 AS BIGINT) AS only_first, CAST(0 AS BIGINT) AS only_second, CAST(0 AS BIGINT) AS different FROM comm"))
def w1_vs_baseline_e(spark, sf):
    """Answers of the continuous engine and of a trussness index rebuilt at each tick."""
    base, up = stream(spark, sf)
    kw = tables.graph(spark, sf, "E").item_kw
    config = EngineConfig(window=STREAM_WINDOW, tick=STREAM_TICK)
    mine = continuous.run(base, up, kw, Q_BUSY, config).results("busy")
    other = baselines.recompute_stream(base, up, kw, Q_BUSY, config, by="trussness")[-1][1]
    return measures.agreement(mine, other)


@reg("w2_window_e", unrolled.sweep([(s, _at(s, 1000, Q_BUSY.keywords), Q_BUSY) for s in wl.WINDOWS], 8))
def w2_window_e(spark, sf):
    base, up = stream(spark, sf)
    return wl.sweep(wl.window_points(base, up, tables.graph(spark, sf, "E").item_kw, Q_BUSY, 1000))


@reg("w3_k_c", unrolled.sweep([(k, filtered("C", Q_C.keywords), Q_C.but(k=k)) for k in wl.KS], 10, drops=6))
def w3_k_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    return wl.sweep([(k, e, kw, Q_C.but(k=k)) for k in wl.KS])


@reg("w4_radius_c", unrolled.sweep([(r, filtered("C", Q_C.keywords), Q_C.but(r=r)) for r in wl.RADII], 7))
def w4_radius_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    return wl.sweep([(r, e, kw, Q_C.but(r=r)) for r in wl.RADII])


@reg("w5_sigma_c", unrolled.sweep([(s, filtered("C", Q_C.keywords), Q_C.but(sigma=s, r=1)) for s in wl.SIGMAS], 50))
def w5_sigma_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    return wl.sweep([(s, e, kw, Q_C.but(sigma=s, r=1)) for s in wl.SIGMAS])


@reg("w6_query_size_c")
def w6_query_size_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    q = CommunityQuery(5, 1, 5)
    return wl.sweep([(n, e, kw, q.but(keywords=wl.sample_query(kw, n))) for n in wl.QUERY_SIZES])


@reg("w7_domain_c", unrolled.sweep([(d, _numbered(d, 3), Q_NUMBERED) for d in wl.DOMAINS], 120, drops=6))
def w7_domain_c(spark, sf):
    e, _ = _graph(spark, sf, "C")
    items = e.select("v").distinct()
    return wl.sweep([(d, e, written(tables.integer_keywords(items, d, 3), "kw"), Q_NUMBERED) for d in wl.DOMAINS])


_PER = ", ".join(f"({n})" for n in wl.PER_ITEM)


@reg("w8_per_item_matching_c", f"""WITH {edges_cte('C')}, kw AS (SELECT DISTINCT n, v, (CAST(v AS BIGINT) * 7919 + j * 104729) % 500 AS kw FROM (SELECT DISTINCT v FROM edges), (VALUES {_PER}) t(n), (SELECT unnest(range(0, 5)) AS j) WHERE j < n)
  SELECT n AS per_item, CAST(count(*) AS BIGINT) AS matching FROM edges e JOIN (SELECT DISTINCT n, v FROM kw WHERE kw < 20) k ON e.v = k.v GROUP BY n""")
def w8_per_item_matching_c(spark, sf):
    e, _ = _graph(spark, sf, "C")
    items = e.select("v").distinct()
    out = None
    for n in wl.PER_ITEM:
        row = prune.keyword(e, tables.integer_keywords(items, 500, n), [str(i) for i in range(20)]).agg(F.count("*").alias("matching")).select(F.lit(n).alias("per_item"), "matching")
        out = row if out is None else out.unionByName(row)
    return out


@reg("w8_per_item_c", unrolled.sweep([(n, _numbered(500, n), Q_NUMBERED) for n in wl.PER_ITEM], 10))
def w8_per_item_c(spark, sf):
    e, _ = _graph(spark, sf, "C")
    items = e.select("v").distinct()
    return wl.sweep([(n, e, written(tables.integer_keywords(items, 500, n), "kw"), Q_NUMBERED) for n in wl.PER_ITEM])


@reg("w9_weight_cap_s", unrolled.sweep([(c, _where("S", Q_CAPPED.keywords, w=f"least(w, {c})"), Q_CAPPED) for c in wl.WEIGHT_CAPS], 12, False))
def w9_weight_cap_s(spark, sf):
    e, kw = _graph(spark, sf, "S")
    return wl.sweep([(c, written(wl.capped(e, c), "capped"), kw, Q_CAPPED) for c in wl.WEIGHT_CAPS], answers=False)


@reg("w10_items_c", unrolled.sweep([(p, _where("C", Q_C.keywords, f"CAST(v AS BIGINT) % 10 < {p}"), Q_C.but(r=1)) for p in wl.SHARES], 8))
def w10_items_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    return wl.sweep([(p, e.filter(F.col("v").cast("bigint") % 10 < p), kw, Q_C.but(r=1)) for p in wl.SHARES])


@reg("w11_users_c", unrolled.sweep([(p, _where("C", Q_C.keywords, f"u % 10 < {p}"), Q_C.but(r=1)) for p in wl.SHARES], 8))
def w11_users_c(spark, sf):
    e, kw = _graph(spark, sf, "C")
    return wl.sweep([(p, e.filter(F.col("u") % 10 < p), kw, Q_C.but(r=1)) for p in wl.SHARES])


@reg("w9_synthetic_weights_y")
def w9_synthetic_weights_y(spark, sf):
    q = CommunityQuery(2, 1, 2, tuple(str(i) for i in range(30)))
    return wl.sweep([wl.synthetic_point(spark, f"1-{hi}", q, n_users=2000, n_items=400, domain=60, weight_range=(1, hi)) for hi in wl.WEIGHT_CAPS], answers=False)


Q_SIZES = CommunityQuery(1, 1, 1, tuple(str(i) for i in range(30)))


@reg("w10_synthetic_items_y")
def w10_synthetic_items_y(spark, sf):
    """Item layers of the published sizes: the larger, the sparser."""
    return wl.sweep([wl.synthetic_point(spark, n, Q_SIZES, n_users=wl.LAYER, n_items=n, domain=60) for n in wl.LAYERS], answers=False)


@reg("w11_synthetic_users_y")
def w11_synthetic_users_y(spark, sf):
    """User layers of the published sizes: the larger, the more edges."""
    return wl.sweep([wl.synthetic_point(spark, n, Q_SIZES, n_users=n, n_items=wl.LAYER, domain=60) for n in wl.LAYERS], answers=False)


@reg("w11_synthetic_kinds_y")
def w11_synthetic_kinds_y(spark, sf):
    q = CommunityQuery(2, 1, 2, tuple(str(i) for i in range(30)))
    return wl.sweep([wl.synthetic_point(spark, f"{d}-{k}", q, n_users=1500, n_items=300, domain=60, degree=d, keyword=k) for d in ("powerlaw", "beta") for k in ("uniform", "lognormal", "pareto")], answers=False)


@reg("g10_synthetic_y")
def g10_synthetic_y(spark, sf):
    """Drawn edges between the given customers and parts."""
    users = tables.table(spark, sf, "customer").select(F.col("c_custkey").cast("bigint").alias("u"))
    items = tables.table(spark, sf, "part").select(F.col("p_partkey").cast("bigint").alias("v"))
    e, _ = generate.synthetic_on(users, items)
    return e.groupBy("w").agg(F.count("*").alias("edges"), F.countDistinct("u").alias("users"))


@reg("g11_keywords_e")
def g11_keywords_e(spark, sf):
    return generate.attach_keywords(tables.graph(spark, sf, "E").edges.select("v"), "lognormal", 100, 3)


@reg("g12_sampled_queries_c")
def g12_sampled_queries_c(spark, sf):
    qs = wl.sample_queries(tables.graph(spark, sf, "C").item_kw, 5, 3)
    return spark.createDataFrame([(q.qid, k) for q in qs for k in q.keywords], "qid string, kw string")


@reg("w12_ablation_s", _ablation_sql("S", 60, 60, keywords.query_vector(("Brand#1", "ECONOMY"))))
def w12_ablation_s(spark, sf):
    return measures.ablation(parts(spark, sf, "S", 1)[2], CommunityQuery(60, 1, 60, ("Brand#1", "ECONOMY")))


@reg("w13_case_study_c")
def w13_case_study_c(spark, sf):
    """Communities beside the complete blocks among their users."""
    e, kw = _graph(spark, sf, "C")
    mine = written(prune.keyword(e, kw, Q_C.keywords), "filtered")
    core = truss.core(mine, Q_C.k, Q_C.sigma)
    comm = written(community.dedupe(written(community.extract(core, Q_C), "communities")), "distinct")
    return measures.case_study(mine, comm, written(baselines.bicliques(core, 2, 3), "blocks"))


@reg("w13_case_study_3x4_c")
def w13_case_study_3x4_c(spark, sf):
    """The published size: communities beside the blocks of 3 users or more by 4 items or more among their users."""
    e, kw = _graph(spark, sf, "C")
    mine = written(prune.keyword(e, kw, Q_C.keywords), "filtered")
    core = truss.core(mine, Q_C.k, Q_C.sigma)
    comm = written(community.dedupe(written(community.extract(core, Q_C), "communities")), "distinct")
    return measures.case_study(mine, comm, written(baselines.bicliques(core, 3, 4), "blocks"))


@reg("w14_time_windows_e", "WITH x AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS d, user_id AS u, event_type || ':' || json_extract_string(props, '$.k') AS v, CAST(count(*) AS BIGINT) AS w FROM events WHERE event_type = 'click' GROUP BY ALL) SELECT CAST(epoch(d) AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS edges, CAST(sum(w) AS BIGINT) AS weight FROM x GROUP BY d")
def w14_time_windows_e(spark, sf):
    g = tables.graph(spark, sf, "E")
    clicks = g.interactions.join(g.item_kw.filter("kw = 'click'").select("v"), "v", "left_semi")
    return win.tumbling(clicks, "1 day").groupBy(epoch("start").alias("start")).agg(F.count("*").alias("edges"), F.sum("w").alias("weight"))


@reg("w15_worked_example", f"WITH {edges_cte('E')}, three AS MATERIALIZED (SELECT u, v, w FROM edges WHERE u BETWEEN 1 AND 3), {pairs_cte('three')} SELECT ui, uj, n, x, y, score FROM pairs")
def w15_worked_example(spark, sf):
    """The worked example's sums for three users of the event graph; its own numbers are in `tests/test_motifs.py`."""
    from ..operators import score

    return score.pairs(tables.graph(spark, sf, "E").edges.filter("u between 1 and 3"))
