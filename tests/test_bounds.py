import brute
import numpy as np
import pyarrow as pa
import pytest
from fixtures import frame, random_graph
from pyspark.sql import functions as F

from bicommunity.model import CommunityQuery, EngineConfig
from bicommunity.operators import bounds, dense, graph, hops, keywords, motifs, prune, score, support, synopsis
from bicommunity.plans import snapshot
from bicommunity.queries import graphs, operators, search, workload
from bicommunity.sources import generate, tables
from bicommunity.store import written


@pytest.mark.parametrize("engine", ["lists", "matrix"])
@pytest.mark.parametrize("sigma", [0, 3])
def test_edge_bounds(spark, engine, sigma):
    """Supports and best scores in several batches and calls, against enumeration."""
    g = random_graph(5, 9, 8, 34) | {(50, "alone"): 7}
    e = written(frame(spark, g), "edges")
    scores = brute.scores(g)
    sup, best = dict.fromkeys(g, 0), dict.fromkeys(g, 0)
    for a, b, v, t in brute.butterflies(g):
        if scores[a, b] >= sigma:
            for edge in ((a, v), (a, t), (b, v), (b, t)):
                sup[edge] += 1
    for (a, b), s in scores.items():
        for v in {v for u, v in g if u == a} & {v for u, v in g if u == b}:
            best[a, v], best[b, v] = max(best[a, v], s), max(best[b, v], s)
    got = bounds.edge_bounds(e, sigma, engine, call=20, batch=40).collect()
    assert len(got) == len(g)
    assert {(r.u, r.v): (r.sup, r.best) for r in got} == {x: (sup[x], best[x]) for x in g}


def test_bounds_shuffle_no_wedges(spark):
    """A bound joins no wedges with pairs: of the plan's rows, none stands for a pair."""
    e = written(frame(spark, random_graph(2, 9, 8, 34)), "edges")
    plan = support.upper_bound(e)._jdf.queryExecution().toString()
    assert "ui" not in plan and "Join" not in plan
    assert support.upper_bound(e.limit(0)).count() == 0


def same(a, b):
    cols = b.columns
    return sorted(map(tuple, a.select(*cols).collect())) == sorted(map(tuple, b.collect()))


def test_dense_hops_equal_joins(spark, monkeypatch):
    """All users and sizes by matrices, in blocks of two or three centres, against the listed sub-graphs."""
    g = random_graph(3, 11, 9, 26) | {(70, "far"): 2, (71, "far"): 1}
    e = written(frame(spark, g), "edges")
    listed = {i: {r: hops.subgraph(e, r, items=i).groupBy("center").agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items"), F.count("*").alias("n"), F.sum("w").alias("w")) for r in (1, 2)} for i in ("inner", "closed")}
    monkeypatch.setattr(dense, "DENSE", 0)
    monkeypatch.setattr(dense, "BLOCK_CELLS", 30)
    for r in (1, 2, 3):
        assert same(hops.all_users(e, r), hops.users(e, r))
    for i, by in listed.items():
        for r, want in by.items():
            assert same(hops.sizes(e, r, i), want)


def test_near_users_repeat_columns(spark, monkeypatch):
    """A task's rows go by user: in a run of rows of one user stand all centres of a tile, so what is written is small."""
    e = written(frame(spark, {(u, str(v)): 1 for u in range(200) for v in range(3)}), "edges")
    monkeypatch.setattr(dense, "DENSE", 0)
    rows = hops.all_users(e, 1).collect()
    assert {(r.center, r.u, r.dist) for r in rows} == {(a, b, 0 if a == b else 2) for a in range(200) for b in range(200)} and len(rows) == 40_000
    runs = sum(a.u != b.u for a, b in zip(rows, rows[1:]))
    assert runs < len(rows) / 4


def test_dense_supports(spark, monkeypatch):
    g = random_graph(4, 9, 8, 40)
    e = written(frame(spark, g), "edges")
    monkeypatch.setattr(dense, "DENSE", 0)
    monkeypatch.setattr(dense, "BLOCK_CELLS", 20)
    assert {(r.u, r.v): r.sup for r in support.exact(e, "auto").collect()} == brute.supports(g)
    for by, key in (("user", 0), ("item", 1)):
        want = dict.fromkeys((x[key] for x in g), 0)
        for a, b, v, t in brute.butterflies(g):
            for x in ((a, b), (v, t))[key]:
                want[x] += 1
        assert {r[0]: r.butterflies for r in motifs.butterfly_counts(e, by).collect()} == want


def test_wedge_totals_list_nothing(spark):
    e = written(frame(spark, random_graph(6, 12, 5, 40, 4) | {(50, "alone"): 7}), "edges")
    want = motifs.wedges(e).groupBy("v").agg(F.count("*").alias("wedges"), F.sum("wm").alias("weight"))
    assert same(motifs.wedge_totals(e), want)
    assert "Join" not in motifs.wedge_totals(e)._jdf.queryExecution().toString()


def test_reach_passes_no_limit_of_rows(spark, small):
    """Recursive SQL counts each way to a user, and stops at the engine's limit of rows."""
    limit = spark.conf.get("spark.sql.cteRecursionRowLimit")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "20")
    try:
        got = {r.u: r.d for r in operators.op_recursive(spark, small).collect()}
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", limit)
    assert got[1] == 0 and set(got.values()) <= {0, 1, 2} and len(got) > 1


def test_fixed_rounds_and_levels(spark, small, monkeypatch):
    """Rows whose SQL has five rounds, or two levels, give those at any size."""
    for edges, want in (([9, 7], [9, 7, 7, 7, 7]), ([9, 8, 7, 6, 5, 4, 4], [9, 8, 7, 6, 5]), ([], [0] * 5)):
        monkeypatch.setattr(search.measures, "collect_metrics", lambda e, q, edges=edges: {"edges": edges, "wedges": 3})
        assert [r.edges for r in search.r11_rounds_c(spark, small).orderBy("round").collect()] == want
    leaf = spark.range(5000).select(F.col("id").alias("u"), F.lit(1).alias("r"), F.array_repeat(F.lit(1).cast("bigint"), 8).alias("bv"), F.lit(1).cast("bigint").alias("ub_sup"), F.col("id").alias("ub_score"))
    monkeypatch.setattr(graphs, "parts", lambda *a: (None, None, leaf))
    assert {r.level for r in graphs.s3_nodes_e(spark, small).collect()} == {0, 1}


def test_moved_onto_tables(spark, small):
    """Drawn edges and the worked example come from given tables."""
    for q in (workload.g10_synthetic_y, workload.w15_worked_example):
        assert q(spark, small).inputFiles()
    users, items = spark.range(40).withColumnRenamed("id", "u"), spark.range(100, 140, 2).withColumnRenamed("id", "v")
    e, _ = generate.synthetic_on(users, items)
    assert {int(r.v) for r in e.collect()} <= set(range(100, 140, 2)) and e.count() > 40


def test_supports_after_update_by_item_pairs(spark):
    """Users and items changed over: the maintained supports are those of the new graph."""
    g = random_graph(8, 9, 8, 34)
    gone = sorted(g)[:3]
    after = {e: w for e, w in g.items() if e not in gone} | {(20, "i1"): 2, (20, "i2"): 1}
    changes = [(u, v, g[u, v], 0) for u, v in gone] + [(20, "i1", 0, 2), (20, "i2", 0, 1)]
    old, new = frame(spark, g), frame(spark, after)
    moved = spark.createDataFrame(changes, "u bigint, v string, w_old bigint, w_new bigint")
    o, n, c, s = (graph.turned(x) for x in (old, new, moved, support.exact(old)))
    pairs = score.pairs(o)
    got = graph.turned(support.maintain(o, n, c, pairs, score.maintain(pairs, o, c), s))
    assert {(r.u, r.v): r.sup for r in got.collect()} == brute.supports(after)


@pytest.mark.parametrize("tile", [3, 1024])
def test_dense_pairs_equal_joins(spark, monkeypatch, tile):
    """Pair rows by tiles equal those of wedges and listed butterflies, with changed edges (new users and items too), and shuffle nothing."""
    monkeypatch.setattr(dense, "TILE", tile)
    e = written(frame(spark, random_graph(7, 14, 8, 70)), "edges")
    changes = [(r.u, r.v, r.w, w) for r, w in zip(e.orderBy("u", "v").limit(3).collect(), (0, 9, 1))]
    changes += [(777, "new", 0, 2), (778, "new", 0, 1), (777, e.first().v, 0, 4)]
    changes = written(spark.createDataFrame(changes, "u long, v string, w_old long, w_new long"), "changes")
    cases = (lambda: motifs.butterfly_pairs(e), lambda: score.direct(e), lambda: score.maintained(e, changes))
    names = (["ui", "uj", "butterflies", "score", "first", "last"], ["ui", "uj", "score"], ["ui", "uj", "n", "x", "y", "score"])
    for make, columns in zip(cases, names):
        monkeypatch.setattr(dense, "DENSE", 1 << 40)
        want = sorted(map(tuple, make().select(columns).collect()))
        monkeypatch.setattr(dense, "DENSE", 0)
        got = make().select(columns)
        assert want and sorted(map(tuple, got.collect())) == want
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "Exchange" not in plan


def test_graphs_are_fetched_as_arrow(spark, monkeypatch):
    """A graph for matrices doesn't come to the driver row by row."""
    from pyspark.sql import DataFrame

    e = written(frame(spark, random_graph(7, 14, 8, 70)), "edges")
    monkeypatch.setattr(DataFrame, "toPandas", lambda self: 1 / 0)
    m = dense.fetch(e)
    assert m.matrix(int).sum() == e.agg(F.sum("w")).first()[0] and len(m.w) == e.count()


def test_lists_go_once_to_a_range(spark):
    """A range of users gets each list of its items once, whatever number of its users the list has; edges are dropped by their bound without a join."""
    us, ws = [[1, 2, 3, 9], [2, 3], [8, 9]], [[1, 1, 2, 1], [4, 1], [1, 1]]
    lists = pa.RecordBatch.from_arrays([pa.array(["a", "b", "c"]), pa.array(us), pa.array(ws)], names=["v", "us", "ws"])
    ends = np.array([3, 6])
    sent = [pa.Table.from_batches(bounds._spread(iter([lists]), ends, now)).to_pylist() for now in (np.array([True, False, False]), np.array([False, True, True]))]
    assert [[(r["g"], r["v"]) for r in x] for x in sent] == [[(0, "a"), (0, "b")], [(2, "a"), (2, "c")]]
    assert next(bounds._sizes(iter([lists]), ends)).to_pydict() == {"g": [0, 2], "n": [6, 6]}
    e = written(frame(spark, random_graph(5, 9, 8, 34)), "edges")
    got = prune.support(e, bounds.edge_bounds(e, engine="lists", call=20, batch=40), 3)
    assert "Join" not in got._jdf.queryExecution().toString()
    assert same(got, prune.support(e, support.exact(e), 3))


def test_vectors_go_in_batches(spark, monkeypatch):
    """Leaf rows whose vectors are shuffled in batches equal those of one shuffle, and no batch holds the vectors of all edges."""
    e = written(frame(spark, random_graph(6, 30, 12, 90)), "edges")
    kw = e.select("v", F.concat(F.lit("k"), F.substring("v", 2, 1)).alias("kw")).distinct()
    items = written(synopsis.items_of_bounds(bounds.edge_bounds(e), keywords.bit_vectors(kw)), "items")
    want = synopsis.leaf_propagated(e, items, 3)
    held, gather = [], synopsis._gather
    monkeypatch.setattr(synopsis, "_gather", lambda link, *a: held.append(link.count()) or gather(link, *a))
    monkeypatch.setattr(synopsis, "ROWS", 20, raising=False)
    got = synopsis.leaf_propagated(e, items, 3)
    assert sorted(map(repr, got.collect())) == sorted(map(repr, want.collect()))
    assert max(held) < e.count() and len(held) == 5 * -(-e.count() // 20)


def test_snapshot_synopsis_needs_no_pairs(spark, monkeypatch):
    """The synopsis of a snapshot is that of the pair sums, and no pair is written for it."""
    e = written(frame(spark, random_graph(6, 30, 12, 90)), "edges")
    kw = e.select("v", F.concat(F.lit("k"), F.substring("v", 2, 1)).alias("kw")).distinct()
    q, config = CommunityQuery(2, 2, 2, ("k1", "k3")), EngineConfig(candidates="both", r_max=2, gamma=4)
    aux = snapshot.initialise(e, kw, config)
    want = sorted(map(repr, snapshot.run(e, kw, q, config, aux).collect()))
    monkeypatch.setattr(score, "pairs", lambda *a: 1 / 0)
    assert sorted(map(repr, snapshot.run(e, kw, q, config).collect())) == want
    once = snapshot.index_once(e, kw, config)
    for a, b in ((once.leaves, aux.leaves), (once.nodes, aux.nodes)):
        assert sorted(map(repr, a.collect())) == sorted(map(repr, b.collect()))


def test_events_are_read_light(spark, small):
    """Keywords are spread over kinds of events, not over events; bounds by matrices come as Arrow batches."""
    plan = tables.graph(spark, small, "E").item_kw._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" in plan[plan.index("Generate") :]
    e = written(frame(spark, random_graph(7, 14, 8, 70)), "edges")
    assert "MapInArrow" in bounds._by_matrix(spark, dense.fetch(e), 0)._jdf.queryExecution().executedPlan().toString()
