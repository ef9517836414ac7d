import brute
import numpy as np
import pytest
from fixtures import F1, F2, F5, block, frame, graph_of, random_graph

from bicommunity.model import CommunityQuery, EngineConfig
from bicommunity.operators import community, hops, prune, truss
from bicommunity.plans import baselines, snapshot


def kws(spark, g, kw="x"):
    return spark.createDataFrame(sorted({(v, kw) for _, v in g}), "v string, kw string")


def answers(df):
    out = {}
    for r in df.collect():
        out.setdefault(r.center, {})[r.u, r.v] = r.w
    return out


def test_worked_example(spark):
    q = CommunityQuery(2, 1, 11, ("x",))
    e, kw = frame(spark, F1), kws(spark, F1)
    got = answers(snapshot.run(e, kw, q))
    want = {(u, v): w for (u, v), w in F1.items() if u in (2, 3)}
    assert got == {2: want, 3: want}
    assert not answers(snapshot.run(e, kw, q.but(sigma=12))) and not answers(snapshot.run(e, kw, q.but(k=3)))


def test_three_ticks(spark):
    q = CommunityQuery(1, 1, 3, ("bank", "malware"))
    kw = spark.createDataFrame([("v1", "bank"), ("v1", "finance"), ("v2", "malware")], "v string, kw string")
    seen = [{u for a in answers(snapshot.run(frame(spark, g), kw, q)).values() for u, _ in a} for g in F2]
    assert seen == [{2, 3}, set(), {1, 2}]


@pytest.mark.parametrize("engine", ["grouped", "relational"])
def test_weak_pairs(spark, engine):
    q = CommunityQuery(3, 2, 3, ("x",))
    core = truss.core(frame(spark, F5), 3, 3)
    assert core.count() == 16
    got = answers(community.extract(core, q, engine=engine))
    for c, a in got.items():
        assert {u for u, _ in a} == ({1, 2} if c < 3 else {3, 4}) and len(a) == 8
    assert sorted(got) == [1, 2, 3, 4]


def test_radius_is_measured_inside(spark):
    g = block((1, 2), "ab") | block((2, 3), "cd") | block((3, 4), "ef") | {(1, "s"): 1, (4, "s"): 1}
    kw = spark.createDataFrame([(v, "x") for v in "abcdef"], "v string, kw string")
    far = hops.users(frame(spark, g), 1, spark.createDataFrame([(1,)], "center bigint"))
    assert 4 in {r.u for r in far.collect()}
    got = answers(snapshot.run(frame(spark, g), kw, CommunityQuery(1, 2, 1, ("x",))))
    assert {u for u, _ in got[1]} == {1, 2, 3}


@pytest.mark.parametrize("drop", ["user", "edge"])
def test_relational_engine_agrees(spark, drop):
    g = random_graph(3, 6, 7, 26)
    q = CommunityQuery(1, 1, 4, ("x",))
    core = truss.core(frame(spark, g), q.k, q.sigma)
    a = answers(community.extract(core, q, drop=drop))
    assert a and a == answers(community.extract(core, q, engine="relational", drop=drop))


@pytest.mark.parametrize("seed", range(2))
@pytest.mark.parametrize("drop", ["user", "edge"])
def test_answers_hold(spark, seed, drop):
    g = random_graph(seed, 7, 8, 34)
    e, kw = frame(spark, g), kws(spark, g)
    for q in (CommunityQuery(2, 2, 4, ("x",)),):
        core = truss.core(e, q.k, q.sigma)
        a = community.extract(core, q, drop=drop)
        assert answers(a) == answers(community.extract(e, q, drop=drop))
        assert community.validate(a, kw, q).count() == 0
        for c, x in answers(a).items():
            assert brute.valid(x, c, q.k, q.r, q.sigma)
        wide = answers(community.extract(core, q.but(r=q.r + 1), drop=drop))
        assert set(answers(a)) <= set(wide)


def test_candidate_strategies_agree(spark):
    g = random_graph(11, 9, 9, 44)
    e, kw = frame(spark, g), kws(spark, g)
    q = CommunityQuery(3, 2, 5, ("x",))
    got = [answers(snapshot.run(e, kw, q, EngineConfig(candidates=c, gamma=2))) for c in ("core", "synopsis", "both", "all")]
    assert got[0] and all(x == got[0] for x in got)
    assert answers(baselines.exhaustive_snapshot(e, kw, q)) == got[0]
    assert answers(baselines.trussness_query(baselines.trussness_index(e), kw, q)) == got[0]


@pytest.mark.parametrize("seed", range(6))
def test_existence_on_tiny_graphs(spark, seed):
    g = random_graph(seed, 3, 4, 10, 2)
    q = CommunityQuery(1, 1, 2)
    for c in {u for u, _ in g}:
        got = community.kernel(c, *map(__import__("numpy").array, ([u for u, _ in g], [v for _, v in g], list(g.values()))), q)
        best = brute.exists(g, c, q.k, q.r, q.sigma)
        if got is not None:
            assert 0 < len(got[0]) <= best
            assert brute.valid({(u, v): w for u, v, w in zip(*got[:3])}, c, q.k, q.r, q.sigma)


@pytest.mark.parametrize("items", ["inner", "closed"])
def test_engines_agree_by_size(spark, items):
    """Small graphs stay resident, larger ones go by centre, and large centres by joins."""
    g = random_graph(5, 8, 8, 34) | {(u + 20, v + "z"): w for (u, v), w in block((1, 2, 3), "abc").items()}
    e, q = frame(spark, g), CommunityQuery(2, 2, 3)
    want = answers(community.extract(e, q, engine="grouped", items=items))
    assert want and want == answers(community.extract(e, q, engine="resident", items=items))
    some = spark.createDataFrame([(21,), (22,), (99,)], "center bigint")
    assert {c for c in answers(community.extract(e, q, some, items=items))} <= {21, 22}
    assert 0 < community.large_centers(e, q.r, None, 20).count() < e.select("u").distinct().count()
    assert want == answers(community.extract(e, q, kernel_limit=20, items=items))


def test_total_rule(spark):
    g = block((1, 2, 3), "abc")
    q = CommunityQuery(1, 1, 3, score_rule="total", p=3)
    e, kw = frame(spark, g), kws(spark, g)
    assert len(answers(snapshot.run(e, kw, q))) == 3
    assert not answers(snapshot.run(e, kw, q.but(p=4)))
    a = community.extract(e, q)
    assert answers(a) == answers(community.extract(e, q, engine="relational"))


def test_dedupe_summary_recommend(spark):
    g = block((1, 2), "abc") | {(1, "z"): 1, (2, "z"): 1, (3, "a"): 1, (3, "b"): 1}
    e, kw = frame(spark, g), kws(spark, g)
    q = CommunityQuery(1, 1, 1, ("x",))
    all_ = snapshot.run(e, kw, q)
    one = community.dedupe(all_)
    # centre 3 reaches only its own items, so its answer is another one
    assert {r.center for r in one.select("center").distinct().collect()} == {1, 3}
    assert {r.center for r in community.dedupe(all_, "contained").select("center").distinct().collect()} == {1}
    one = one.filter("center = 1")
    s = community.summarise(one).first()
    assert (s.n_users, s.n_items, s.n_edges, s.max_dist) == (3, 4, 10, 2)
    assert {(r.u, r.v) for r in community.recommend(one).collect()} == {(3, "c"), (3, "z")}
    assert community.top(all_, 1).count() == 1


def test_layer_size_and_literal_rule(spark):
    c = frame(spark, block((1, 2, 3), "ab")).selectExpr("1L as center", "u", "v")
    assert prune.layer_size(c, 2).count() == 1 and prune.layer_size(c, 3).count() == 0
    from bicommunity.operators import score

    p = score.pairs(frame(spark, F5))
    assert prune.score(p, 3, "literal").count() == 0
    assert {r.u for r in prune.score(p, 3, "hop").collect()} == {1, 2, 3, 4}
    assert prune.score(p, 3).count() == 2


def test_bicliques(spark):
    g = block((1, 2, 3), "abcd") | block((3, 4), "de") | {(1, "q"): 1}
    got = [(tuple(r["users"]), tuple(r["items"])) for r in baselines.bicliques(frame(spark, g), 3, 4).collect()]
    assert got == [((1, 2, 3), ("a", "b", "c", "d"))]
    assert graph_of(frame(spark, g))


def test_bicliques_of_many_users(spark):
    g = {(u, v): 1 for u in range(6) for v in range(5)} | {(u, v): 1 for u in (6, 7) for v in range(10, 14)}
    got = {(tuple(r["users"]), len(r["items"])) for r in baselines.bicliques(frame(spark, g), 2, 4).collect()}
    assert got == {((0, 1, 2, 3, 4, 5), 5), ((6, 7), 4)}


def test_kernel_takes_rounds_together(monkeypatch):
    """A dense graph: users of many rounds go at once where support and radius stay, with the answer of one round at a time."""
    rng = np.random.default_rng(8)
    m = (rng.random((300, 40)) < 0.3).astype(np.int64)
    q, ids, calls, settle = CommunityQuery(4, 2, 3), np.arange(300), [], community._Dense.settle
    monkeypatch.setattr(community._Dense, "settle", lambda self, *a: calls.append(1) or settle(self, *a))
    got = community._Dense(m, 5, "user", True).one(q, 2, 3, ids)
    few = len(calls)
    monkeypatch.setattr(community._Dense, "stays", lambda *a: False)
    assert (got == community._Dense(m, 5, "user", True).one(q, 2, 3, ids)).all() and got[5].any()
    assert few <= 8 and len(calls) > 3 * few


def test_kernel_follows_changes(monkeypatch):
    """Within a step nearly each round takes support from others: it is followed from the users that change, not worked out anew."""
    rng = np.random.default_rng(3)
    m = (rng.random((400, 40)) < 0.5) * rng.integers(1, 3, (400, 40))
    q, ids, calls, relate, change = CommunityQuery(4, 2, 30), np.arange(400), [], community.relate, community._Live.change
    monkeypatch.setattr(community, "relate", lambda *a, **b: calls.append(1) or relate(*a, **b))
    got = community._Dense(m, 5, "user", True).one(q, 1, 30, ids)
    few = len(calls)

    def anew(self, rows, new):
        self.weak = None
        return change(self, rows, new)

    monkeypatch.setattr(community._Live, "change", anew)
    assert (got == community._Dense(m, 5, "user", True).one(q, 1, 30, ids)).all() and got[5].any()
    assert few <= 20 and len(calls) > 10 * few


def test_dense_graph_of_many_users_is_held(spark, monkeypatch):
    """Pairs of users take a byte each, so a graph of few items is held by each task with more users than its matrix would allow squared."""
    g = random_graph(5, 8, 4, 26)
    e, q = frame(spark, g), CommunityQuery(2, 2, 3)
    want = answers(community.extract(e, q, engine="grouped"))
    monkeypatch.setattr(community, "large_centers", lambda *a: pytest.fail("the graph isn't held"))
    assert want and want == answers(community.extract(e, q, max_cells=32))
    assert community.held(e, 25, 32) is None and community.held(e, 26, 31) is None
