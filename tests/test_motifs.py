import random

import brute
import pytest
from fixtures import F1, block, frame, graph_of, random_graph
from pyspark.sql import functions as F

from bicommunity.operators import graph, motifs, score, support, truss


def rows(df, *cols):
    return {tuple(r[c] for c in cols[:-1]): r[cols[-1]] for r in df.collect()}


def test_worked_example(spark):
    e = frame(spark, F1)
    w = rows(motifs.wedges(e), "ui", "uj", "v", "wm")
    assert w[1, 2, "v1"] == 2
    b = rows(motifs.butterflies(e), "ui", "uj", "va", "vb", "score")
    assert len(b) == 3 and b[2, 3, "v2", "v3"] == 3
    p = {(r.ui, r.uj): r for r in score.pairs(e).collect()}
    assert (p[2, 3].n, p[2, 3].x, p[2, 3].y, p[2, 3].score) == (3, 6, 14, 11)
    assert p[1, 2].score == p[1, 3].score == 0
    s = rows(support.exact(e), "u", "v", "sup")
    assert s[1, "v1"] == 0 and sorted(s.values()) == [0] + [2] * 6
    assert motifs.butterfly_counts(e).first()[0] == 3


@pytest.mark.parametrize("seed", range(3))
def test_against_enumeration(spark, seed):
    g = random_graph(seed, 7, 7, 26)
    e = frame(spark, g)
    assert rows(motifs.wedges(e), "ui", "uj", "v", "wm") == brute.wedges(g)
    assert rows(motifs.wedges(e, hub_degree=2), "ui", "uj", "v", "wm") == brute.wedges(g)
    assert motifs.wedges(e, hub_degree=2).count() == len(brute.wedges(g))
    assert rows(score.pairs(e), "ui", "uj", "score") == brute.scores(g)
    assert {k: v for k, v in brute.scores(g).items() if v} == rows(score.direct(e), "ui", "uj", "score")
    want = brute.supports(g)
    for side in ("user", "item", "auto"):
        assert rows(support.exact(e, side), "u", "v", "sup") == want
    total = motifs.butterfly_counts(e).first()[0]
    assert sum(want.values()) == 4 * total == 4 * len(brute.butterflies(g))
    assert sum(rows(motifs.butterfly_counts(e, "user"), "u", "butterflies").values()) == 2 * total
    assert sum(rows(motifs.butterfly_counts(e, "item"), "v", "butterflies").values()) == 2 * total


def test_complete_block(spark):
    e = frame(spark, block(range(4), "abc"))
    assert {r.sup for r in support.exact(e).collect()} == {(4 - 1) * (3 - 1)}


def test_unit_rule(spark):
    cases = [(1, 2, True, 1), (2, 2, True, 0), (3, 2, True, 0), (1, 2, False, -1), (2, 2, False, -1), (3, 2, False, 0), (0, 1, True, 1), (1, 1, False, -1)]
    df = spark.createDataFrame(cases, "own bigint, other bigint, up boolean, want bigint")
    step, dy = score.unit_change(F.col("own"), F.col("other"), F.col("up"))
    for r in df.select("*", step.alias("step"), dy.alias("dy")).collect():
        new = r.own + (1 if r.up else -1)
        assert r.step == r.want == min(new, r.other) - min(r.own, r.other)
        assert r.dy == min(new, r.other) ** 2 - min(r.own, r.other) ** 2


@pytest.mark.parametrize("seed", range(3))
def test_maintenance_equals_rebuild(spark, seed):
    rng = random.Random(seed)
    g = random_graph(seed, 6, 6, 20)
    old = frame(spark, g)
    new_g = dict(g)
    for e in rng.sample(sorted(g), 6):
        new_g[e] = rng.choice([0, 1, 4])
    for _ in range(4):
        new_g.setdefault((rng.randrange(8), f"i{rng.randrange(8)}"), 2)
    moved = {e: (g.get(e, 0), w) for e, w in new_g.items() if g.get(e, 0) != w}
    new_g = {e: w for e, w in new_g.items() if w}
    changes = spark.createDataFrame([(u, v, a, b) for (u, v), (a, b) in moved.items()], "u bigint, v string, w_old bigint, w_new bigint")
    new = graph.apply_changes(old, changes.selectExpr("u", "v", "w_new - w_old as dw"))
    assert graph_of(new) == new_g
    pairs = score.maintain(score.pairs(old), old, changes)
    assert set(map(tuple, pairs.collect())) == set(map(tuple, score.pairs(frame(spark, new_g)).select(*pairs.columns).collect()))
    sup = support.maintain(old, new, changes, score.pairs(old), pairs, support.exact(old))
    assert rows(sup, "u", "v", "sup") == brute.supports(new_g)


def test_unit_maintenance(spark):
    g = random_graph(5, 5, 4, 14)
    e = frame(spark, g)
    rng = random.Random(1)
    for up in (True, False):
        (u, v), w = rng.choice(sorted(g.items()))
        h = dict(g) | {(u, v): w + (1 if up else -1)}
        h = {k: x for k, x in h.items() if x}
        got = score.maintain_unit(score.pairs(e), e, u, v, up)
        assert rows(got, "ui", "uj", "score") == brute.scores(h)


def brute_size(g):
    """A limit that only a peeled graph keeps to: the kernel takes over after a round of joins."""
    return len(g) - 1


@pytest.mark.parametrize("seed", range(3))
def test_peeling(spark, seed):
    g = random_graph(seed, 7, 7, 30)
    e = frame(spark, g)
    for k, sigma in ((1, 0), (2, 0), (2, 4), (3, 6)):
        assert graph_of(truss.core(e, k, sigma)) == brute.core(g, k, sigma)
        assert graph_of(truss.core(e, k, sigma, engine="joins")) == brute.core(g, k, sigma)
    assert graph_of(truss.core(e, 2, 4, kernel_limit=brute_size(g))) == brute.core(g, 2, 4)
    assert graph_of(truss.core(e.repartition(7), 2, 4, hub_degree=2)) == brute.core(g, 2, 4)
    a = rows(truss.bitruss_numbers(e, "kernel"), "u", "v", "number")
    assert a == rows(truss.bitruss_numbers(e, "joins"), "u", "v", "number")
    for k in (1, 2, 3):
        assert {x for x, n in a.items() if n >= k} == set(brute.core(g, k, 0))


def test_empty(spark):
    e = frame(spark, {})
    assert truss.core(e, 2, 1).count() == 0
    assert truss.bitruss_numbers(e, "kernel").count() == truss.bitruss_numbers(e, "joins").count() == 0
    assert graph.layers(e).first().edges == 0
