"""Continuous queries over a count window: state, ticks and answer changes."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import community, dense, graph, hops, prune, score, support, synopsis, truss
from ..store import written
from . import snapshot

RESULT = "qid string, center bigint, u bigint, v string, w bigint, radius int"


def region(old: DataFrame, new: DataFrame, changes: DataFrame, r: int) -> DataFrame:
    """``center``: users whose answer can change, within ``r`` steps of a changed edge's user
    before or after (an answer reads nothing beyond its hop)."""
    return synopsis.affected(old, new, changes, r)


def changed_edges(old: DataFrame, new: DataFrame) -> DataFrame:
    """``u, v, w_old, w_new`` of edges that differ between two graphs (0: no edge)."""
    both = old.select("u", "v", F.col("w").alias("w_old")).join(new.select("u", "v", F.col("w").alias("w_new")), ["u", "v"], "full")
    zero = F.lit(0).cast("bigint")
    return both.select("u", "v", F.coalesce("w_old", zero).alias("w_old"), F.coalesce("w_new", zero).alias("w_new")).filter("w_old <> w_new")


def query_core(edges: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig) -> DataFrame:
    """The core of a query's edges: all that its answers are made of."""
    sigma = q.sigma if q.score_rule == "pair" else 0
    return truss.core(prune.keyword(edges, item_kw, q.keywords), q.k, sigma, config.hub_degree, config.max_rounds, kernel_limit=config.kernel_limit)


def refresh_exact(results: DataFrame, core_old: DataFrame, core_new: DataFrame, q: CommunityQuery, config: EngineConfig) -> DataFrame:
    """Answers that equal a snapshot's: an answer is made of core edges near its centre, so the centres near
    an edge in which the two cores differ are extracted again and the others keep theirs. Small cores (counted
    first) are compared and searched as local tables, others by joins."""
    if config.engine == "auto":
        old = dense.local(core_old, config.kernel_limit)
        new = dense.local(core_new, config.kernel_limit) if old is not None else None
        if new is not None:
            return _refresh_local(results, old, new, q, config)
    moved = written(changed_edges(core_old, core_new), "core-changes")
    if not moved.limit(1).count():
        return results
    centers = written(region(core_old, core_new, moved, q.r), "region")
    fresh = community.extract(core_new, q, centers, config.engine, config.drop, config.items)
    return written(results.join(centers, "center", "left_anti").select(*_columns()).unionByName(fresh), "results")


def _refresh_local(results: DataFrame, old: pd.DataFrame, new: pd.DataFrame, q: CommunityQuery, config: EngineConfig) -> DataFrame:
    both = old.merge(new, on=["u", "v"], how="outer", suffixes=("_old", "_new")).fillna({"w_old": 0, "w_new": 0})
    users = np.unique(both.u[both.w_old != both.w_new].to_numpy(np.int64))
    if not len(users):
        return results
    spark = results.sparkSession
    centers = np.union1d(dense.near(old, users, q.r), dense.near(new, users, q.r))
    fresh = community.extract_local(spark, new, q, np.intersect1d(centers, new.u.to_numpy()), config.drop, config.items)
    again = F.broadcast(spark.createDataFrame(pd.DataFrame({"center": centers}), "center bigint"))
    return written(results.join(again, "center", "left_anti").select(*_columns()).unionByName(fresh), "results")


def refresh_published(results: DataFrame, new: DataFrame, changes: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig) -> DataFrame:
    """Answers after changed edges (u, v, w_old, w_new) by the published rule: it looks again at answers
    that hold an expired edge, probes the centres near an inserting user, and keeps other old
    answers, even where a larger one is now possible."""
    mine_new = written(prune.keyword(new, item_kw, q.keywords), "filtered")
    relevant = changes
    if q.keywords:
        relevant = changes.join(item_kw.filter(F.col("kw").isin(*q.keywords)).select("v").distinct(), "v", "left_semi")
    fallen = relevant.filter("w_new < w_old")
    risen = relevant.filter("w_new > w_old")
    again = results.join(fallen.select("u", "v"), ["u", "v"], "left_semi").select("center").distinct()
    near = hops.users(mine_new, q.r, risen.select(F.col("u").alias("center")).distinct()).select(F.col("u").alias("center")).distinct()
    probe = near.join(results.select("center").distinct(), "center", "left_anti")
    centers = written(again.unionByName(probe).distinct(), "region")
    fresh = community.extract(mine_new, q, centers, config.engine, config.drop, config.items)
    kept = results.join(again, "center", "left_anti").select("qid", "center", "u", "v", "radius").join(mine_new, ["u", "v"]).select(*_columns())
    return written(kept.unionByName(fresh), "results")


def _columns() -> list[str]:
    return ["qid", "center", "u", "v", "w", "radius"]


def answer_changes(before: DataFrame, after: DataFrame, t: int) -> DataFrame:
    """``t, qid, center, op``: answers added, updated and dropped."""
    a = community.fingerprints(before).select("qid", "center", F.col("fingerprint").alias("old"))
    b = community.fingerprints(after).select("qid", "center", F.col("fingerprint").alias("new"))
    op = F.when(F.col("old").isNull(), "add").when(F.col("new").isNull(), "drop").when(F.col("old") != F.col("new"), "update")
    return a.join(b, ["qid", "center"], "full").select(F.lit(t).cast("bigint").alias("t"), "qid", "center", op.alias("op")).filter("op is not null")


@dataclass
class CommunityEngine:
    """The framework: a graph, its auxiliary data, registered queries and their answers.

    ``base`` edges never expire; updates enter with an arrival number and leave
    ``config.window`` arrivals later. State is a set of immutable tables in the shared folder; a tick makes new
    ones and then switches to them.
    """

    base: DataFrame
    item_kw: DataFrame
    config: EngineConfig = EngineConfig()
    auxiliary: bool = False
    edges: DataFrame = None
    at: int = 0
    aux: snapshot.Auxiliary | None = None
    queries: dict[str, CommunityQuery] = field(default_factory=dict)
    answers: dict[str, DataFrame] = field(default_factory=dict)
    cores: dict[str, DataFrame] = field(default_factory=dict)
    log: list[DataFrame] = field(default_factory=list)

    def __post_init__(self) -> None:
        self.item_kw = written(self.item_kw, "keywords")
        self.edges = written(self.base.select("u", "v", "w"), "edges")
        if self.auxiliary:
            self.aux = snapshot.initialise(self.edges, self.item_kw, self.config)

    def register(self, q: CommunityQuery) -> None:
        """Answer a query now and keep its answers up to date."""
        self.queries[q.qid] = q
        if self.config.policy == "exact":
            self.cores[q.qid] = query_core(self.edges, self.item_kw, q, self.config)
        self.answers[q.qid] = self.snapshot(q)

    def restore(self, edges: DataFrame, answers: dict[str, DataFrame], at: int) -> None:
        """Go on from saved edges and answers of arrival ``at``; cores and auxiliary data are worked out again."""
        self.edges, self.answers, self.at = edges, dict(answers), at
        if self.config.policy == "exact":
            self.cores = {qid: query_core(edges, self.item_kw, q, self.config) for qid, q in self.queries.items()}
        if self.auxiliary:
            self.aux = snapshot.initialise(edges, self.item_kw, self.config)

    def snapshot(self, q: CommunityQuery, dedupe: str | None = None) -> DataFrame:
        config = self.config if self.aux is not None else replace(self.config, candidates="core")
        return snapshot.run(self.edges, self.item_kw, q, config, self.aux, dedupe)

    def results(self, qid: str) -> DataFrame:
        return self.answers[qid]

    def changes(self) -> DataFrame:
        """All answer changes so far."""
        out = self.edges.sparkSession.createDataFrame([], "t bigint, qid string, center bigint, op string")
        for x in self.log:
            out = out.unionByName(x)
        return out

    def advance(self, inserted: DataFrame, expired: DataFrame, to: int) -> None:
        """One tick: any number of arrivals (u, v) up to ``to`` and what they push out."""
        moved = graph.net_changes(inserted, expired)
        changes = graph.changed_weights(self.edges, moved)
        if self.aux is not None or self.config.policy != "exact":
            changes = written(changes, "changes")
        new = written(graph.apply_changes(self.edges, moved), "edges")
        if self.aux is not None:
            self.aux = self.maintained(self.edges, new, changes)
        for qid, q in self.queries.items():
            before = self.answers[qid]
            if self.config.policy == "exact":
                core = query_core(new, self.item_kw, q, self.config)
                after = refresh_exact(before, self.cores[qid], core, q, self.config)
                self.cores[qid] = core
            else:
                after = refresh_published(before, new, changes, self.item_kw, q, self.config)
            if after is not before:
                self.log.append(written(answer_changes(before, after, to), "answer-changes"))
            self.answers[qid] = after
        self.edges, self.at = new, to

    def maintained(self, old: DataFrame, new: DataFrame, changes: DataFrame) -> snapshot.Auxiliary:
        """Auxiliary data after changed edges: pair sums, supports, item values and leaf rows near the changes are worked out
        again, and the tree from the touched leaves up; all else stays. A leaf that has grown too large has the tree built anew."""
        c, aux = self.config, self.aux
        pairs = written(score.maintain(aux.pairs, old, changes), "pairs")
        sup = written(support.maintain(old, new, changes, aux.pairs, pairs, aux.sup, c.hub_degree), "supports")
        moved = written(synopsis.changed_items(old, new, changes), "changed-items")
        items = written(synopsis.maintain_items(aux.items, new, aux.vectors, sup, pairs, moved, c.bits, c.hub_degree), "items")
        leaf = written(synopsis.maintain(aux.leaf, old, new, changes, items, c.r_max, c.bits), "leaf")
        here = leaf.select("u").distinct()
        strangers = leaf.join(aux.placed, "u", "left_anti")
        placed = written(synopsis.add_users(aux.placed.join(here, "u", "left_semi"), leaf, strangers), "placed")
        anew = synopsis.rebalance(placed, leaf, c.gamma)
        if anew is not placed:
            leaves, nodes = synopsis.build(leaf, anew, c.gamma, c.bits)
            return snapshot.Auxiliary(aux.vectors, pairs, sup, leaf, anew, written(leaves, "leaves"), written(nodes, "nodes"), items)
        gone = aux.placed.join(here, "u", "left_anti").select("u")
        touched = written(synopsis.affected(old, new, changes, c.r_max).select(F.col("center").alias("u")).unionByName(gone).distinct(), "touched")
        leaves, nodes = synopsis.refresh(aux.leaves, aux.nodes, leaf, placed, touched, c.gamma, c.bits)
        return snapshot.Auxiliary(aux.vectors, pairs, sup, leaf, placed, leaves, nodes, items)

    def feed(self, updates: DataFrame, until: int | None = None) -> None:
        """Advance over ranked updates (t, u, v) in ticks of ``config.tick`` arrivals."""
        last = updates.agg(F.max("t")).first()[0] or 0
        last = last if until is None else min(last, until)
        while self.at < last:
            to = min(self.at + self.config.tick, last)
            s = self.config.window
            inserted = updates.filter(F.col("t").between(self.at + 1, to))
            expired = updates.filter(F.col("t").between(self.at + 1 - s, to - s))
            self.advance(inserted, expired, to)


def run(base: DataFrame, updates: DataFrame, item_kw: DataFrame, queries: CommunityQuery | Iterable[CommunityQuery], config: EngineConfig = EngineConfig(), until: int | None = None) -> CommunityEngine:
    """Register one or many queries on the base graph and feed the updates through."""
    engine = CommunityEngine(base, item_kw, config)
    for q in [queries] if isinstance(queries, CommunityQuery) else queries:
        engine.register(q)
    engine.feed(updates, until)
    return engine


def queries_of(table: DataFrame) -> list[CommunityQuery]:
    """A table (qid, k, r, sigma, kws) of registered queries as query objects."""
    return [CommunityQuery(int(x.k), int(x.r), int(x.sigma), tuple(x.kws or ()), x.qid) for x in table.orderBy("qid").collect()]


def run_many(base: DataFrame, updates: DataFrame, item_kw: DataFrame, queries: DataFrame, config: EngineConfig = EngineConfig(), until: int | None = None) -> CommunityEngine:
    """Queries from a table share the edges, changes and state of each tick."""
    return run(base, updates, item_kw, queries_of(queries), config, until)
