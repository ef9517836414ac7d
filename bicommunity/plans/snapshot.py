"""Snapshot queries: candidates, core, extraction, refinement."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import CommunityQuery, EngineConfig
from ..operators import bounds, community, keywords, prune, score, support, synopsis, truss
from ..store import written


@dataclass
class Auxiliary:
    """What is kept beside the edges: pair sums, support bounds, keyword vectors, synopsis."""

    vectors: DataFrame
    pairs: DataFrame
    sup: DataFrame
    leaf: DataFrame
    placed: DataFrame
    leaves: DataFrame
    nodes: DataFrame
    items: DataFrame | None = None


def initialise(edges: DataFrame, item_kw: DataFrame, config: EngineConfig = EngineConfig()) -> Auxiliary:
    """All auxiliary data from one graph."""
    vectors = written(keywords.bit_vectors(item_kw, config.bits), "vectors")
    pairs = written(score.pairs(edges, config.hub_degree), "pairs")
    sup = written(support.exact(edges, hub_degree=config.hub_degree), "supports")
    return index(edges, vectors, pairs, sup, config)


def index(edges: DataFrame, vectors: DataFrame, pairs: DataFrame, sup: DataFrame, config: EngineConfig) -> Auxiliary:
    """The synopsis over given sums and bounds."""
    items = written(synopsis.item_values(edges, vectors, sup, pairs, config.bits, config.hub_degree), "items")
    return Auxiliary(vectors, pairs, sup, *_tree(edges, items, config), items)


def _tree(edges: DataFrame, items: DataFrame, config: EngineConfig) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Leaf rows, places, and the two tables of the synopsis."""
    leaf = written(synopsis.leaf_propagated(edges, items, config.r_max, config.bits), "leaf")
    placed = written(synopsis.partition(leaf, config.gamma), "placed")
    leaves, nodes = synopsis.build(leaf, placed, config.gamma, config.bits)
    return leaf, placed, written(leaves, "leaves"), written(nodes, "nodes")


@dataclass
class Index:
    """A synopsis that won't be maintained: it needs no table of pairs."""

    leaves: DataFrame
    nodes: DataFrame


def index_once(edges: DataFrame, item_kw: DataFrame, config: EngineConfig = EngineConfig()) -> Index:
    """The synopsis of one (written) graph from the bounds of its edges: the same as ``initialise`` builds, without pairs or wedges."""
    vectors = keywords.bit_vectors(item_kw, config.bits)
    items = written(synopsis.items_of_bounds(bounds.edge_bounds(edges), vectors, config.bits), "items")
    return Index(*_tree(edges, items, config)[2:])


def candidates(aux: Auxiliary | Index, q: CommunityQuery, config: EngineConfig = EngineConfig()) -> DataFrame:
    """``center``: users that the synopsis can't rule out."""
    return synopsis.traverse(aux.leaves, aux.nodes, q, config.bits)


def run(edges: DataFrame, item_kw: DataFrame, q: CommunityQuery, config: EngineConfig = EngineConfig(), aux: Auxiliary | None = None, dedupe: str | None = None) -> DataFrame:
    """Communities of a query on one graph: ``qid, center, u, v, w, radius``.

    ``config.candidates``: ``synopsis`` takes its users as centres, ``core`` those of the
    core, ``both`` the users in both, ``all`` every user of the filtered graph on its raw edges. The answer is the
    same. ``dedupe``: ``identical`` or ``contained`` keeps each community once.
    """
    mine = prune.keyword(edges, item_kw, q.keywords)
    centers = None
    if config.candidates in ("synopsis", "both"):
        centers = written(candidates(aux if aux is not None else index_once(edges, item_kw, config), q, config), "centers")
    if config.candidates in ("core", "both"):
        sigma = q.sigma if q.score_rule == "pair" else 0
        mine = truss.core(mine, q.k, sigma, config.hub_degree, config.max_rounds)
    else:
        mine = written(mine, "filtered")
    found = written(community.extract(mine, q, centers, config.engine, config.drop, config.items), "communities")
    return community.dedupe(found, dedupe) if dedupe else found
