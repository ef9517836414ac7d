"""Extraction, checking and comparison of (k, r, sigma)-communities.

The thresholds of support and radius only tighten as edges go, so each has a unique
largest sub-graph; the score rule hasn't: of two users with a weak score either may go. The answer
for a centre is therefore fixed by an order: first the fixpoint of support and radius; then the
centre's own weak partners go; then, round by round, every user that is worst among its weak partners
by (weak partners, distance, id). The best result over radii 1 to r is taken, so that
a larger radius never loses an answer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import CommunityQuery
from ..store import written
from . import hops
from .dense import MAX_CELLS, distances, matrix


#: Edges of the largest graph that each task holds, and how many times the cells of a matrix its pairs of users may be.
HELD_EDGES, PAIR_BYTES = 1 << 20, 32
#: Cells of a tile of user pairs.
TILE_CELLS = 1 << 19


_BELOW = np.tri(64, k=-1, dtype=np.uint8)


def enough(level: int, sigma: int) -> int:
    """The fewest shared items of two users that score ``sigma`` if all have the weight ``level``."""
    n = int(np.sqrt(2 * sigma)) // level
    while level * level * n * (n - 1) < 2 * sigma:
        n += 1
    return n


def relate(w: np.ndarray, sigma: int, at: np.ndarray | None = None, of: np.ndarray | None = None, levels: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Of the users ``of`` with those at ``at`` (all by default): the pairs that share an item and score less than ``sigma``, and the butterflies
    of other pairs on each cell. Sums of pairs are held for a tile of users at a time. ``levels``: all weights in order, if known."""
    at, of = (np.arange(len(w)) if x is None else x for x in (at, of))
    columns = np.flatnonzero(w.any(axis=0))
    if len(columns) < w.shape[1]:
        weak, part = relate(w[:, columns], sigma, at, of, levels)
        sup = np.zeros((len(of), w.shape[1]), part.dtype)
        sup[:, columns] = part
        return weak, sup
    most = max(int(w.sum(axis=1).max(initial=0)) ** 2, len(w) * w.shape[1])
    kind = np.float32 if most < 1 << 24 else np.float64
    levels = np.unique(w[w > 0]).tolist() if levels is None else levels
    weak, sup = np.zeros((len(of), len(at)), bool), np.zeros((len(of), w.shape[1]), kind)
    if not levels or not len(at):
        return weak, sup
    first, mine, others = levels[0], w[of], w[at]
    base = (mine > 0).astype(kind), (others > 0).astype(kind)
    above = [(mine > first).any(axis=1), np.flatnonzero((others > first).any(axis=1))]  # the others' sums follow from the shared items alone
    high = [((mine >= t).astype(kind), (others[above[1]] >= t).astype(kind)) for t in levels[1:]] if above[0].any() and len(above[1]) else []
    few = enough(first, sigma)
    place = np.minimum(np.searchsorted(at, of), len(at) - 1)
    self_at = np.where(at[place] == of, place, -1)
    step = max(1, TILE_CELLS // len(at))
    for lo in range(0, len(of), step):
        n = base[0][lo : lo + step] @ base[1].T
        me = self_at[lo : lo + step]
        n[np.flatnonzero(me >= 0), me[me >= 0]] = 0
        low = n < few
        rows = np.flatnonzero(above[0][lo : lo + step])
        if len(rows) and high:
            some = n[np.ix_(rows, above[1])]
            before, x, y = first, first * some, first * first * some
            for t, (a, b) in zip(levels[1:], high):
                both = a[lo + rows] @ b.T
                x += (t - before) * both
                y += (t * t - before * before) * both
                before = t
            low[np.ix_(rows, above[1])] = (x * x - y < 2 * sigma) | (some == 0) if sigma > 0 else False
        np.logical_and(n > 0, low, out=weak[lo : lo + step])
        n -= 1
        if sigma > 0:  # none shared is low, too
            n *= ~low
        else:
            np.maximum(n, 0, out=n)
        sup[lo : lo + step] = n @ base[1]
    return weak, sup


def total(w: np.ndarray) -> int:
    """The sum of the scores of all pairs, a tile of users at a time."""
    out, step = 0, max(1, TILE_CELLS // max(len(w), 1))
    for lo in range(0, len(w), step):
        before, x, y = 0, 0, 0
        for t in np.unique(w[w > 0]).tolist():
            both = (w[lo : lo + step] >= t).astype(np.float64) @ (w >= t).astype(np.float64).T
            both[np.arange(len(both)), np.arange(lo, lo + len(both))] = 0
            x, y, before = x + (t - before) * both, y + (t * t - before * before) * both, t
        out += int(np.sum(x * x - y))
    return out // 4


def worst(weak: np.ndarray, key: np.ndarray, few: int) -> tuple[np.ndarray, int]:
    """Places of the keys (-1: none) that are greater than those of all weak partners, and the number of greatest keys that settled it.

    A user that isn't among the worst ones looked at and has a weak partner there doesn't go, so few rows decide a round.
    """
    live = int((key >= 0).sum())
    while True:
        few = min(few, live)
        top = np.argpartition(key, len(key) - few)[len(key) - few :]
        top = top[np.argsort(-key[top])]
        rows = weak[top]
        seen = rows.max(axis=0) | (key < 0)
        seen[top] = 1
        other = np.flatnonzero(seen == 0)
        if len(other) <= 2 * few:
            break
        few *= 2
    found = top[~(rows[:, top] & (_BELOW[:few, :few] if few <= len(_BELOW) else np.tri(few, k=-1, dtype=np.uint8))).any(axis=1)]
    if len(other):  # each of these is held against its own weak partners
        found = np.append(found, other[np.where(weak[other] > 0, key, -1).max(axis=1) < key[other]])
    return found, few


def ranked(dist: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Places of users in the order of (distance, id)."""
    rank = np.empty(len(ids), np.int64)
    rank[np.lexsort((ids, dist))] = np.arange(len(ids))
    return rank


def rounds(weak: np.ndarray, dist: np.ndarray, ids: np.ndarray, goal: int, most: int = 1 << 29) -> np.ndarray:
    """The round in which each user goes (a large number: none), until at most ``goal`` are left, ``most`` rounds are over or none is weak. In a round go those that are worst
    among their weak partners by (weak partners, distance, id).

    What is left after some rounds is what is left if the worst go one at a time, but rounds are kept: other rules may set in between them.
    """
    n = left = len(weak)
    gone, at, count, number = np.full(n, 1 << 30), np.arange(n), weak.sum(axis=1), 0
    rank = ranked(dist, ids)
    weak, few = weak.view(np.uint8), 32
    while left > goal and number < most:
        key = np.where((gone[at] == 1 << 30) & (count > 0), count * n + rank[at], -1)
        live = int((key >= 0).sum())
        if not live:
            break
        if live < 0.5 * len(at):
            on = key >= 0
            at, count, weak, key = at[on], count[on], weak[np.ix_(on, on)], key[on]
        number += 1
        found, few = worst(weak, key, max(32, few // 2))
        gone[at[found]] = number
        count = count - weak[found].sum(axis=0, dtype=np.int64)
        left -= len(found)
    return gone


def last(weak: np.ndarray, count: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The users left when the worst go one at a time until none is weak: those that all rounds leave. ``count``: weak partners of each
    user (-1: it isn't there)."""
    n = len(count)
    key, less = np.where(count >= 0, count * n + rank, -1), np.empty(n, np.int64)
    while (i := int(key.argmax())) >= 0 and key[i] >= n:
        np.multiply(weak[i], n, out=less, dtype=np.int64)
        key -= less
        key[i] = -n * n
    return np.flatnonzero(key >= 0)


class _Live:
    """What is left of a graph: the weights of users ``at`` by items ``columns``. Weak pairs, their number at each user and supports follow
    each change, at the cost of the changed rows; users without an edge are left out now and then."""

    def __init__(self, w: np.ndarray, sigma: int, levels: list):
        self.levels = levels  # all weights in order
        self.w, self.at, self.columns, self.sigma = w, np.arange(len(w)), np.arange(w.shape[1]), sigma
        self.degree, self.dist, self.rank, self.weak, self.few = (w > 0).sum(axis=1), np.zeros(len(w), np.int64), None, None, 32

    def keep(self, rows: np.ndarray) -> None:
        """Leave out other users, which have no edge, and items without one."""
        columns = np.flatnonzero(self.w[rows].any(axis=0))
        if len(rows) == len(self.at) and len(columns) == len(self.columns):
            return
        self.w, self.at, self.columns = self.w[np.ix_(rows, columns)], self.at[rows], self.columns[columns]
        self.degree, self.dist, self.rank = self.degree[rows], self.dist[rows], None
        if self.weak is not None:
            self.weak, self.count, self.sup = self.weak[rows].take(rows, axis=1), self.count[rows], self.sup[np.ix_(rows, columns)]
            self.masks = None

    def follow(self, weak: np.ndarray, sup: np.ndarray, count: np.ndarray, own: bool) -> None:
        """Follow changes from here on. Arrays that aren't its ``own`` are copied before they change."""
        self.weak, self.sup, self.count, self.own, self.masks, self.rank = weak.view(np.uint8), sup, count, own, None, None

    def meet(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Weak pairs of some users with all, and the butterflies of other pairs on an edge."""
        mine = self.masks[0][rows]
        n = mine @ self.masks[0].T
        n[np.arange(len(rows)), rows] = 0
        low, first = n < self.fewest, self.levels[0]
        high = np.flatnonzero(self.place[rows] >= 0)
        if len(high) and self.sigma > 0:
            some = n[high].take(self.above, axis=1)
            before, x, y = first, first * some, first * first * some
            for t, m in zip(self.levels[1:], self.masks[1:]):
                mine = m[self.place[rows[high]]]
                if not mine.any():
                    break
                both = mine @ m.T
                x += (t - before) * both
                y += (t * t - before * before) * both
                before = t
            x *= x
            x -= y
            low[high[:, None], self.above] = (x < 2 * self.sigma) | (some == 0)
        weak = low & (n > 0)
        n -= 1
        if self.sigma > 0:
            n *= ~low
        else:
            np.maximum(n, 0, out=n)
        return weak.view(np.uint8), n

    def change(self, rows: np.ndarray, new: np.ndarray) -> np.ndarray:
        """Lower the weights of some users; the users whose supports may be others now."""
        if self.weak is None or 3 * len(rows) > len(self.at):
            self.w, self.degree = self.w.copy(), self.degree.copy()
            self.w[rows], self.degree[rows], self.weak = new, (new > 0).sum(axis=1), None
            return rows
        if not self.own:
            self.weak, self.sup, self.count, self.own = self.weak.copy(), self.sup.copy(), self.count.copy(), True
        if self.masks is None:
            self.fewest = enough(self.levels[0], self.sigma)
            self.w, self.above = self.w.copy(), np.flatnonzero((self.w > self.levels[0]).any(axis=1))
            self.masks = [(self.w > 0).astype(self.sup.dtype), *((self.w[self.above] >= t).astype(self.sup.dtype) for t in self.levels[1:])]
            self.place = np.full(len(self.w), -1)
            self.place[self.above] = np.arange(len(self.above))
        has, past = self.masks[0], self.masks[0][rows]
        before, old = self.weak[rows], self.meet(rows)[1]
        self.w[rows], self.degree[rows] = new, (new > 0).sum(axis=1)
        has[rows] = new > 0
        if len(self.above):
            high = self.place[rows]
            for t, m in zip(self.levels[1:], self.masks[1:]):
                m[high[high >= 0]] = new[high >= 0] >= t
        moved = old.any(axis=0)
        near = np.flatnonzero(moved)
        if self.degree[rows].any():
            weak, now = self.meet(rows)
            self.sup[near] += now[:, near].T @ has[rows] - old[:, near].T @ past
            self.sup[rows] = now @ has
        else:
            weak = np.zeros_like(before)
            self.sup[near] -= old[:, near].T @ past
            self.sup[rows] = 0
        self.count += weak.sum(axis=0, dtype=np.int64) - before.sum(axis=0, dtype=np.int64)
        self.count[rows] = weak.sum(axis=1, dtype=np.int64)
        self.weak[rows], self.weak[:, rows] = weak, weak.T
        moved[rows] = True
        return np.flatnonzero(moved)

    def worst(self, ids: np.ndarray) -> np.ndarray:
        """Users that are worst among their weak partners."""
        if self.rank is None:
            self.rank = ranked(self.dist, ids[self.at])
        found, self.few = worst(self.weak, np.where(self.count > 0, self.count * len(self.at) + self.rank, -1), max(8, self.few // 2))
        return found


class _Dense:
    """A small graph as a matrix of weights, users by items."""

    def __init__(self, weights: np.ndarray, center: int, drop: str, inner: bool, known: dict | None = None):
        """``known``: keeps what ``relate`` says of all weights for the next centre of the same ones."""
        self.w, self.c, self.drop, self.inner, self.known = weights, center, drop, inner, known
        if known is None or "levels" not in known:
            self.levels = np.unique(weights[weights > 0]).tolist()
            if known is not None:
                known["levels"] = self.levels
        else:
            self.levels = known["levels"]

    def settle(self, g: _Live, k: int, r: int, moved: np.ndarray | None = None) -> None:
        """Drop edges without ``k`` butterflies of compatible pairs and what is beyond the radius, until nothing is. ``moved``: users that
        lost edges or support since nothing was (all by default)."""
        c = int(np.searchsorted(g.at, self.c))
        steady = moved is not None and r == 1 and self.inner  # all items are the centre's: distances change with its edges only
        items = g.degree[c] if steady else -1
        if moved is None:
            moved = self.near(g, c, r)
        while g.degree[c]:
            while True:
                if g.weak is None:
                    self.start(g, k, c)
                    c, moved = int(np.searchsorted(g.at, self.c)), np.arange(len(g.at))
                low = (g.w[moved] > 0) & (g.sup[moved] < k)
                rows = np.flatnonzero(low.any(axis=1))
                if not len(rows):
                    break
                moved = g.change(moved[rows], np.where(low[rows], 0, g.w[moved[rows]]))
            if steady and g.degree[c] == items and len(g.dist) == len(g.at):
                g.dist[g.degree == 0] = 1 << 30
                return
            items, moved = g.degree[c], self.near(g, c, r)
            if not len(moved):
                return

    def near(self, g: _Live, c: int, r: int) -> np.ndarray:
        """Distances from the centre; drops what is beyond the radius. The users whose edges or supports may be others now."""
        on, limit = g.w > 0, 2 * r - 2 if self.inner else 2 * r
        dist = distances(on, np.array([c]))
        if (dist != g.dist)[g.degree > 0].any():
            g.rank = None
        g.dist = dist
        out = on & ~((dist <= 2 * r)[:, None] & on[dist <= limit].any(axis=0))
        rows = np.flatnonzero(out.any(axis=1))
        return g.change(rows, np.where(out[rows], 0, g.w[rows])) if len(rows) else rows

    def start(self, g: _Live, k: int, c: int) -> None:
        """Weak pairs and supports of all that is left."""
        while k > 0:  # edges that are alone at their user or item are in no butterfly
            on = g.w > 0
            alone = on & ((on.sum(axis=1) < 2)[:, None] | (on.sum(axis=0) < 2)[None, :])
            if not alone.any():
                break
            g.w = np.where(alone, 0, g.w)
            g.degree = (g.w > 0).sum(axis=1)
        full = g.degree > 0
        full[c] = True
        g.keep(np.flatnonzero(full))
        shared = self.known is not None and g.w is self.w
        known = self.known if shared else {}
        if g.sigma not in known:
            weak, sup = relate(g.w, g.sigma, levels=self.levels)
            known[g.sigma] = weak, sup, weak.sum(axis=1)
        g.follow(*known[g.sigma], own=not shared)

    def extract(self, q: CommunityQuery, ids: np.ndarray) -> tuple[np.ndarray, int] | None:
        """Weights of the answer and the radius that gave it."""
        best = None
        sigma = q.sigma if q.score_rule == "pair" else 0
        for r in range(q.r, 0, -1):  # of equal answers that of the smallest radius counts
            w = self.one(q, r, sigma, ids, best[0][0] if best else 0)
            if w is not None:
                size = (int((w > 0).any(axis=1).sum()), int((w > 0).sum()))
                if best is None or size >= best[0]:
                    best = (size, w, r)
        return best[1:] if best else None

    def whole(self, g: _Live) -> np.ndarray:
        out = np.zeros_like(self.w)
        out[np.ix_(g.at, g.columns)] = g.w
        return out

    def one(self, q: CommunityQuery, r: int, sigma: int, ids: np.ndarray, least: int = 0) -> np.ndarray | None:
        """Weights of the answer at a radius; None if there is none, or surely none of ``least`` users."""
        g, moved = _Live(self.w, sigma, self.levels), None
        self.tries = 0 if r == 1 and self.inner else 3  # among the centre's items alone supports are too tight
        while True:
            self.settle(g, q.k, r, moved)
            c = int(np.searchsorted(g.at, self.c))
            left = g.degree > 0
            if left.sum() < least or not left[c]:
                return None
            if q.score_rule == "total":
                return self.whole(g) if total(g.w) >= q.p * q.sigma else None
            if not g.count.any():
                return self.whole(g)
            if self.tries or left.sum() < 0.75 * len(left):
                g.keep(np.flatnonzero(left))
                c = int(np.searchsorted(g.at, self.c))
            if self.drop == "user":
                rows = self.losers(g, c, ids, q.k, r)
                moved = g.change(rows, np.zeros((len(rows), g.w.shape[1]), g.w.dtype))
            else:
                weak = g.weak.view(bool)
                rows = np.flatnonzero(weak[c]) if weak[c].any() else g.worst(ids)
                new = g.w[rows]
                for i, x in zip(rows, new):
                    x[g.w[c] > 0 if weak[c].any() else (g.w[weak[i]] > 0).any(axis=0)] = 0
                moved = g.change(rows, new)

    def losers(self, g: _Live, c: int, ids: np.ndarray, k: int, r: int) -> np.ndarray:
        """Users that go before anything else does: the centre's weak partners, if it has any, and those of as many rounds as support and
        radius surely change nothing in between."""
        weak = g.weak.view(bool)
        if self.tries:
            gone, first, rest = np.full(len(weak), 1 << 30), 1, ~weak[c]
            rank = ranked(g.dist, ids[g.at])
            if not rest.all():
                gone[weak[c]], first = 0, 0
            kept = np.zeros(len(weak), bool)
            kept[last(g.weak, np.where(rest, g.count - weak[~rest].sum(axis=0), -1), rank)] = True
            if self.stays(g.w, c, kept, g.dist, k, r, g.sigma):
                return np.flatnonzero(~kept)
            rest = np.flatnonzero(rest)
            gone[rest] = later = rounds(weak if first else weak[np.ix_(rest, rest)], g.dist[rest], ids[g.at[rest]], len(rest) // 8)
            ends = np.sort(later[later < 1 << 30])
            for part in (1, 0.75, 0.5, 0.25) if len(ends) else ():
                end = ends[max(0, int(part * len(ends)) - 1)]
                if end > first and self.stays(g.w, c, gone > end, g.dist, k, r, g.sigma):
                    return np.flatnonzero(gone <= end)
            self.tries -= 1  # they would mostly fail again
            return np.flatnonzero(gone <= first)
        return np.flatnonzero(weak[c]) if weak[c].any() else g.worst(ids)

    def stays(self, w: np.ndarray, c: int, kept: np.ndarray, dist: np.ndarray, k: int, r: int, sigma: int) -> bool:
        """True if the kept users alone give each edge of all users its support, and each user and item its distance. Then these hold in each part
        between, too: both only fall as users go, and users that go take no edge of others along."""
        on, at = w > 0, np.flatnonzero(kept)
        near = distances(on[at], np.searchsorted(at, [c]))
        if (near != dist[at]).any():
            return False
        limit = 2 * r - 2 if self.inner else 2 * r
        if (on.any(axis=0) & ~on[at][near <= limit].any(axis=0)).any():
            return False
        for d in range(2, 2 * r + 1, 2):
            if not on[~kept & (dist == d)][:, on[at][near <= d - 2].any(axis=0)].any(axis=1).all():
                return False
        rest, have, some = np.arange(len(w)), np.zeros(w.shape, np.int64), 64
        while len(at):  # some of the kept users are mostly enough
            have[rest] += relate(w, sigma, at[:some], rest, self.levels)[1].astype(np.int64)
            rest, at, some = rest[(on[rest] & (have[rest] < k)).any(axis=1)], at[some:], 2 * some
            if not len(rest):
                return True
        return False


def kernel(center: int, u: np.ndarray, v: np.ndarray, w: np.ndarray, q: CommunityQuery, drop: str = "user", items: str = "inner") -> tuple[np.ndarray, np.ndarray, np.ndarray, int] | None:
    """The answer of one centre within the given edges: u, v, w and radius; None if there is none."""
    if q.k <= 0:
        return None
    users, a = np.unique(u, return_inverse=True)
    names, b = np.unique(v, return_inverse=True)
    at = np.searchsorted(users, center)
    if at == len(users) or users[at] != center:
        return None
    m = np.zeros((len(users), len(names)), np.int64)
    m[a, b] = w
    got = _Dense(m, int(at), drop, items == "inner").extract(q, users)
    if got is None:
        return None
    i, j = np.nonzero(got[0])
    return users[i], names[j], got[0][i, j], got[1]


_OUT = "qid string, center bigint, u bigint, v string, w bigint, radius int"


def large_centers(core: DataFrame, r: int, centers: DataFrame | None = None, kernel_limit: int = 200_000, max_cells: int = MAX_CELLS) -> DataFrame:
    """``center``: those whose candidate may be too large for a kernel, by its users and the sum of
    their degrees, which bounds its edges and items."""
    degree = core.groupBy("u").agg(F.count("*").alias("degree"))
    size = hops.users(core, r, centers).join(degree, "u").groupBy("center").agg(F.count("*").alias("users"), F.sum("degree").alias("edges"))
    cells = F.col("users").cast("double") * F.greatest("users", "edges")
    return size.filter((F.col("edges") > kernel_limit) | (cells > max_cells)).select("center")


def held(core: DataFrame, kernel_limit: int, max_cells: int) -> pd.DataFrame | None:
    """A written graph as a local table, if a task can hold its matrix and a byte for each two users; it is counted before it is fetched."""
    if core.count() > kernel_limit:
        return None
    size = core.agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items")).first()
    if size.users * size.items > max_cells or size.users**2 > PAIR_BYTES * max_cells:
        return None
    return core.select("u", "v", "w").toArrow().to_pandas().astype({"u": np.int64, "w": np.int64})


def extract(core: DataFrame, q: CommunityQuery, centers: DataFrame | None = None, engine: str = "auto", drop: str = "user", items: str = "inner", kernel_limit: int = HELD_EDGES, max_cells: int = MAX_CELLS) -> DataFrame:
    """``qid, center, u, v, w, radius``: the community of each centre, by the edges of the core (or of
    any graph around it: the result is the same).

    ``resident``: the whole graph is small (counted first), goes to every task, and the centres are shared out.
    ``grouped``: a centre's candidate edges meet in one kernel, which suits candidates of bounded
    size. ``relational``: all centres advance together by joins, keyed by centre. ``auto``: resident if the graph
    is small enough; else each centre is measured, and those too large for a kernel go by joins.
    """
    from .relational import extract as by_joins

    if engine == "relational":
        return by_joins(core, q, centers, drop=drop, items=items)
    if engine in ("auto", "resident"):
        g = held(core, kernel_limit, max_cells)
        if g is not None:
            ids = np.unique(g.u.to_numpy())
            if centers is not None:
                own = centers.select("center").join(core.select(F.col("u").alias("center")).distinct(), "center", "left_semi").distinct()
                ids = np.sort(own.toPandas().center.to_numpy(np.int64))  # no more than the graph's users
            return extract_local(core.sparkSession, g, q, ids, drop, items)
        if engine == "resident":
            raise ValueError("the graph is too large to be resident")
        large = written(large_centers(core, q.r, centers, min(kernel_limit, 200_000), max_cells), "large-centers")
        if large.limit(1).count():
            every = (centers if centers is not None else core.select(F.col("u").alias("center"))).select("center").distinct()
            rest = written(every.join(large, "center", "left_anti"), "small-centers")
            return _grouped(core, q, rest, drop, items).unionByName(by_joins(core, q, large, drop=drop, items=items).select("qid", "center", "u", "v", "w", "radius"))
    return _grouped(core, q, centers, drop, items)


def extract_local(spark: SparkSession, g: pd.DataFrame, q: CommunityQuery, centers: np.ndarray, drop: str = "user", items: str = "inner") -> DataFrame:
    """Communities of the given centres on a small graph that each task holds as a matrix."""
    if q.k <= 0 or not len(centers) or not len(g):
        return spark.createDataFrame([], _OUT)
    m, _, _ = matrix(g.u.to_numpy(), g.v.to_numpy().astype(str), g.w.to_numpy())
    users, names = np.unique(g.u.to_numpy()), np.unique(g.v.to_numpy().astype(str))
    row, col = np.nonzero(m)
    graph = row.astype(np.int32), col.astype(np.int32), m[row, col], m.shape, users, names, centers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row, col, w, shape, users, names, centers = graph
        m = np.zeros(shape, np.int64)
        m[row, col] = w
        on, names = m > 0, pa.array(names, pa.string())
        known: dict = {}
        for c in (c for batch in batches for c in centers[batch.column(0).to_numpy()].tolist()):
            # what holds for all of the graph is worked out once a task
            at = int(np.searchsorted(users, c))
            dist = distances(on, np.array([at]))
            i = np.flatnonzero(dist <= 2 * q.r)
            j = np.flatnonzero(on[dist <= (2 * q.r - 2 if items == "inner" else 2 * q.r)].any(axis=0))
            every = len(i) == m.shape[0] and len(j) == m.shape[1]
            got = _Dense(m if every else m[np.ix_(i, j)], int(np.searchsorted(i, at)), drop, items == "inner", known if every else None).extract(q, users[i])
            if got is not None:
                a, b = np.nonzero(got[0])
                same = (pa.scalar(q.qid, pa.string()), pa.scalar(c, pa.int64()), pa.scalar(got[1], pa.int32()))
                qid, center, radius = (pa.repeat(x, len(a)) for x in same)
                yield pa.RecordBatch.from_arrays([qid, center, pa.array(users[i[a]]), names.take(pa.array(j[b])), pa.array(got[0][a, b]), radius], names=["qid", "center", "u", "v", "w", "radius"])

    parts = max(1, min(len(centers), 4 * spark.sparkContext.defaultParallelism))
    return spark.range(0, len(centers), 1, parts).mapInArrow(run, _OUT)


def _grouped(core: DataFrame, q: CommunityQuery, centers: DataFrame | None, drop: str, items: str) -> DataFrame:
    candidates = hops.subgraph(core, q.r, centers, items)

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        got = kernel(int(key[0]), g.u.to_numpy(), g.v.to_numpy().astype(str), g.w.to_numpy(), q, drop, items)
        if got is None:
            return pd.DataFrame({"qid": [], "center": [], "u": [], "v": [], "w": [], "radius": []}).astype({"qid": str, "center": "int64", "u": "int64", "v": str, "w": "int64", "radius": "int32"})
        u, v, w, r = got
        return pd.DataFrame({"qid": q.qid, "center": int(key[0]), "u": u, "v": v, "w": w, "radius": np.int32(r)})

    return candidates.groupBy("center").applyInPandas(run, _OUT)


def _inside(comm: DataFrame, key: list[str]) -> tuple[DataFrame, DataFrame]:
    """Wedges and pair sums within each community."""
    a = comm.select(*key, "v", F.col("u").alias("ui"), F.col("w").alias("wi"))
    b = comm.select(*key, "v", F.col("u").alias("uj"), F.col("w").alias("wj"))
    w = a.join(b, [*key, "v"]).filter("ui < uj").select(*key, "ui", "uj", "v", F.least("wi", "wj").alias("wm"))
    pairs = w.groupBy(*key, "ui", "uj").agg(F.count("*").alias("n"), F.sum("wm").alias("x"), F.sum(F.col("wm") * F.col("wm")).alias("y"))
    return w, pairs.withColumn("score", F.shiftright(F.col("x") * F.col("x") - F.col("y"), 1))


def measure(comm: DataFrame, r_max: int = 3) -> DataFrame:
    """Per community: users, items, edges, least support, least pair score, largest distance from the
    centre (null if a user can't be reached within ``r_max`` steps)."""
    key = ["qid", "center"]
    w, pairs = _inside(comm, key)
    met = w.join(pairs.select(*key, "ui", "uj", (F.col("n") - 1).alias("b")), [*key, "ui", "uj"])
    sup = met.select(*key, F.explode(F.array("ui", "uj")).alias("u"), "v", "b").groupBy(*key, "u", "v").agg(F.sum("b").alias("sup"))
    sup = comm.join(sup, [*key, "u", "v"], "left").groupBy(*key).agg(F.min(F.coalesce("sup", F.lit(0).cast("bigint"))).alias("min_sup"))
    low = pairs.groupBy(*key).agg(F.min("score").alias("min_score"), F.sum("score").alias("sum_score"))
    size = comm.groupBy(*key).agg(F.countDistinct("u").alias("n_users"), F.countDistinct("v").alias("n_items"), F.count("*").alias("n_edges"))
    seen = comm.filter("u = center").select(*key, "u", F.lit(0).alias("dist")).distinct()
    reach = seen
    for step in range(1, r_max + 1):
        items = reach.join(comm.select(*key, "u", "v"), [*key, "u"]).select(*key, "v").distinct()
        reach = items.join(comm.select(*key, "u", "v"), [*key, "v"]).select(*key, "u").distinct().join(seen, [*key, "u"], "left_anti").select(*key, "u", F.lit(2 * step).alias("dist"))
        seen = seen.unionByName(reach)
    far = seen.groupBy(*key).agg(F.max("dist").alias("d"), F.count("*").alias("reached"))
    out = size.join(sup, key).join(low, key, "left").join(far, key, "left")
    return out.select(*key, "n_users", "n_items", "n_edges", "min_sup", "min_score", "sum_score", F.when(F.col("reached") == F.col("n_users"), F.col("d")).alias("max_dist"))


def validate(comm: DataFrame, item_kw: DataFrame, q: CommunityQuery) -> DataFrame:
    """``qid, center, rule``: one row for each rule that a community breaks."""
    m = measure(comm.select("qid", "center", "u", "v", "w"), q.r)
    low = F.col("min_score") < q.sigma if q.score_rule == "pair" else F.col("sum_score") < q.p * q.sigma
    rules = [(F.col("min_sup") < q.k, "support"), (F.col("min_score").isNull() | low, "score"), (F.col("max_dist").isNull() | (F.col("max_dist") > 2 * q.r), "radius")]
    broken = m.select("qid", "center", F.explode(F.array_compact(F.array(*[F.when(c, F.lit(n)) for c, n in rules]))).alias("rule"))
    if not q.keywords:
        return broken
    fits = item_kw.filter(F.col("kw").isin(*q.keywords)).select("v").distinct()
    return broken.unionByName(comm.join(fits, "v", "left_anti").select("qid", "center", F.lit("keyword").alias("rule")).distinct())


def fingerprints(comm: DataFrame) -> DataFrame:
    """``qid, center, n_edges, fingerprint`` of each community's edge set."""
    edge = F.concat_ws("\x1f", F.col("u").cast("string"), "v")
    return comm.groupBy("qid", "center").agg(F.count("*").alias("n_edges"), F.sha2(F.array_join(F.array_sort(F.collect_list(edge)), "\x1e"), 256).alias("fingerprint"))


def dedupe(comm: DataFrame, how: str = "identical") -> DataFrame:
    """Communities once each, under their smallest centre; ``contained`` also drops those that are part
    of a larger one. A community is looked for only in the larger ones that have its rarest edge."""
    prints = fingerprints(comm)
    first = prints.groupBy("qid", "fingerprint").agg(F.min("center").alias("center"), F.first("n_edges").alias("n_edges"))
    kept = comm.join(first.select("qid", "center"), ["qid", "center"], "left_semi")
    if how == "identical":
        return kept
    sized = written(kept.select("qid", "center", "u", "v").join(first.select("qid", "center", "n_edges"), ["qid", "center"]), "distinct-communities")
    often = sized.groupBy("qid", "u", "v").agg(F.count("*").alias("times"))
    rarest = sized.join(often, ["qid", "u", "v"]).groupBy("qid", F.col("center").alias("ca"), F.col("n_edges").alias("na")).agg(F.min(F.struct("times", "u", "v")).alias("e"))
    rarest = rarest.filter("e.times > 1").select("qid", "ca", "na", F.col("e.u").alias("u"), F.col("e.v").alias("v"))
    larger = written(rarest.join(sized, ["qid", "u", "v"]).filter("n_edges > na").select("qid", "ca", "na", F.col("center").alias("cb")), "larger")
    mine = larger.join(sized.select("qid", F.col("center").alias("ca"), "u", "v"), ["qid", "ca"])
    both = mine.join(sized.select("qid", F.col("center").alias("cb"), "u", "v"), ["qid", "cb", "u", "v"]).groupBy("qid", "ca", "cb", "na").agg(F.count("*").alias("met"))
    inside = both.filter("met = na").select("qid", F.col("ca").alias("center")).distinct()
    return kept.join(inside, ["qid", "center"], "left_anti")


def summarise(comm: DataFrame, r_max: int = 3) -> DataFrame:
    """Measures, density and fingerprint of each community."""
    m = measure(comm.select("qid", "center", "u", "v", "w"), r_max)
    prints = fingerprints(comm).select("qid", "center", "fingerprint")
    return m.join(prints, ["qid", "center"]).withColumn("density", F.col("n_edges") / (F.col("n_users") * F.col("n_items")))


def recommend(comm: DataFrame) -> DataFrame:
    """``qid, center, u, v``: items of a community that its user isn't linked with."""
    users = comm.select("qid", "center", "u").distinct()
    items = comm.select("qid", "center", "v").distinct()
    return users.join(items, ["qid", "center"]).join(comm.select("qid", "center", "u", "v"), ["qid", "center", "u", "v"], "left_anti")


def top(comm: DataFrame, n: int, by: str = "min_score", r_max: int = 3) -> DataFrame:
    """The ``n`` communities of each query that are greatest by a measure."""
    m = summarise(comm, r_max)
    return m.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(by), "center"))).filter(F.col("rank") <= n)
