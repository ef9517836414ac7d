"""Small graphs as matrices of weights, users by items."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

#: Cells of the largest matrix that a kernel may build (users by users, or users by items).
MAX_CELLS = 1 << 22
#: Cells and edges of the largest matrix (users by items) that tasks work on by blocks of users.
FETCH_CELLS, FETCH_EDGES = 1 << 26, 1 << 23
#: Cells of a block (its users by all users), distinct weights for products by weight, and meetings an edge from which matrices gain.
BLOCK_CELLS, MAX_LEVELS, DENSE = 1 << 22, 64, 64
#: Users on each side of a tile of pairs.
TILE = 1 << 10
#: Users whose rows are turned to floating point at once.
FEW = 1 << 13


def fits(edges: DataFrame, kernel_limit: int, max_cells: int = MAX_CELLS) -> bool:
    """True if a written graph has at most ``kernel_limit`` edges and its matrices ``max_cells`` cells each."""
    if edges.count() > kernel_limit:
        return False
    size = edges.agg(F.countDistinct("u").alias("users"), F.countDistinct("v").alias("items")).first()
    return size.users * max(size.users, size.items) <= max_cells


def local(edges: DataFrame, kernel_limit: int, max_cells: int = MAX_CELLS) -> pd.DataFrame | None:
    """A written graph as a local table if it is as small as ``fits`` asks, else None. It is counted before
    it is fetched, so the driver never gets more than ``kernel_limit`` edges."""
    if edges.count() > kernel_limit:
        return None
    g = edges.select("u", "v", "w").toPandas().astype({"u": np.int64, "w": np.int64})
    users = g.u.nunique()
    return g if users * max(users, g.v.nunique()) <= max_cells else None


@dataclass(frozen=True)
class Fetched:
    """A graph of few cells: sorted users and items, the row, column and weight of each edge, and the users of a block."""

    users: np.ndarray
    items: list[str]
    a: np.ndarray
    b: np.ndarray
    w: np.ndarray
    block: int

    def blocks(self, spark: SparkSession) -> DataFrame:
        """``lo``: the first row of each block of users, a few blocks a task."""
        n = -(-len(self.users) // self.block)
        return spark.range(0, len(self.users), self.block, max(1, min(n, 4 * spark.sparkContext.defaultParallelism))).withColumnRenamed("id", "lo")

    def matrix(self, kind: type = np.float32) -> np.ndarray:
        m = np.zeros((len(self.users), len(self.items)), kind)
        m[self.a, self.b] = self.w
        return m

    def exact_in_float32(self) -> bool:
        """True if sums over a row or column of weights, squares and common items are all exact in 24 bits."""
        squares = self.w.astype(np.float64) ** 2
        if not len(squares):
            return True
        most = max(np.bincount(x, squares).max() for x in (self.a, self.b))
        return max(most, np.bincount(self.a).max() * np.bincount(self.b).max()) < 1 << 24


def measured(edges: DataFrame) -> Row:
    """``n, items, meet``: edges and items of a graph, and the meetings of its edges on their items, each with itself too."""
    n = edges.groupBy("v").agg(F.count("*").alias("n"))
    return n.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("items"), F.coalesce(F.sum(F.col("n") * F.col("n")), F.lit(0)).alias("meet")).first()


def fetch(edges: DataFrame, size: Row | None = None) -> Fetched | None:
    """A written graph on the driver if it has at most ``FETCH_EDGES`` edges and ``FETCH_CELLS`` cells, else None. It is
    counted before it is fetched (``size``: by ``measured``, if that is known)."""
    size = size or measured(edges)
    if size.n > FETCH_EDGES or size.items > FETCH_CELLS or edges.agg(F.countDistinct("u")).first()[0] * size.items > FETCH_CELLS:
        return None
    items = sorted(r.v for r in edges.select("v").distinct().collect())
    place = edges.sparkSession.createDataFrame([(v, i) for i, v in enumerate(items)], "v string, b int")
    # as Arrow columns: millions of edges one by one as Python rows take minutes
    g = edges.join(F.broadcast(place), "v").select(F.col("u").cast("long"), "b", F.col("w").cast("long")).toArrow()
    u, b, w = (g.column(i).to_numpy() for i in range(3))
    users, a = np.unique(u, return_inverse=True)
    return Fetched(users, items, a.astype(np.int32), b, w, max(1, BLOCK_CELLS // max(len(users), len(items), 1)))


def worth(edges: DataFrame) -> Fetched | None:
    """The fetched graph if it fits and its edges meet so many others on their items that matrices gain, else None."""
    size = measured(edges)
    return fetch(edges, size) if size.meet > DENSE * size.n else None


def item_pairs(has: np.ndarray) -> np.ndarray:
    """Of each two items: the users of both but one."""
    others = np.full((has.shape[1],) * 2, -1.0)
    for lo in range(0, len(has), FEW):
        part = has[lo : lo + FEW].astype(np.float64)
        others += part.T @ part
    np.fill_diagonal(others, 0)
    return others


def supports(spark: SparkSession, m: Fetched) -> DataFrame:
    """``u, v, sup`` of every edge through item pairs."""
    shared = spark.sparkContext.broadcast(m)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = shared.value
        has = (g.matrix() > 0).view(np.uint8)
        others = item_pairs(has)
        items = np.array(g.items, object)
        for batch in batches:
            for lo in batch.lo:
                rows = has[lo : lo + g.block].astype(np.float64)
                a, b = np.nonzero(rows)
                if len(a):
                    yield pd.DataFrame({"u": g.users[lo + a], "v": items[b], "sup": (rows @ others)[a, b].astype(np.int64)})

    return m.blocks(spark).mapInPandas(run, "u bigint, v string, sup bigint")


def pair_rows(spark: SparkSession, m: Fetched, least: int = 1, ends: bool = False, moved: pd.DataFrame | None = None) -> DataFrame:
    """``ui, uj, n, x, y`` (ui < uj) of all user pairs with ``least`` shared items or more; with ``ends`` also the ``first``
    and ``last`` shared item. A task multiplies its users' weights with those of all later users, tile by tile, and hands the rows on:
    nothing is shuffled. ``moved`` (ui, uj, dn, dx, dy) is added to the sums first."""
    levels = np.unique(m.w[m.w > 0]).tolist()
    if moved is not None:
        a, b = np.searchsorted(m.users, moved.ui.to_numpy(np.int64)), np.searchsorted(m.users, moved.uj.to_numpy(np.int64))
        order = np.argsort(a, kind="stable")
        deltas = [x[order] for x in (a, b, *(moved[c].to_numpy(np.int64) for c in ("dn", "dx", "dy")))]
    else:
        deltas = [np.empty(0, np.int64)] * 5
    shared = spark.sparkContext.broadcast((m, deltas))
    n_users = len(m.users)
    step = max(1, min(TILE, -(-n_users // (4 * spark.sparkContext.defaultParallelism))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, (da, db, *ds) = shared.value
        kind = np.float32 if g.exact_in_float32() else np.float64
        full, items = g.matrix(kind), pa.array(g.items, pa.string())
        for lo in (x for batch in batches for x in batch.column(0).to_pylist()):
            rows = full[lo : lo + step]
            mine = [(rows >= t).astype(kind) for t in levels]
            own = slice(*np.searchsorted(da, [lo, lo + len(rows)]))
            for at in range(lo, n_users, TILE):
                others = full[at : at + TILE]
                sums = [np.zeros((len(rows), len(others)), np.int64) for _ in range(3)]
                before = 0
                for t, on in zip(levels, mine):
                    both = (on @ (others >= t).astype(kind).T).astype(np.int64)
                    for total, by in zip(sums, (int(before == 0), t - before, t * t - before * before)):
                        if by:
                            total += by * both
                    before = t
                here = np.flatnonzero((db[own] >= at) & (db[own] < at + len(others)))
                for total, d in zip(sums, ds):
                    np.add.at(total, (da[own][here] - lo, db[own][here] - at), d[own][here])
                i, j = np.nonzero((sums[0] >= least) & (np.arange(lo, lo + len(rows))[:, None] < np.arange(at, at + len(others))))
                out = [pa.array(g.users[lo + i]), pa.array(g.users[at + j]), *(pa.array(total[i, j]) for total in sums)]
                if ends:
                    first, last = (np.zeros((len(rows), len(others)), np.int32) for _ in range(2))
                    have = [(np.flatnonzero(rows[:, k]), np.flatnonzero(others[:, k])) for k in range(len(g.items))]
                    for k, (x, y) in enumerate(have):
                        last[x[:, None], y] = k
                    for k, (x, y) in reversed(list(enumerate(have))):
                        first[x[:, None], y] = k
                    out += [items.take(pa.array(e[i, j])) for e in (first, last)]
                yield pa.RecordBatch.from_arrays(out, names=["ui", "uj", "n", "x", "y", "first", "last"][: len(out)])

    starts = spark.range(0, n_users, step, max(1, -(-n_users // step)))
    return starts.mapInArrow(run, "ui bigint, uj bigint, n bigint, x bigint, y bigint" + (", first string, last string" if ends else ""))


def few_levels(m: Fetched | None) -> bool:
    """True for a fetched graph with so few weights that sums over pairs go by weight."""
    return m is not None and len(np.unique(m.w)) <= MAX_LEVELS


def reach(has: np.ndarray, lo: int, n: int, r: int) -> tuple[np.ndarray, np.ndarray]:
    """User steps from each of the ``n`` users from row ``lo`` on to every user (-1: more than ``r``), and the items within ``2 r - 1`` hops."""
    n = min(n, len(has) - lo)
    dist = np.full((n, len(has)), -1, np.int8 if r < 128 else np.int32)
    dist[np.arange(n), lo + np.arange(n)] = 0
    items = np.zeros((n, has.shape[1]), bool)
    for step in range(1, r + 1):
        near = ((dist == step - 1).astype(has.dtype) @ has > 0) & ~items
        if not near.any():
            break
        items |= near
        dist[(near.astype(has.dtype) @ has.T > 0) & (dist < 0)] = step
    return dist, items


def near_users(spark: SparkSession, m: Fetched, r: int) -> DataFrame:
    """``center, u, dist`` for all centres. A task's rows go by user and then by centre: nearly each user is near nearly each centre
    of a tile, so the columns repeat themselves and the written result takes a small part of what it would take by centre."""
    shared = spark.sparkContext.broadcast(m)
    n_users = len(m.users)
    tasks = 4 * spark.sparkContext.defaultParallelism
    step = max(1, min(TILE, 4 * BLOCK_CELLS // max(n_users, 1), -(-n_users // tasks)))
    rows = max(1, BLOCK_CELLS // 4 // step)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = shared.value
        has = g.matrix()
        np.minimum(has, 1, out=has)
        for lo in (x for batch in batches for x in batch.column(0).to_pylist()):
            dist, _ = reach(has, lo, step, r)
            for at in range(0, len(has), rows):
                part = dist[:, at : at + rows].T
                b, a = np.nonzero(part >= 0)
                out = g.users[lo + a], g.users[at + b], 2 * part[b, a].astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in out], names=["center", "u", "dist"])

    return spark.range(0, n_users, step, max(1, min(-(-n_users // step), 2 * tasks))).mapInArrow(run, "center bigint, u bigint, dist int")


def near_sizes(spark: SparkSession, m: Fetched, r: int, closed: bool) -> DataFrame:
    """``center, users, items, n, w`` of each centre's sub-graph."""
    shared = spark.sparkContext.broadcast(m)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = shared.value
        kind = np.float32 if g.exact_in_float32() else np.float64
        full = g.matrix(kind)
        has = (full > 0).astype(kind)
        for batch in batches:
            for lo in batch.lo:
                dist, good = reach(has, lo, g.block, r)
                near = (dist >= 0).astype(kind)
                n, w = near @ has, near @ full
                if closed:
                    good = good | (n > 1)
                n, w = np.where(good, n, 0).sum(axis=1, dtype=np.float64), np.where(good, w, 0).sum(axis=1, dtype=np.float64)
                yield pd.DataFrame({"center": g.users[lo : lo + len(near)], "users": (dist >= 0).sum(axis=1), "items": good.sum(axis=1), "n": n.astype(np.int64), "w": w.astype(np.int64)})

    return m.blocks(spark).mapInPandas(run, "center bigint, users bigint, items bigint, n bigint, w bigint")


def distances(on: np.ndarray, sources: np.ndarray) -> np.ndarray:
    """Hops from the nearest of the given users to each user; a large number where there is no path."""
    dist = np.full(len(on), 1 << 30, np.int64)
    seen, at, step = np.zeros(len(on), bool), np.zeros(len(on), bool), 0
    at[sources] = True
    while at.any():
        dist[at] = step
        seen |= at
        at = on[:, on[at].any(axis=0)].any(axis=1) & ~seen
        step += 2
    return dist


def near(g: pd.DataFrame, users: np.ndarray, r: int) -> np.ndarray:
    """Users of a graph within ``r`` steps of the given ones, and those themselves."""
    own = np.intersect1d(users, g.u.to_numpy())
    if not len(own):
        return users
    m, _, _ = matrix(g.u.to_numpy(), g.v.to_numpy().astype(str), g.w.to_numpy())
    ids = np.unique(g.u.to_numpy())
    return np.union1d(users, ids[distances(m > 0, np.searchsorted(ids, own)) <= 2 * r])


def matrix(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weights, and the row and column of each edge."""
    users, a = np.unique(u, return_inverse=True)
    items, b = np.unique(v, return_inverse=True)
    m = np.zeros((len(users), len(items)), np.int64)
    m[a, b] = w
    return m, a, b


def pair_sums(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Shared items and scores of all user pairs: min(a, b) adds up over weight levels."""
    def shared(mask: np.ndarray) -> np.ndarray:
        b = mask.astype(np.float64)  # exact below 2**53, and much faster than integer products
        return (b @ b.T).astype(np.int64)

    n = shared(w > 0)
    x, y = np.zeros_like(n), np.zeros_like(n)
    levels, before = np.unique(w[w > 0]), 0
    for level in levels.tolist():
        both = shared(w >= level)
        x += (level - before) * both
        y += (level * level - before * before) * both
        before = level
    score = (x * x - y) >> 1
    np.fill_diagonal(n, 0)
    np.fill_diagonal(score, 0)
    return n, score


def core(w: np.ndarray, k: int, sigma: int) -> np.ndarray:
    """Mask of the edges of the core: rows and columns that are empty are left out of each round."""
    on = w > 0
    while True:
        rows, columns = np.flatnonzero(on.any(axis=1)), np.flatnonzero(on.any(axis=0))
        at = np.ix_(rows, columns)
        part = on[at]
        n, score = pair_sums(np.where(part, w[at], 0))
        good = np.maximum(n - 1, 0)
        if sigma > 0:
            good[score < sigma] = 0
        keep = part & ((good.astype(np.float64) @ part.astype(np.float64)) >= k)
        if keep.sum() == part.sum():
            return on
        on = np.zeros_like(on)
        on[at] = keep


def bitruss_numbers(w: np.ndarray) -> np.ndarray:
    """Bitruss number of each cell that holds an edge."""
    m = (w > 0).astype(np.float64)
    number = np.zeros(m.shape, np.int64)
    k = 0
    while m.any():
        n = m @ m.T
        np.fill_diagonal(n, 1)
        sup = (np.maximum(n - 1, 0) @ m) * m  # whole numbers far below 2**53
        live = m > 0
        k = max(k, int(sup[live].min()))
        gone = live & (sup <= k)
        number[gone] = k
        m[gone] = 0
    return number
