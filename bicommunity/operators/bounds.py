"""Supports and best scores of all edges without a table of wedges: by lists of users, or by products of matrices."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import release, remove, shared_dir, written
from . import dense

#: Meetings (an edge with another user of its item) that a kernel works on at once, and list entries that one batch hands over.
CALL, BATCH = 1 << 21, 1 << 26
#: Meetings in a product of matrices that take as long as one that is added up on its own.
SCATTER = 64
SCHEMA = "u bigint, v string, w bigint, sup bigint, best bigint"


def edge_bounds(edges: DataFrame, sigma: int = 0, engine: str = "auto", call: int = CALL, batch: int = BATCH) -> DataFrame:
    """``u, v, w, sup, best`` for every edge: its butterflies, and the greatest score of its user with another
    user of its item (0 if there is none). With ``sigma``, only butterflies of pairs that score it count.

    ``lists`` cuts the users into ranges of about ``call`` meetings, sends each range the users of its items, once an item, and counts a
    user's pairs where they meet; ranges go in as many batches as keep the entries of one below ``batch``, and a batch's shuffle
    files go before the next. ``matrix`` takes a graph whose matrix fits; ``auto`` takes it where the graph is dense enough to gain by it.
    """
    size = dense.measured(edges)
    if engine != "lists":
        m = dense.fetch(edges, size) if engine == "matrix" or size.meet > dense.DENSE * size.n else None
        if m is not None and (engine == "matrix" or len(np.unique(m.w)) <= dense.MAX_LEVELS):
            return written(_by_matrix(edges.sparkSession, m, sigma), "bounds")
        if engine == "matrix":
            raise ValueError("the graph's matrix doesn't fit")
    return _by_lists(edges, sigma, size.meet, call, batch)


def _by_lists(edges: DataFrame, sigma: int, volume: int, call: int, batch: int) -> DataFrame:
    spark = edges.sparkSession
    groups = -(-volume // call) or 1
    shares = [i / groups for i in range(1, groups)] or [1.0]
    seen = edges.agg(F.percentile_approx("u", shares).alias("ends"), F.max(F.greatest(F.abs("u"), "w")).alias("most")).first()
    ends = np.unique(np.array(seen.ends or [], np.int64))  # the last user of each range but the last one
    kind = "int" if (seen.most or 0) < 1 << 31 else "bigint"
    at = f"{shared_dir(spark)}/lists-{uuid.uuid4().hex}"
    pair = F.collect_list(F.struct(F.col("u").cast(kind).alias("u"), F.col("w").cast(kind).alias("w"))).alias("p")
    edges.groupBy("v").agg(pair).select("v", F.col("p.u").alias("us"), F.col("p.w").alias("ws")).write.parquet(at)
    lists = spark.read.parquet(at)
    sizes = lists.mapInArrow(lambda x: _sizes(x, ends), "g int, n bigint").groupBy("g").agg(F.sum("n").alias("n")).collect()
    of, full = np.zeros(len(ends) + 1, np.int32), 0
    for g, n in sorted(sizes):
        full += n
        of[g] = full // batch
    path = f"{shared_dir(spark)}/bounds-{uuid.uuid4().hex}"
    batches = np.unique(of[[r.g for r in sizes]]).tolist() or [0]
    for i in batches:
        sent = lists.mapInArrow(lambda x, i=i: _spread(x, ends, of == i), f"g int, v string, us array<{kind}>, ws array<{kind}>")
        sent.groupBy("g").applyInArrow(lambda cell: _bounds_of(cell, ends, sigma, call), SCHEMA).write.mode("append").parquet(path)
        del sent
        if len(batches) > 1:
            release(spark)
    remove(spark, at)
    return spark.read.schema(SCHEMA).parquet(path)


def _flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Sizes of the lists of a column, and their values one after the other."""
    return column.value_lengths().to_numpy(zero_copy_only=False), column.flatten().to_numpy(zero_copy_only=False)


def _calls(us: pa.Array, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``row, range`` once for each range that has users of a list, and the size of each list."""
    size, u = _flat(us)
    code = np.unique(np.repeat(np.arange(len(size)), size) * (len(ends) + 1) + np.searchsorted(ends, u))
    return *np.divmod(code, len(ends) + 1), size


def _sizes(batches: Iterator[pa.RecordBatch], ends: np.ndarray) -> Iterator[pa.RecordBatch]:
    total = np.zeros(len(ends) + 1, np.int64)
    for batch in batches:
        row, g, size = _calls(batch.column("us"), ends)
        total += np.bincount(g, size[row], len(total)).astype(np.int64)
    g = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(g, pa.int32()), pa.array(total[g])], names=["g", "n"])


def _spread(batches: Iterator[pa.RecordBatch], ends: np.ndarray, now: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Each list for each of the present ranges that has users of it, in pieces of bounded size."""
    for batch in batches:
        row, g, size = _calls(batch.column("us"), ends)
        row, g = row[now[g]], g[now[g]]
        piece = np.cumsum(size[row]) // CALL
        for lo, hi in pairwise([0, *(np.flatnonzero(np.diff(piece)) + 1).tolist(), len(row)]):
            if hi > lo:
                part = batch.take(pa.array(row[lo:hi]))
                yield pa.RecordBatch.from_arrays([pa.array(g[lo:hi], pa.int32()), *part.columns], names=["g", "v", "us", "ws"])


def _bounds_of(cell: pa.Table, ends: np.ndarray, sigma: int, call: int) -> pa.Table:
    """Bounds of all edges of a range's users, from the lists of its items; so many users at a time that few meetings are held."""
    cell = cell.combine_chunks()
    (size, other), (_, weight) = (_flat(cell.column(c).combine_chunks()) for c in ("us", "ws"))
    other, weight = other.astype(np.int64), weight.astype(np.int64)
    first = np.cumsum(size) - size
    own = np.flatnonzero(np.searchsorted(ends, other) == cell.column("g")[0].as_py())
    own = own[np.argsort(other[own], kind="stable")]
    u, w = other[own], weight[own]
    row = np.repeat(np.arange(len(size)), size)[own]
    sup, best = np.zeros(len(u), np.int64), np.zeros(len(u), np.int64)
    starts = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
    held = np.add.reduceat(size[row], starts)
    lo = 0
    while lo < len(starts):
        hi = lo + max(1, int(np.searchsorted(np.cumsum(held[lo:]), call, "right")))
        part = slice(starts[lo], starts[hi] if hi < len(starts) else len(u))
        n = size[row[part]]
        at = np.arange(n.sum()) + np.repeat(first[row[part]] - np.cumsum(n) + n, n)
        sup[part], best[part] = _count(u[part], w[part], n, other[at], weight[at], sigma)
        lo = hi
    v = cell.column("v").combine_chunks().take(pa.array(row)).cast(pa.string())
    return pa.table({"u": pa.array(u), "v": v, "w": pa.array(w), "sup": pa.array(sup), "best": pa.array(best)})


def _count(u: np.ndarray, w: np.ndarray, size: np.ndarray, other: np.ndarray, weight: np.ndarray, sigma: int) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of all edges of some users, each edge with the users of its item."""
    own = np.repeat(np.arange(len(size)), size)
    real = other != u[own]
    own, other = own[real], other[real]
    wm = np.minimum(weight[real], w[own])
    sup, best = np.zeros(len(u), np.int64), np.zeros(len(u), np.int64)
    if len(own):
        mine = np.unique(u, return_inverse=True)[1][own]
        ids, theirs = np.unique(other, return_inverse=True)
        code = mine * len(ids) + theirs
        order = np.argsort(code, kind="stable")
        code = code[order]
        start = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]]))
        n = np.diff(np.append(start, len(code)))
        x, y = np.add.reduceat(wm[order], start), np.add.reduceat(wm[order] ** 2, start)
        pair = np.empty(len(code), np.int64)
        pair[order] = np.repeat(np.arange(len(start)), n)
        first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        score = (x * x - y) >> 1
        sup[own[first]] = np.add.reduceat(np.where(score >= sigma, n - 1, 0)[pair], first)
        best[own[first]] = np.maximum.reduceat(score[pair], first)
    return sup, best


def _by_matrix(spark, m: dense.Fetched, sigma: int) -> DataFrame:
    shared = spark.sparkContext.broadcast(m)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = shared.value
        kind = np.float32 if g.exact_in_float32() else np.float64
        wide = np.float32 if kind is np.float32 and np.bincount(g.a, g.w).max(initial=0) ** 2 < 1 << 24 else np.float64
        order = np.lexsort((g.b, g.a))
        row, column, weight = g.a[order], g.b[order], g.w[order]
        has = np.zeros((len(g.users), len(g.items)), kind)
        has[row, column] = 1
        others = None if sigma > 0 else dense.item_pairs(has)
        items = pa.array(g.items, pa.string())

        def users_of(t: int) -> list[np.ndarray]:
            on = np.flatnonzero(weight >= t)
            on = on[np.argsort(column[on], kind="stable")]
            return np.split(row[on], np.searchsorted(column[on], np.arange(1, len(g.items))))

        levels = []  # from, weight gained, square gained, users of each item, their matrix if many
        before = 0
        for t in np.unique(weight).tolist():
            of = users_of(t)
            many = before and SCATTER * sum(len(x) ** 2 for x in of) > len(has) ** 2 * len(of)
            levels.append((t - before, t * t - before * before, of, (g.matrix(kind) >= t).astype(kind) if many else None))
            before = t
        for lo in (x for batch in batches for x in batch.column(0).to_pylist()):
            hi = min(lo + g.block, len(has))
            for dx, dy, of, on in levels:
                if of is levels[0][2]:
                    n = has[lo:hi] @ has.T
                    x, y = kind(dx) * n, kind(dy) * n
                elif on is not None:
                    both = on[lo:hi] @ on.T
                    x += kind(dx) * both
                    y += kind(dy) * both
                else:
                    for users in of:
                        own = slice(*np.searchsorted(users, [lo, hi]))
                        if own.stop > own.start:
                            at = np.ix_(users[own] - lo, users)
                            x[at] += kind(dx)
                            y[at] += kind(dy)
            s = x.astype(wide, copy=False)
            s = (s * s - y) / wide(2)
            here = np.arange(hi - lo)
            s[here, lo + here] = 0
            if others is None:
                n = np.where((n > 0) & (s >= sigma), n - 1, 0).astype(np.float64)
                n[here, lo + here] = 0
                sup = n @ has
            else:
                sup = has[lo:hi].astype(np.float64) @ others
            best = np.zeros(sup.shape, np.int64)
            for i, users in enumerate(levels[0][2]):
                own = slice(*np.searchsorted(users, [lo, hi]))
                if own.stop > own.start:
                    best[users[own] - lo, i] = s[np.ix_(users[own] - lo, users)].max(axis=1)
            e = slice(*np.searchsorted(row, [lo, hi]))
            at = row[e] - lo, column[e]
            yield pa.RecordBatch.from_arrays([pa.array(g.users[row[e]]), items.take(pa.array(column[e])), pa.array(weight[e]), pa.array(np.rint(sup[at]).astype(np.int64)), pa.array(best[at])], names=["u", "v", "w", "sup", "best"])

    return m.blocks(spark).mapInArrow(run, SCHEMA)
