"""Approximate nearest neighbours: p-stable hashing with query-directed probing."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .store import written

TABLES = 4
#: Hash functions of a table and buckets a query visits in it. Recall doesn't depend on the number of rows.
FUNCTIONS, PROBES = 8, 90
#: Width of a cell, in standard deviations of a projection.
WIDTH = 2.5
#: Vectors the cell width is fitted on: those with the smallest hash of their id.
FIT_ROWS = 2000
#: Vectors of a bucket, and queries that visit it, that meet in one cell on average.
CHUNK, BLOCK = 2048, 512
#: Queries whose results a task holds before it hands them on.
HELD = 20_000


def probe_order(inside: np.ndarray, n: int) -> np.ndarray:
    """The ``n`` likeliest shifts of a hash, best first (shifts of -1, 0, 1 by
    function). ``inside``: where the query lies in its cell, in [0, 1).

    A shift's score is the sum of squared distances to the boundaries that it crosses. Sets
    of crossings come off a heap: each makes two more, by moving its last crossing on to the
    next nearest boundary, and by adding that one.
    """
    k = len(inside)
    dist = np.r_[inside, 1.0 - inside] ** 2
    order = np.argsort(dist, kind="stable")
    cost, function, sign = dist[order].tolist(), (order % k).tolist(), np.where(order < k, -1, 1).tolist()
    out, heap = [[0] * k], [(cost[0], (0,))]
    while heap and len(out) < n:
        score, crossed = heapq.heappop(heap)
        functions = [function[j] for j in crossed]
        if len(set(functions)) == len(functions):
            shift = [0] * k
            for j in crossed:
                shift[function[j]] = sign[j]
            out.append(shift)
        last = crossed[-1]
        if last + 1 < 2 * k:
            heapq.heappush(heap, (score - cost[last] + cost[last + 1], (*crossed[:-1], last + 1)))
            heapq.heappush(heap, (score + cost[last + 1], (*crossed, last + 1)))
    return np.array(out, np.int64)


class _Hashes:
    def __init__(self, dim: int, functions: int, width: float, seed: int):
        rng = np.random.default_rng(seed)
        self.planes = rng.standard_normal((TABLES, dim, functions))
        self.offsets = rng.uniform(0, width, (TABLES, functions))
        self.width = width
        self.mix = rng.integers(1, 1 << 62, functions, dtype=np.int64) * 2 + 1

    def place(self, x: np.ndarray, table: int) -> np.ndarray:
        return (x @ self.planes[table] + self.offsets[table]) / self.width

    def bucket(self, cells: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            h = (cells.astype(np.int64) * self.mix).sum(axis=-1)
            return h ^ (h >> np.int64(31))


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(-1, dim)


def _rows(name: str, ids: np.ndarray, table: int, bucket: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
    vec = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.ravel()))
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), table, np.int32)), pa.array(bucket), pa.array(ids), vec], names=["tbl", "bucket", name, "vec"])


def _nearest(rows: DataFrame, dim: int, keep: int) -> DataFrame:
    """``rows`` (tbl, bucket, chunk, block, probe, id, vec; vectors of a cell before its
    queries) -> ``query, id, d2``: the nearest ``keep`` of each query that a task saw."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        key, ids, vecs = None, [], []

        def handed() -> Iterator[pa.RecordBatch]:
            if held:
                q = np.repeat(np.fromiter(held, np.int64, len(held)), [len(d) for d, _ in held.values()])
                yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(np.concatenate([i for _, i in held.values()])), pa.array(np.concatenate([d for d, _ in held.values()]))], names=["query", "id", "d2"])
                held.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            tbl, bucket, chunk, block, probe, own = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(6))
            x = _matrix(batch.column(6), dim)
            cut = np.flatnonzero((tbl[1:] != tbl[:-1]) | (bucket[1:] != bucket[:-1]) | (chunk[1:] != chunk[:-1]) | (block[1:] != block[:-1]) | (probe[1:] != probe[:-1])) + 1
            for a, b in zip(np.r_[0, cut], np.r_[cut, batch.num_rows]):
                if (now := (tbl[a], bucket[a], chunk[a], block[a])) != key:
                    key, ids, vecs = now, [], []
                if not probe[a]:
                    ids.append(own[a:b])
                    vecs.append(x[a:b])
                    continue
                if not ids:
                    continue
                if len(ids) > 1:
                    ids, vecs = [np.concatenate(ids)], [np.concatenate(vecs)]
                at = max(1, (1 << 20) // vecs[0].size)
                for lo in range(a, b, at):
                    d2 = ((x[lo : min(b, lo + at), None, :] - vecs[0][None]) ** 2).sum(axis=2)
                    for i, d in enumerate(d2):
                        near = np.arange(len(d))
                        if len(d) > keep:
                            near = np.flatnonzero(d <= np.partition(d, keep - 1)[keep - 1])
                        d, n = d[near], ids[0][near]
                        if (q := int(own[lo + i])) in held:
                            d, n = np.r_[held[q][0], d], np.r_[held[q][1], n]
                            n, first = np.unique(n, return_index=True)
                            d = d[first]
                        best = np.lexsort((n, d))[:keep]
                        held[q] = d[best], n[best]
                if len(held) > HELD:
                    yield from handed()
        yield from handed()

    cell = ["tbl", "bucket", "chunk", "block"]
    ready = rows.repartition(*cell).sortWithinPartitions(*cell, "probe")
    return ready.select(*cell, "probe", "id", "vec").mapInArrow(run, "query long, id long, d2 double")


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, seed: int = 42, functions: int = FUNCTIONS, probes: int = PROBES, chunk: int = CHUNK, block: int = BLOCK) -> DataFrame:
    """``query_id, rank, vec_id, score`` for tables of ``vec_id, embedding``.

    Distinct vectors are searched, so copies cost one search: a class of equal vectors is
    one point with its k + 1 smallest ids. Every vector is in a bucket of each table; a query visits its
    own and the likeliest neighbouring buckets. A bucket's vectors and its queries are dealt to a grid of cells of bounded size,
    so neither a hot bucket nor a much-asked one falls to one task, and exact
    distances are taken in double precision. Queries that find too few points search all
    chunks. ``functions`` and ``probes`` set recall and work: more functions make smaller buckets, of which more are to be
    probed. Vectors that are null, zero, hold a null or a value that isn't finite, or whose
    length isn't the commonest one (the greatest, among equals) take no part. Ties go to the smaller
    vec_id; repeated query ids are asked once; empty tables give an empty result.
    """
    spark = vectors.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")

    def usable(df: DataFrame) -> DataFrame:
        v = df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("vec"))
        odd = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
        return v.filter(F.col("vec_id").isNotNull() & F.col("vec").isNotNull() & ~F.coalesce(odd, F.lit(True)) & F.exists("vec", lambda x: x != 0)).withColumn("vec", F.transform("vec", lambda x: x + F.lit(0.0)))

    sizes = usable(vectors).groupBy(F.size("vec").alias("dim")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), F.desc("dim")).first()
    if sizes is None:
        return empty
    dim = sizes.dim
    points = usable(vectors).filter(F.size("vec") == dim)
    few = points.distinct().withColumn("nth", F.row_number().over(Window.partitionBy("vec").orderBy("vec_id"))).filter(F.col("nth") <= k + 1)
    classes = written(few.groupBy("vec").agg(F.min("vec_id").alias("id"), F.sort_array(F.collect_list("vec_id")).alias("members")), "classes")
    asked = written(usable(queries).filter(F.size("vec") == dim).distinct().join(classes, "vec").select(F.col("vec_id").alias("query_id"), "id"), "asked")
    base = classes.select("id", "vec")
    wanted = base.join(asked.select("id").distinct(), "id", "left_semi")

    n = classes.count()
    sample = np.array([r.vec for r in base.orderBy(F.xxhash64("id"), "id").limit(FIT_ROWS).collect()], np.float64)
    spread = float(np.sqrt(((sample - sample.mean(axis=0)) ** 2).sum(axis=1).mean())) or float(np.abs(sample).max())
    hashes = _Hashes(dim, functions, WIDTH * spread, seed)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, x = batch.column(0).to_numpy(), _matrix(batch.column(1), dim)
            for t in range(TABLES):
                yield _rows("id", ids, t, hashes.bucket(np.floor(hashes.place(x, t))), x)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, x = batch.column(0).to_numpy(), _matrix(batch.column(1), dim)
            for t in range(TABLES):
                placed = hashes.place(x, t)
                cells = np.floor(placed)
                for i in range(len(ids)):
                    shifts = probe_order(placed[i] - cells[i], probes)
                    at = np.unique(hashes.bucket(cells[i] + shifts))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), t, np.int32)), pa.array(at), pa.array(np.full(len(at), ids[i]))], names=["tbl", "bucket", "id"])

    entries = base.mapInArrow(index, "tbl int, bucket long, id long, vec array<double>")
    sought = written(wanted.mapInArrow(ask, "tbl int, bucket long, id long"), "sought")
    asks = sought.groupBy("tbl", "bucket").agg(F.ceil(F.count("*") / block).alias("blocks"))
    buckets = written(entries.groupBy("tbl", "bucket").agg(F.ceil(F.count("*") / chunk).alias("chunks")).join(asks, ["tbl", "bucket"]), "buckets")

    def met(entries: DataFrame, sought: DataFrame, buckets: DataFrame) -> DataFrame:
        def every(n: str) -> Column:
            return F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))

        left = entries.join(buckets, ["tbl", "bucket"]).select("tbl", "bucket", F.expr("pmod(xxhash64(id), chunks)").alias("chunk"), every("blocks").alias("block"), F.lit(0).alias("probe"), "id", "vec")
        right = sought.join(buckets, ["tbl", "bucket"]).select("tbl", "bucket", every("chunks").alias("chunk"), F.expr("pmod(xxhash64(id, 1), blocks)").alias("block"), "id")
        right = right.join(wanted, "id").select("tbl", "bucket", "chunk", "block", F.lit(1).alias("probe"), "id", "vec")
        found = _nearest(left.unionByName(right), dim, k + 1).dropDuplicates(["query", "id"])
        nth = F.row_number().over(Window.partitionBy("query").orderBy("d2", "id"))
        return found.withColumn("nth", nth).filter(F.col("nth") <= k + 1).drop("nth")

    found = written(met(entries, sought, buckets), "found")
    enough = found.groupBy("query").agg(F.count("*").alias("n")).filter(F.col("n") >= min(k + 1, n)).select(F.col("query").alias("id"))
    short = written(wanted.join(enough, "id", "left_anti"), "short")
    if short.limit(1).count():
        chunks = max(1, -(-n // chunk))
        blocks = max(1, -(-short.count() // block))
        cells = spark.range(chunks).select(F.lit(0).alias("tbl"), F.col("id").alias("bucket"), F.lit(1).cast("long").alias("chunks"), F.lit(blocks).cast("long").alias("blocks"))
        everything = base.select(F.lit(0).alias("tbl"), F.expr(f"pmod(xxhash64(id), {chunks})").alias("bucket"), "id", "vec")
        everywhere = short.select(F.lit(0).alias("tbl"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(chunks - 1).cast("long"))).alias("bucket"), "id")
        rest = written(met(everything, everywhere, cells), "found-all")
        found = found.join(short.select(F.col("id").alias("query")), "query", "left_anti").unionByName(rest)
    named = found.join(classes.select("id", "members"), "id").select("query", F.sqrt("d2").alias("score"), F.explode("members").alias("vec_id"))
    nth = F.row_number().over(Window.partitionBy("query").orderBy("score", "vec_id"))
    lists = named.withColumn("nth", nth).filter(F.col("nth") <= k + 1).groupBy("query").agg(F.sort_array(F.collect_list(F.struct("score", "vec_id"))).alias("near"))
    own = asked.join(lists, asked["id"] == lists["query"]).select("query_id", F.slice(F.filter("near", lambda x: x["vec_id"] != F.col("query_id")), 1, k).alias("near"))
    return own.select("query_id", F.posexplode("near").alias("at", "x")).select("query_id", (F.col("at") + 1).alias("rank"), "x.vec_id", "x.score")
