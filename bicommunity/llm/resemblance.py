"""Near-duplicates: SimHash fingerprints propose pairs, min-hash bands those that fingerprints miss, and the shingle
sets decide."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .components import connected_components
from .store import Scratch, written
from .textkern import slices

SEED = 42
SHINGLE = 5
#: Least share of common shingles, as a fraction.
AT_LEAST = (4, 5)
#: A pair of resemblance s shares a band with probability 1 - (1 - s^ROWS)^BANDS: 0.9996 at 0.8.
BANDS, ROWS = 20, 5
#: Shingles that meet all hash functions at once.
CHUNK = 2048
#: Members of a block, two of which are compared at once.
BLOCK = 256

_rng = np.random.default_rng(SEED)
_A, _B, _MIX = (_rng.integers(0, 1 << 63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1) for _ in range(3))


def shingles(text: bytes | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of one text (UTF-8). A shorter text is one shingle; no word: none."""
    words = text.lower().split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    joined = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(words[i:] for i in range(shingle))))
    return np.unique(np.array(list(map(xxhash.xxh3_64_intdigest, joined, repeat(SEED))), np.uint64))


def node_of(hashes: np.ndarray) -> int:
    """64 bits that stand for a whole shingle set."""
    return int(np.uint64(xxhash.xxh3_64_intdigest(hashes.tobytes(), SEED)).view(np.int64))


def buckets(hashes: np.ndarray) -> np.ndarray:
    """One bucket per band; an empty set has none."""
    if not len(hashes):
        return np.empty(0, np.int64)
    low = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for i in range(0, len(hashes), CHUNK):
        low = np.minimum(low, (hashes[None, i : i + CHUNK] * _A[:, None] + _B[:, None]).min(axis=1))
    mixed = ((low ^ (low >> np.uint64(31))) * _MIX).reshape(BANDS, ROWS).sum(axis=1, dtype=np.uint64)
    return (mixed ^ (mixed >> np.uint64(29))).view(np.int64)


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    common = len(np.intersect1d(a, b, assume_unique=True))
    return common * AT_LEAST[1] >= (len(a) + len(b) - common) * AT_LEAST[0]


def signatures(docs: DataFrame) -> DataFrame:
    """``doc_id, tk, node, n, fp, buckets``: a row per input row; tk is a hash of the text, n the number of distinct shingles, fp
    the SimHash of all shingles, repeats included."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            sets = [shingles(t) for t in texts]
            fp = np.array([simhash.fingerprint(t, SHINGLE) for t in texts], np.uint64).view(np.int64)
            columns = [piece.column("doc_id"), piece.column("tk"), pa.array([node_of(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(fp), pa.array([buckets(s) for s in sets], pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "tk", "node", "n", "fp", "buckets"])

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("tk"), "text")
    return keyed.mapInArrow(run, "doc_id long, tk long, node long, n long, fp long, buckets array<long>")


def by_fingerprint(nodes: DataFrame, scratch: Scratch) -> DataFrame:
    """``a, n_a, b, n``: pairs of nodes whose fingerprints differ in at most ``simhash.MAX_BITS`` bits. A fingerprint stands for
    its smallest node, which meets its other ones and those that linked fingerprints stand for."""
    own = scratch.written(nodes.select("node", "n", F.explode("fps").alias("fp")), "of-fingerprints")
    stands = own.groupBy("fp").agg(F.min(F.struct("node", "n")).alias("c")).select("fp", F.col("c.node").alias("a"), F.col("c.n").alias("n_a"))
    stands = scratch.written(stands, "fingerprints")
    found = simhash.links(stands.select("fp")).toDF("fp_a", "fp_b").distinct()
    same = own.join(stands, "fp").select("a", "n_a", F.col("node").alias("b"), "n")
    near = found.join(stands.toDF("fp_a", "a", "n_a"), "fp_a").join(stands.toDF("fp_b", "b", "n"), "fp_b")
    # the smaller node first
    pairs = same.unionByName(near.select("a", "n_a", "b", "n")).filter("a <> b")
    return pairs.select(F.least("a", "b").alias("a"), F.when(F.col("a") < F.col("b"), F.col("n_a")).otherwise(F.col("n")).alias("n_a"), F.greatest("a", "b").alias("b"), F.when(F.col("a") < F.col("b"), F.col("n")).otherwise(F.col("n_a")).alias("n"))


def verified(pairs: DataFrame, nodes: DataFrame, docs: DataFrame) -> DataFrame:
    """``a, b``: the pairs of nodes whose shingle sets are alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, of_last = None, None
        for batch in batches:
            good = []
            for piece, theirs in slices([batch], "text_b"):
                a, b = piece.column("a").to_pylist(), piece.column("b").to_pylist()
                for x, y, text_a, text_b in zip(a, b, piece.column("text_a").cast(pa.binary()), theirs):
                    if x != last:
                        last, of_last = x, shingles(text_a.as_py())
                    of_b = shingles(text_b)
                    # an id with several texts brings all of them: only the node's own counts
                    if node_of(of_last) != x:
                        last = None
                    elif node_of(of_b) == y and alike(of_last, of_b):
                        good.append((x, y))
            yield pa.RecordBatch.from_arrays([pa.array([g[i] for g in good], pa.int64()) for i in (0, 1)], names=["a", "b"])

    ids = nodes.select("node", "first")
    named = pairs.join(ids.toDF("a", "id_a"), "a").join(ids.toDF("b", "id_b"), "b")
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    both = named.join(text.toDF("id_b", "text_b"), "id_b").join(text.toDF("id_a", "text_a"), "id_a")
    return both.select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long")


def spanning(cell: pa.Table) -> pa.Table:
    """``a, b``: links that span the groups of alike nodes among the rows (node, text) of one cell."""
    sets = {}
    for node, text in zip(cell.column("node").to_pylist(), cell.column("text").cast(pa.binary())):
        if node not in sets:
            found = shingles(text.as_py())
            # an id with several texts brings all of them: only the node's own counts
            if node_of(found) == node:
                sets[node] = found
    nodes, n = list(sets), len(sets)
    out = []
    if n > 1:
        sizes = np.array([len(sets[x]) for x in nodes])
        names, place = np.unique(np.concatenate([sets[x] for x in nodes]), return_inverse=True)
        owner = np.repeat(np.arange(n), sizes)[np.argsort(place, kind="stable")]
        posts = np.split(owner, np.cumsum(np.bincount(place, minlength=len(names)))[:-1])
        root = np.arange(n)
        for i, mine in enumerate(np.split(place, np.cumsum(sizes)[:-1])):
            common = np.bincount(np.concatenate([posts[p] for p in mine]), minlength=n)
            near = common * AT_LEAST[1] >= (sizes + sizes[i] - common) * AT_LEAST[0]
            for j in np.flatnonzero(near & (root != root[i])):
                if root[j] != root[i]:
                    out.append((nodes[i], nodes[j]))
                    root[root == root[j]] = root[i]
    return pa.table({"a": pa.array([x[0] for x in out], pa.int64()), "b": pa.array([x[1] for x in out], pa.int64())})


def links(nodes: DataFrame, docs: DataFrame, scratch: Scratch) -> DataFrame:
    """``a, b``: alike nodes; they span every group that the buckets show.

    First the pairs by fingerprint are compared, and each node of a bucket with the smallest one. Where a bucket of three or
    more still holds several groups, all its members are compared in cells of two blocks,
    and a cell hands on only links that span its groups. So rows stay near a
    bucket's size, and no pair that could join two groups is left out.
    """
    at_least = AT_LEAST[0] / AT_LEAST[1]
    sized = F.least("n", "n_a") >= F.greatest("n", "n_a") * F.lit(at_least - 1e-9)
    member = scratch.written(nodes.select("node", "n", F.explode("buckets").alias("bucket")), "buckets")
    centre = member.groupBy("bucket").agg(F.min(F.struct("node", "n")).alias("c"), F.count("*").alias("size")).filter("size > 1")
    shared = scratch.written(member.join(centre.select("bucket", "size", F.col("c.node").alias("a"), F.col("c.n").alias("n_a")), "bucket"), "shared")
    first = shared.filter("node <> a").select("a", "n_a", F.col("node").alias("b"), "n").unionByName(by_fingerprint(nodes, scratch))
    first = first.filter(sized).select("a", "b").distinct()
    found = scratch.written(verified(first, nodes, docs), "links")
    grouped = shared.filter("size > 2").join(connected_components(found), "node", "left").withColumn("root", F.coalesce("root", "node"))
    mixed = grouped.groupBy("bucket").agg(F.max("size").alias("size"), F.min("root").alias("low"), F.max("root").alias("high"), F.min("node").alias("least"), F.expr("bit_xor(xxhash64(node))").alias("members")).filter("low <> high")
    # bands that show the same members are looked at once
    once = scratch.written(mixed.groupBy("members", "least", "size").agg(F.min("bucket").alias("bucket")).select("bucket", F.ceil(F.col("size") / BLOCK).alias("blocks")), "mixed")
    own = F.pmod(F.xxhash64("node"), F.col("blocks"))
    cells = member.join(once, "bucket").withColumn("own", own).select("node", "bucket", "own", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    cells = cells.select("node", "bucket", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
    text = docs.select(F.col("doc_id").cast("long").alias("first"), "text")
    told = cells.join(nodes.select("node", "first"), "node").join(text, "first").select("bucket", "i", "j", "node", "text")
    return found.unionByName(told.groupBy("bucket", "i", "j").applyInArrow(lambda cell: spanning(cell), "a long, b long"))


def groups(docs: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, tk, component_id, first_tk``: a row per input row; component_id is the smallest doc_id
    reachable over pairs that are alike, and first_tk the hash of its text. Equal shingle sets are one node, so copies cost nothing beyond
    their signature; texts without a word are one group; rows without a doc_id have no group unless another is like them."""
    scratch = scratch or Scratch(docs.sparkSession, "near-copies")
    rows = scratch.written(signatures(docs), "signatures")
    least = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "tk"))).alias("least")
    nodes = scratch.written(rows.groupBy("node").agg(least, F.first("n").alias("n"), F.collect_set("fp").alias("fps"), F.first("buckets").alias("buckets")).withColumn("first", F.col("least.doc_id")), "nodes")
    named_nodes = nodes.filter("first is not null")
    roots = connected_components(scratch.written(links(named_nodes, docs, scratch), "all-links"))
    named = nodes.join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "least")
    lowest = named.groupBy("root").agg(F.min("least").alias("least"))
    classes = named.join(lowest.withColumnRenamed("least", "of_group"), "root").select("node", "of_group")
    return rows.join(classes, "node").select("doc_id", "tk", F.col("of_group.doc_id").alias("component_id"), F.col("of_group.tk").alias("first_tk"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each group: that of the smallest doc_id (of several texts with that doc_id, the one of the smallest
    hash; of rows that repeat both, any one). A row with no doc_id stays. All columns are handed on as they are, whatever
    their names; an empty table gives an empty result."""
    scratch = Scratch(docs.sparkSession, "near-copies")
    found = scratch.written(groups(docs, scratch).filter("doc_id is not null"), "groups")
    own = found.groupBy("doc_id", "tk").agg(F.count("*").alias("n"), F.max((F.col("doc_id") == F.col("component_id")) & (F.col("tk") == F.col("first_tk"))).alias("stays"))
    own = written(own.filter("not stays or n > 1"), "not-as-they-are")
    scratch.clear()
    row = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("tk"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    kept = row.join(own, ["doc_id", "tk"], "left_anti")
    again = own.filter("stays").select("doc_id", "tk")
    if again.limit(1).count():
        kept = kept.unionByName(row.join(again, ["doc_id", "tk"], "left_semi").dropDuplicates(["doc_id", "tk"]))
    return kept.select("row.*")
