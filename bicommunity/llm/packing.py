"""Length buckets of least padding, and token-budget batches inside each bucket."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .mixing import word_count
from .store import written

MAX_LENGTH = 2048
BUCKETS = 16
TOKEN_BUDGET = 65_536
#: Sequences a bucket's shard holds on average at most.
SHARD_ROWS = 16_384


def best_boundaries(histogram: dict[int, int], n_buckets: int) -> list[int]:
    """Upper ends of at most ``n_buckets`` length ranges with the least padding.

    Dynamic programming over the distinct lengths: the cheapest way to cover the first j
    lengths with b buckets extends the cheapest way to cover some i < j with b - 1.
    Among equal ways, the one with the fewest buckets.
    """
    lengths = np.array(sorted(histogram), np.int64)
    if not len(lengths):
        return []
    counts = np.array([histogram[x] for x in lengths.tolist()], np.int64)
    n = np.r_[0, np.cumsum(counts)]
    mass = np.r_[0, np.cumsum(counts * lengths)]
    size = len(lengths)
    never = np.iinfo(np.int64).max // 4
    cost = np.full(size + 1, never, np.int64)
    cost[0] = 0
    choices, bests = [], []
    for _ in range(min(n_buckets, size)):
        new, choice = np.full(size + 1, never, np.int64), np.zeros(size + 1, np.int64)
        for j in range(1, size + 1):
            ways = cost[:j] + lengths[j - 1] * (n[j] - n[:j]) - (mass[j] - mass[:j])
            choice[j] = int(np.argmin(ways))
            new[j] = ways[choice[j]]
        cost = new
        choices.append(choice)
        bests.append(int(cost[size]))
    b, j, ends = int(np.argmin(bests)), size, []
    while j > 0:
        ends.append(int(lengths[j - 1]))
        j = int(choices[b][j])
        b -= 1
    return ends[::-1]


def pack(docs: DataFrame, text: str = "text", max_length: int = MAX_LENGTH, n_buckets: int = BUCKETS, token_budget: int = TOKEN_BUDGET, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """``doc_id, piece, start, length, bucket, padded_length, batch, slot``.

    A text of more than ``max_length`` words is cut into pieces of that length and a
    rest, so every word is in one piece. Boundaries come from the histogram of all pieces'
    lengths, which has at most ``max_length`` rows whatever the input. A batch of
    a bucket has as many sequences as fit ``token_budget`` at the bucket's padded
    length (one at least); only a bucket's last batch can have fewer. Texts without words (null, blank)
    keep one row of length 0 with no bucket. Repeated rows are packed each; an empty table
    gives an empty result.

    A bucket can hold any share of all rows: its rows are dealt by hash to shards of
    bounded size, ranked there, and moved up by the number of rows in the shards before.
    """
    lengths = docs.select(F.col("doc_id").cast("long").alias("doc_id"), word_count(F.col(text)).alias("n"))
    pieces = lengths.select("doc_id", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0).cast("long"), F.expr(f"(n - 1) div {max_length}")))).alias("piece"))
    pieces = written(pieces.select("doc_id", "piece", (F.col("piece") * max_length).alias("start"), F.least(F.lit(max_length).cast("long"), F.col("n") - F.col("piece") * max_length).alias("length")), "pieces")
    histogram = {r.length: r.n for r in pieces.filter("length > 0").groupBy("length").agg(F.count("*").alias("n")).collect()}
    ends = best_boundaries(histogram, n_buckets)
    shards = max(1, -(-sum(histogram.values()) // shard_rows))
    if not ends:
        return pieces.select("*", *[F.lit(None).cast(t).alias(c) for c, t in (("bucket", "int"), ("padded_length", "long"), ("batch", "long"), ("slot", "long"))])
    bounds = F.array(*[F.lit(e).cast("long") for e in ends])
    placed = pieces.filter("length > 0").withColumn("bucket", F.size(F.filter(bounds, lambda b: b < F.col("length")))).withColumn("padded_length", F.element_at(bounds, F.col("bucket") + 1))
    placed = placed.withColumn("order", F.xxhash64("doc_id", "piece")).withColumn("shard", F.expr(f"pmod(order, {shards})"))
    before = placed.groupBy("bucket", "shard").agg(F.count("*").alias("n"))
    before = before.select("bucket", "shard", (F.sum("n").over(Window.partitionBy("bucket").orderBy("shard")) - F.col("n")).alias("before"))
    own = F.row_number().over(Window.partitionBy("bucket", "shard").orderBy("order", "doc_id", "piece")) - 1
    ranked = placed.withColumn("own", own).join(before, ["bucket", "shard"]).withColumn("rank", F.col("own") + F.col("before"))
    room = F.greatest(F.lit(1).cast("long"), F.expr(f"{token_budget} div padded_length"))
    packed = ranked.withColumn("room", room).select("doc_id", "piece", "start", "length", "bucket", "padded_length", F.expr("rank div room").alias("batch"), F.expr("rank % room").alias("slot"))
    blank = pieces.filter("length = 0").select("*", F.lit(None).cast("int").alias("bucket"), F.lit(None).cast("long").alias("padded_length"), F.lit(None).cast("long").alias("batch"), F.lit(None).cast("long").alias("slot"))
    return packed.unionByName(blank)
