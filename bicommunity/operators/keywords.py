"""Keyword bit vectors as arrays of 32-bit words held in longs."""

from __future__ import annotations

import hashlib
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD_BITS = 32


def bit_of(kw: str, bits: int = 256) -> int:
    return int(hashlib.md5(kw.encode()).hexdigest()[:8], 16) % bits


def query_vector(keywords: Iterable[str], bits: int = 256) -> list[int]:
    """The query's bit vector, as words."""
    words = [0] * (bits // WORD_BITS)
    for kw in keywords:
        b = bit_of(kw, bits)
        words[b // WORD_BITS] |= 1 << (b % WORD_BITS)
    return words


def bit_column(kw: Column, bits: int = 256) -> Column:
    return F.pmod(F.conv(F.substring(F.md5(kw), 1, 8), 16, 10).cast("bigint"), F.lit(bits))


def or_words(column: str, bits: int) -> Column:
    """Aggregate: bitwise or, word by word."""
    return F.array(*[F.coalesce(F.bit_or(F.col(column)[i]), F.lit(0).cast("bigint")) for i in range(bits // WORD_BITS)])


def bit_vectors(item_kw: DataFrame, bits: int = 256) -> DataFrame:
    """``v, bv`` of each item that has a keyword."""
    b = bit_column(F.col("kw"), bits)
    one = item_kw.select("v", F.expr("1L").alias("one"), F.floor(b / WORD_BITS).cast("int").alias("word"), (b % WORD_BITS).cast("int").alias("at"))
    mask = one.select("v", "word", F.call_function("shiftleft", F.col("one"), F.col("at")).alias("m"))
    return mask.groupBy("v").agg(F.array(*[F.coalesce(F.bit_or(F.when(F.col("word") == i, F.col("m"))), F.lit(0).cast("bigint")) for i in range(bits // WORD_BITS)]).alias("bv"))


def bitmaps(item_kw: DataFrame) -> DataFrame:
    """``v, bucket, bitmap``: exact sets over a keyword dictionary, without hash collisions.

    The dictionary is numbered by first arrival in sorted order within hash shards."""
    from ..store import written

    words = item_kw.select("kw").distinct().repartitionByRange("kw").withColumn("part", F.spark_partition_id())
    words = written(words, "dictionary")
    from pyspark.sql import Window

    own = words.withColumn("own", F.row_number().over(Window.partitionBy("part").orderBy("kw")))
    sizes = words.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    numbered = own.join(F.broadcast(before), "part").select("kw", (F.col("own") + F.col("before") - 1).alias("id"))
    return item_kw.join(numbered, "kw").groupBy("v", F.bitmap_bucket_number("id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("id")).alias("bitmap"))


def overlaps(bv: Column, words: list[int]) -> Column:
    """Does a vector share a bit with the query's? An empty query matches all."""
    if not any(words):
        return F.lit(True)
    hits = [bv[i].bitwiseAND(F.lit(w)) != 0 for i, w in enumerate(words) if w]
    out = hits[0]
    for h in hits[1:]:
        out = out | h
    return F.coalesce(out, F.lit(False))


def fill_factor(vectors: DataFrame, bits: int = 256, column: str = "bv") -> DataFrame:
    """Mean share of set bits: near 1 the keyword test on vectors prunes nothing."""
    ones = F.aggregate(column, F.lit(0), lambda a, x: a + F.bit_count(x))
    return vectors.agg((F.avg(ones) / bits).alias("fill"))
