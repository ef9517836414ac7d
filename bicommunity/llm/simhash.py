"""SimHash near-duplicates with multi-index hashing over two 32-bit halves."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .store import written
from .textkern import slices

SEED = 42
#: A pair within 3 bits is within 1 bit in one of the two halves.
MAX_BITS = 3
#: Distinct fingerprints that share a half; beyond it, pairs aren't compared one by one.
HOT_BUCKET = 2048


def fingerprint(text: bytes | None, shingle: int = 3) -> int:
    """Unsigned 64-bit majority fingerprint of one text (UTF-8); no word: 0."""
    words = text.lower().split() if text else []
    if not words:
        return 0
    joined = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(words[i:] for i in range(shingle))))
    hashes = np.array(list(map(xxhash.xxh64_intdigest, joined, repeat(SEED))), dtype=">u8")
    ones = np.unpackbits(hashes.view(np.uint8)).reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, text: str = "text", shingle: int = 3) -> DataFrame:
    """``doc_id, fp``: fp as a signed long. Null and blank texts get 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            fp = np.array([fingerprint(t, shingle) for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, fp long")


def _low(fp: Column) -> Column:
    return fp.bitwiseAND(F.lit(0xFFFFFFFF))


def _high(fp: Column) -> Column:
    return F.shiftrightunsigned(fp, 32)


def _ball(value: Column, radius: int) -> Column:
    """All 32-bit values at distance <= radius, as an array."""
    masks = [0] + [sum(1 << b for b in bits) for r in range(1, radius + 1) for bits in combinations(range(32), r)]
    return F.transform(F.array(*[F.lit(m) for m in masks]).cast("array<bigint>"), lambda m: value.bitwiseXOR(m))


def links(distinct_fps: DataFrame, hot_bucket: int = HOT_BUCKET) -> DataFrame:
    """``a, b``: pairs of distinct fingerprints at <= 3 bits that span every group.

    Each half of a fingerprint is a table. A fingerprint looks into both tables
    at its own half and at the halves one bit away (only towards a set bit: the
    partner of such a pair looks the same way up), and complete distances are
    verified in the join. In a bucket of more than ``hot_bucket`` fingerprints
    the pairs aren't enumerated: members meet at the points of small balls around their
    other half, and each is linked with the smallest member that is a verified
    partner of it. So work stays linear in such a bucket and no link between
    groups is lost.
    """
    fp = F.col("fp")
    table = distinct_fps.select("fp", F.explode(F.array(F.struct(F.lit(0).alias("half"), _high(fp).alias("value"), _low(fp).alias("rest")), F.struct(F.lit(1).alias("half"), _low(fp).alias("value"), _high(fp).alias("rest")))).alias("e")).select("fp", "e.*")
    value = F.col("value")
    flips = F.transform(F.filter(F.sequence(F.lit(0), F.lit(31)), lambda b: _bit(value, b) == 0), lambda b: value.bitwiseOR(_power(b)))
    probes = table.select("fp", "half", F.explode(flips).alias("value"), "rest")
    big = table.groupBy("half", "value").agg(F.count("*").alias("n")).filter(F.col("n") > hot_bucket).select("half", "value")
    big = written(big, "hot-buckets")
    hot = big.limit(1).count() > 0

    def usual(rows: DataFrame) -> DataFrame:
        return rows.join(big, ["half", "value"], "left_anti") if hot else rows

    t = usual(table).select(F.col("fp").alias("b"), "half", "value")
    distance = F.bit_count(F.col("a").bitwiseXOR(F.col("b")))
    same = usual(table).select(F.col("fp").alias("a"), "half", "value").join(t, ["half", "value"]).filter((F.col("a") < F.col("b")) & (distance <= MAX_BITS))
    near = usual(probes).select(F.col("fp").alias("a"), "half", "value").join(t, ["half", "value"]).filter(distance <= MAX_BITS)
    found = same.select("a", "b").unionByName(near.select("a", "b"))
    if hot:
        own = table.join(big, ["half", "value"], "left_semi")
        at = own.select("fp", "half", "value", F.explode(_ball(F.col("rest"), 2)).alias("point"), "rest", F.lit(True).alias("own"))
        at = at.unionByName(probes.join(big, ["half", "value"], "left_semi").select("fp", "half", "value", F.explode(_ball(F.col("rest"), 1)).alias("point"), "rest", F.lit(False).alias("own")))
        at = at.withColumn("far", F.bit_count(F.col("rest").bitwiseXOR(F.col("point"))))
        centre = at.filter("own and far <= 1").groupBy("half", "value", "point").agg(F.min("fp").alias("b"))
        found = found.unionByName(at.join(centre, ["half", "value", "point"]).filter("fp <> b").select(F.col("fp").alias("a"), "b").distinct())
    return found


def _bit(value: Column, b: Column) -> Column:
    return F.call_function("getbit", value, b)


def _power(b: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), b)


def near_duplicates(docs: DataFrame, text: str = "text", shingle: int = 3, hot_bucket: int = HOT_BUCKET) -> DataFrame:
    """``doc_id, fp, component_id``: one row per input row.

    Equal fingerprints are one node, so copies cost nothing beyond their
    fingerprint. component_id is the smallest doc_id reachable over links of at most 3
    bits. Null or blank texts share fingerprint 0 and link as any other; repeated
    rows each get a row; an empty table gives an empty result. Rows with a null
    doc_id keep a row whose component is that of their fingerprint.
    """
    fps = written(fingerprints(docs, text, shingle), "fingerprints")
    nodes = fps.groupBy("fp").agg(F.min("doc_id").alias("first"))
    roots = connected_components(written(links(nodes.select("fp"), hot_bucket), "links"))
    named = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "first")
    lowest = named.groupBy("root").agg(F.min("first").alias("component_id"))
    classes = named.join(lowest, "root").select("fp", "component_id")
    return fps.join(classes, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """Rows of ``docs`` that are the first of their group (smallest doc_id; a row
    with no doc_id stays)."""
    groups = near_duplicates(docs).filter("doc_id > component_id").select("doc_id").distinct()
    return docs.join(groups, "doc_id", "left_anti")
