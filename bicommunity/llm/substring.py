"""Exact removal of repeated word windows, with a log-structured index.

A document's windows of ``window`` words are represented by winnowed anchors: the
smallest hash among a window's sub-windows of about half its length. Equal windows have
equal anchors, so neighbouring windows with one anchor form a stretch, and only stretches whose
anchor occurs in several contexts need a comparison window by window. A context is the hash of all
words of a stretch.

The index of a corpus is a list of immutable runs. A run has two tables that are bucketed and
sorted: keys (part, anchor, context, doc_id) by part, which is the anchor (then left out) or, for rows of a hot
anchor, one of several hashes of it, and windows (anchor, context, doc_id, hashes of the
stretch's windows) by anchor and context. A batch is merge-joined with them bucket by
bucket: the runs are never exchanged, and no text of an earlier batch is read again. Matches
are verified with the hash of the whole window (128 bits with the anchor). The batch becomes a new run, and
runs are compacted into one.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import joins
from .store import release, remove, shared_dir
from .textkern import slices

WINDOW = 50
#: Runs that are merged into one as soon as so many stand side by side.
FAN_IN = 2
#: Batches that a table is cut into, by doc_id.
BATCHES = 3
#: Parts that the rows of a hot anchor are dealt to.
SPREAD = 64

_MIX = 0x9E3779B97F4A7C15
_BASES = (0xD6E8FEB86659FD93, 0xC2B2AE3D27D4EB4F)
_INVERSE = pow(_BASES[1], -1, 1 << 64)
#: Powers that a process remembers for each base.
_REMEMBERED = 1 << 16
_known_powers: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    """The first ``n`` powers of a base, modulo 2**64."""
    if n > _REMEMBERED:
        return np.cumprod(np.r_[np.uint64(1), np.full(n - 1, base, np.uint64)])
    if base not in _known_powers:
        _known_powers[base] = np.cumprod(np.r_[np.uint64(1), np.full(_REMEMBERED - 1, base, np.uint64)])
    return _known_powers[base][:n]


def _finish(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(_MIX)
    return h ^ (h >> np.uint64(29))


def _rolling(h: np.ndarray, length: int, base: int) -> np.ndarray:
    """Polynomial hashes of all runs of ``length`` values, by doubling."""
    parts, size, cur = [], 1, h
    while size <= length:
        if length & size:
            parts.append((size, cur))
        if size * 2 <= length:
            cur = cur[: len(cur) - size] * np.uint64(pow(base, size, 1 << 64)) + cur[size:]
        size *= 2
    total, out = 0, None
    for size, part in reversed(parts):
        if out is None:
            out, total = part, size
        else:
            n = min(len(out), len(part) - total)
            out = out[:n] * np.uint64(pow(base, size, 1 << 64)) + part[total : total + n]
            total += size
    return out


def _lowest(h: np.ndarray, length: int) -> np.ndarray:
    """Minimum of every ``length`` consecutive values."""
    size, cur = 1, h
    while size * 2 <= length:
        cur = np.minimum(cur[: len(cur) - size], cur[size:])
        size *= 2
    rest = length - size
    return np.minimum(cur[: len(cur) - rest], cur[rest:]) if rest else cur


class _Text:
    """Hashes of one text's windows; ``anchor[i]`` belongs to the window at word i."""

    def __init__(self, words: list[bytes], window: int):
        self.words, self.window = words, window
        self.hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
        gram = window // 2
        self.anchor = _lowest(_finish(_rolling(self.hashes, gram, _BASES[0])), window - gram + 1)

    def whole(self) -> np.ndarray:
        """Hash of each window."""
        return _finish(_rolling(self.hashes, self.window, _BASES[1]))

    def spans(self) -> tuple[np.ndarray, np.ndarray]:
        """First and last window of each stretch of windows with one anchor."""
        starts = np.flatnonzero(np.r_[True, self.anchor[1:] != self.anchor[:-1]])
        return starts, np.r_[starts[1:], len(self.anchor)] - 1

    def contexts(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Anchor, context hash and windows of each stretch. Two stretches with equal context
        have the same words from their first window's start to their last one's end."""
        starts, ends = self.spans()
        n = len(self.hashes)
        sums = np.r_[np.uint64(0), np.cumsum(_finish(self.hashes) * _powers(_BASES[1], n))]
        stop = ends + self.window
        # the inverse power takes a sum back to the first place: equal words give equal values in any text
        value = (sums[stop] - sums[starts]) * _powers(_INVERSE, n)[starts]
        return self.anchor[starts], _finish(value ^ (stop - starts).astype(np.uint64) * np.uint64(_MIX)), starts, ends


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _stretches(docs: DataFrame, window: int, hashes: bool = True) -> DataFrame:
    """``anchor, context, doc_id, whole``: the stretches of each text; whole holds the hash of each window (without
    ``hashes`` left out)."""
    names = ["anchor", "context", "doc_id", "whole"][: 4 if hashes else 3]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            ids = piece.column("doc_id").to_numpy()
            anchors, contexts, owners, cuts, wholes, at = [], [], [], [], [], 0
            for i, text in enumerate(texts):
                words = text.split() if text else []
                if len(words) >= window:
                    t = _Text(words, window)
                    anchor, context, starts, _ = t.contexts()
                    anchors.append(anchor)
                    contexts.append(context)
                    owners.append(np.full(len(starts), ids[i]))
                    if hashes:
                        cuts.append(starts + at)
                        wholes.append(t.whole())
                        at += len(t.anchor)
            if anchors:
                columns = [_signed(np.concatenate(anchors)), _signed(np.concatenate(contexts)), pa.array(np.concatenate(owners))]
                if hashes:
                    columns.append(pa.ListArray.from_arrays(pa.array(np.r_[np.concatenate(cuts), at].astype(np.int32)), _signed(np.concatenate(wholes))))
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.select("doc_id", "text").mapInArrow(run, "anchor long, context long, doc_id long" + (", whole array<long>" if hashes else ""))


def _removed(docs: DataFrame, window: int, rejoin: bool) -> DataFrame:
    """``docs`` with ``resolved`` (contexts) and ``repeated`` (window hashes) ->
    its columns and the words that stay."""
    rest = [f for f in docs.schema.fields if f.name not in ("text", "resolved", "repeated")]
    names = [f.name for f in rest]
    schema = T.StructType([*rest, T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_text", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            resolved, repeated = piece.column("resolved").to_pylist(), piece.column("repeated").to_pylist()
            n_words, n_removed, kept = [], [], []
            for i, text in enumerate(texts):
                words = text.split() if text else []
                gone = np.zeros(len(words), bool)
                if len(words) >= window and (resolved[i] or repeated[i]):
                    t = _Text(words, window)
                    mark = np.zeros(len(words) + 1, np.int64)
                    if resolved[i]:
                        _, context, starts, ends = t.contexts()
                        hit = np.isin(context.view(np.int64), np.array(resolved[i], np.int64))
                        np.add.at(mark, starts[hit], 1)
                        np.add.at(mark, ends[hit] + window, -1)
                    if repeated[i]:
                        at = np.flatnonzero(np.isin(t.whole().view(np.int64), np.array(repeated[i], np.int64)))
                        np.add.at(mark, at, 1)
                        np.add.at(mark, at + window, -1)
                    gone = np.cumsum(mark)[:-1] > 0
                n_words.append(len(words))
                n_removed.append(int(gone.sum()))
                if n_removed[-1]:
                    words = [w for w, g in zip(words, gone, strict=True) if not g]
                kept.append(b" ".join(words) if rejoin or n_removed[-1] else text)
            texts_out = pa.array(kept, pa.binary()).cast(pa.string())
            yield pa.RecordBatch.from_arrays([*(piece.column(c) for c in names), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), texts_out], names=[*names, "n_words", "n_removed", "kept_text"])

    return docs.mapInArrow(run, schema)


@contextmanager
def _in_order(spark: SparkSession):
    """Plans made here take a bucket of one sorted file as sorted."""
    name = "spark.sql.legacy.bucketedTableScan.outputOrdering"
    before = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


@dataclass
class Run:
    """Paths of an immutable run: its keys, its windows and its hot anchors (None: none)."""

    keys: str
    windows: str
    hot: str | None


@dataclass
class WindowIndex:
    """Runs of window hashes in the shared folder.

    What is in the index counts as earlier than any batch to come, whatever the ids, so batches
    with rising ids give the same answer as one call over all. ``manifest`` describes the index; ``opened`` makes it
    anew from that, in another session too.
    """

    spark: SparkSession
    window: int = WINDOW
    fan_in: int = FAN_IN
    buckets: int = 0
    hot_rows: int = joins.LEAST
    runs: list[Run] = field(default_factory=list)
    where: str = ""

    KEYS = ("part long, anchor long, context long, doc_id long", "part")
    WINDOWS = ("anchor long, context long, doc_id long, last long, n long, whole array<long>", "anchor, context")

    def __post_init__(self) -> None:
        self.where = self.where or f"{shared_dir(self.spark)}/windows-{uuid.uuid4().hex}"
        self.buckets = self.buckets or int(self.spark.conf.get("spark.sql.shuffle.partitions"))

    def manifest(self) -> dict:
        return {"window": self.window, "fan_in": self.fan_in, "buckets": self.buckets, "hot_rows": self.hot_rows, "where": self.where, "runs": [vars(r) for r in self.runs]}

    @classmethod
    def opened(cls, spark: SparkSession, manifest: dict) -> WindowIndex:
        return cls(spark, **{**manifest, "runs": [Run(**r) for r in manifest["runs"]]})

    def table(self, path: str, kind: tuple[str, str]) -> DataFrame:
        """A bucketed table by its path; a session that doesn't know it yet is told of it."""
        name = f"run_{path.rsplit('/', 1)[-1].replace('-', '_')}"
        self.spark.sql(f"CREATE TABLE IF NOT EXISTS {name} ({kind[0]}) USING parquet CLUSTERED BY ({kind[1]}) SORTED BY ({kind[1]}) INTO {self.buckets} BUCKETS LOCATION '{path}'")
        return self.spark.table(name)

    def bucketed(self, df: DataFrame, kind: tuple[str, str]) -> str:
        path = f"{self.where}/{uuid.uuid4().hex}"
        name = f"run_{path.rsplit('/', 1)[-1]}"
        by = kind[1].split(", ")
        df.write.format("parquet").bucketBy(self.buckets, *by).sortBy(*by).option("path", path).saveAsTable(name)
        return path

    def forget(self, path: str) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS run_{path.rsplit('/', 1)[-1]}")
        remove(self.spark, path)

    def add(self, batch: DataFrame, keep_batch: bool = True) -> DataFrame:
        """Judge the documents of ``batch`` (doc_id, text) against the index and one another, and index
        them unless ``keep_batch`` is false. Returns ``doc_id, resolved, repeated``: contexts and windows of a document
        that an earlier one has."""
        spark, tag = self.spark, f"{self.where}/{uuid.uuid4().hex}"
        temporary: list[str] = []

        def keep(df: DataFrame, name: str) -> DataFrame:
            temporary.append(f"{tag}-{name}")
            df.write.parquet(temporary[-1])
            return spark.read.schema(df.schema).parquet(temporary[-1])

        # the stretches with their hashes go straight into the new run: written beside it, they would take its size once more
        merged = _stretches(batch, self.window).groupBy("anchor", "context").agg(F.min("doc_id").alias("doc_id"), F.max("doc_id").alias("last"), F.count("*").alias("n"), F.first("whole").alias("whole"))
        windows = self.bucketed(merged, self.WINDOWS)
        del merged
        release(spark)
        found = keep(_stretches(batch, self.window, hashes=False), "found")
        fresh = self.table(windows, self.WINDOWS)
        own = fresh.groupBy("anchor").agg(F.count("*").alias("n"), F.min("context").alias("low"), F.max("context").alias("high"), F.min("doc_id").alias("first"), F.max("last").alias("last"))
        own = keep(own, "anchors")
        with _in_order(spark):
            known = keep(self.known(own), "known")

        # a context that an earlier document has: all its windows are repeated
        of_run = known.groupBy("anchor", "context").agg(F.min("doc_id").alias("old"))
        shared = fresh.select("anchor", "context", "doc_id", "last", "n").join(of_run, ["anchor", "context"], "left").filter("old is not null or doc_id < last")
        shared = keep(shared.select("anchor", "context", F.coalesce("old", "doc_id").alias("first"), F.col("old").isNotNull().alias("before"), "n"), "shared")
        earlier = (F.col("before") & (F.col("doc_id") != F.col("first"))) | (F.col("doc_id") > F.col("first"))
        hits = joins.met(found.select("anchor", "context", "doc_id"), shared, ["anchor", "context"], "n", found.count(), self.hot_rows)
        resolved = hits.filter(earlier).groupBy("doc_id").agg(F.collect_set("context").alias("resolved"))

        # an anchor in several contexts, of several documents: its windows are compared one by one
        every = own.select("anchor", "n", "low", "high", "first", "last", F.lit(False).alias("before"))
        every = every.unionByName(known.select("anchor", F.lit(1).cast("long").alias("n"), F.col("context").alias("low"), F.col("context").alias("high"), F.col("doc_id").alias("first"), F.col("doc_id").alias("last"), F.lit(True).alias("before")))
        many = every.groupBy("anchor").agg(F.sum("n").alias("n"), F.min("low").alias("low"), F.max("high").alias("high"), F.min("first").alias("first"), F.max("last").alias("last")).filter("low < high and first < last")
        many = keep(many.select("anchor", "n"), "many")
        old, new = known.select("anchor", "context"), fresh.select("anchor", "context")
        total = many.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        opened = keep(joins.met(new, many, ["anchor"], "n", total, self.hot_rows, "left_semi").distinct(), "opened")
        with _in_order(spark):
            listed = fresh.join(opened, ["anchor", "context"], "left_semi").select("anchor", "doc_id", F.lit(False).alias("before"), F.explode("whole").alias("whole"))
            if self.runs:
                again = keep(joins.met(old, many, ["anchor"], "n", total, self.hot_rows, "left_semi").distinct(), "opened-again")
                for r in self.runs:
                    past = self.table(r.windows, self.WINDOWS).join(again, ["anchor", "context"], "left_semi")
                    listed = listed.unionByName(past.select("anchor", "doc_id", F.lit(True).alias("before"), F.explode("whole").alias("whole")))
            listed = keep(listed, "listed")
        lowest = listed.groupBy("anchor", "whole").agg(F.min(F.struct((~F.col("before")).alias("new"), "doc_id")).alias("low"), F.count("*").alias("n")).filter("n > 1")
        lowest = keep(lowest.select("anchor", "whole", F.col("low.doc_id").alias("first"), (~F.col("low.new")).alias("before"), "n"), "lowest")
        hits = joins.met(listed.filter("not before").select("anchor", "whole", "doc_id"), lowest, ["anchor", "whole"], "n", listed.count(), self.hot_rows)
        repeated = hits.filter(earlier).groupBy("doc_id").agg(F.collect_set("whole").alias("repeated"))

        path = f"{tag}-marks"
        resolved.join(repeated, "doc_id", "full").write.parquet(path)
        if keep_batch:
            self.runs.append(self.run_of(windows, own))
        else:
            self.forget(windows)
        for x in temporary:
            remove(spark, x)
        release(spark)
        if len(self.runs) >= self.fan_in:
            self.compact()
        return spark.read.schema("doc_id long, resolved array<long>, repeated array<long>").parquet(path)

    def known(self, own: DataFrame) -> DataFrame:
        """``anchor, context, doc_id``: rows of the runs whose anchor is among ``own``. Each run is read in its
        buckets; only the anchors asked for are exchanged."""
        out = self.spark.createDataFrame([], "anchor long, context long, doc_id long")
        for r in self.runs:
            asked = own.select(F.col("anchor").alias("part"))
            if r.hot:
                hot = self.spark.read.schema("anchor long").parquet(r.hot)
                salts = F.explode(F.sequence(F.lit(0), F.lit(SPREAD - 1))).alias("salt")
                asked = asked.unionByName(own.join(F.broadcast(hot), "anchor", "left_semi").select("anchor", salts).select(F.xxhash64("anchor", "salt").alias("part")))
            out = out.unionByName(self.table(r.keys, self.KEYS).join(asked, "part", "left_semi").select(F.coalesce("anchor", "part").alias("anchor"), "context", "doc_id"))
        return out

    def run_of(self, windows: str, own: DataFrame) -> Run:
        """Written windows as a run; ``own`` counts contexts by anchor."""
        total = own.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        hot = own.filter(F.col("n") >= max(self.hot_rows, total // joins.SHARE)).select("anchor")
        path = f"{self.where}/{uuid.uuid4().hex}-hot"
        hot.write.parquet(path)
        hot = self.spark.read.schema("anchor long").parquet(path)
        rows = self.table(windows, self.WINDOWS).select(F.col("anchor").alias("part"), "anchor", "context", "doc_id")
        some = hot.limit(1).count() > 0
        if some:
            dealt = rows.join(F.broadcast(hot), "anchor", "left_semi").withColumn("part", F.xxhash64("anchor", F.pmod("context", F.lit(SPREAD)).cast("int")))
            rows = rows.join(F.broadcast(hot), "anchor", "left_anti").unionByName(dealt.select(*rows.columns))
        anchor = F.when(F.col("part") != F.col("anchor"), F.col("anchor")).alias("anchor")
        keys = self.bucketed(rows.select("part", anchor, "context", "doc_id").repartition(self.buckets, "part"), self.KEYS)
        return Run(keys, windows, path if some else None)

    def merged(self) -> DataFrame:
        """All runs as one, merged bucket by bucket; a context keeps its first document."""
        every = None
        for r in self.runs:
            rows = self.table(r.windows, self.WINDOWS)
            every = rows if every is None else every.unionByName(rows)
        return every.groupBy("anchor", "context").agg(F.min("doc_id").alias("doc_id"), F.max("last").alias("last"), F.sum("n").alias("n"), F.first("whole").alias("whole"))

    def compact(self) -> None:
        """One run in place of all."""
        if not self.runs:
            return
        # keys follow from windows, so they go first and come last
        for r in self.runs:
            self.forget(r.keys)
        with _in_order(self.spark):
            windows = self.bucketed(self.merged(), self.WINDOWS)
        for r in self.runs:
            self.forget(r.windows)
        own = self.table(windows, self.WINDOWS).groupBy("anchor").agg(F.count("*").alias("n"))
        self.runs = [self.run_of(windows, own)]
        release(self.spark)


def dedup_windows(docs: DataFrame, text: str = "text", window: int = WINDOW, batches: int = BATCHES, index: WindowIndex | None = None, rejoin: bool = True) -> DataFrame:
    """Remove each word covered by a window of ``window`` words that also starts
    in a document with a smaller doc_id, or in one that ``index`` had before.

    Returns the columns of ``docs`` without the text, then ``n_words, n_removed,
    kept_text`` (kept words joined by one space, or without ``rejoin`` a text that loses nothing as it is; columns
    of ``docs`` with those names are replaced, others of any name stay). ``docs`` is cut into ``batches`` ranges of doc_id, which go through the index in order; an index of the
    caller's keeps them all, for calls to come. Null and blank texts have
    no words; texts shorter than a window lose nothing; rows that repeat a doc_id don't count
    against one another; rows without a doc_id are neither judged nor indexed. An empty table gives an
    empty result.
    """
    spark = docs.sparkSession
    lasting = index is not None
    index = index or WindowIndex(spark, window)
    others = [c for c in docs.columns if c not in ("doc_id", text, "n_words", "n_removed", "kept_text")]
    packed = F.struct(*[F.col(f"`{c}`") for c in others]) if others else F.lit(None).cast("int")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).alias("text"), packed.alias("rest"))
    texts = keyed.filter("doc_id is not null and text is not null").select("doc_id", "text")
    cuts: list[int] = []
    if batches > 1:
        quantiles = texts.select(F.percentile_approx("doc_id", [i / batches for i in range(1, batches)], 10_000)).first()[0]
        cuts = sorted(set(quantiles or []))
    marks, low = None, None
    for cut in [*cuts, None]:
        part = texts if low is None else texts.filter(F.col("doc_id") > low)
        part = part if cut is None else part.filter(F.col("doc_id") <= cut)
        got = index.add(part, lasting or cut is not None)
        marks = got if marks is None else marks.unionByName(got)
        low = cut
    none = F.lit(None).cast("array<long>")
    judged = keyed.filter("doc_id is not null").join(marks, "doc_id", "left")
    without = keyed.filter("doc_id is null").withColumn("resolved", none).withColumn("repeated", none)
    out = _removed(judged.unionByName(without), index.window, rejoin)
    return out.select(*[F.col("doc_id") if c == "doc_id" else F.col("rest")[c].alias(c) for c in docs.columns if c in ("doc_id", *others)], "n_words", "n_removed", "kept_text")
