"""The continuous query on Structured Streaming.

Arrival numbers are given in ``foreachBatch``, where a micro-batch is a table: it is ordered, numbered after
the arrivals so far and fed to the engine as ticks. State is a versioned folder per batch, and a
marker file ends a version. A batch that is replayed after a failure finds its version and does nothing, and a new
process starts from the version before its first batch.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..model import CommunityQuery, EngineConfig
from ..operators.window import rank_updates
from ..plans.continuous import RESULT, CommunityEngine

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


@dataclass
class StreamingCommunities:
    """Feeds micro-batches (ts, seq, u, v) to an engine, and keeps its results in ``state``."""

    engine: CommunityEngine
    state: str
    last: int | None = None

    def _path(self, batch: int, what: str) -> str:
        return f"{self.state}/v={batch}/{what}"

    def _done(self, spark: SparkSession, batch: int) -> bool:
        where = spark._jvm.org.apache.hadoop.fs.Path(f"{self.state}/v={batch}/_DONE")
        return where.getFileSystem(spark._jsc.hadoopConfiguration()).exists(where)

    def _finish(self, spark: SparkSession, batch: int) -> None:
        where = spark._jvm.org.apache.hadoop.fs.Path(f"{self.state}/v={batch}/_DONE")
        where.getFileSystem(spark._jsc.hadoopConfiguration()).create(where, True).close()

    def restore(self, spark: SparkSession, batch: int) -> None:
        """Put the engine in the state that a batch has left."""
        e = self.engine
        edges = spark.read.schema("u bigint, v string, w bigint").parquet(self._path(batch, "edges"))
        at = spark.read.schema("at bigint").parquet(self._path(batch, "at")).first().at
        answers = {qid: spark.read.schema(RESULT).parquet(self._path(batch, f"results/{qid}")) for qid in e.queries}
        e.restore(edges, answers, at)
        self.last = batch

    def on_batch(self, rows: DataFrame, batch: int) -> None:
        spark = rows.sparkSession
        if self._done(spark, batch):
            return
        if batch > 0 and self.last != batch - 1 and self._done(spark, batch - 1):
            self.restore(spark, batch - 1)
        e = self.engine
        start, s = e.at, e.config.window
        ranked = rank_updates(rows.filter("u is not null and v is not null")).withColumn("t", F.col("t") + start)
        ranked.write.mode("overwrite").parquet(self._path(batch, "updates"))
        recent = spark.read.parquet(self._path(batch, "updates")).select("t", "u", "v")
        if batch > 0:
            recent = recent.unionByName(spark.read.schema("t bigint, u bigint, v string").parquet(self._path(batch - 1, "recent")))
        last = recent.agg(F.max("t")).first()[0] or start
        e.feed(recent, last)
        recent.filter(F.col("t") > last - s).write.mode("overwrite").parquet(self._path(batch, "recent"))
        e.edges.write.mode("overwrite").parquet(self._path(batch, "edges"))
        for qid in e.queries:
            e.results(qid).write.mode("overwrite").parquet(self._path(batch, f"results/{qid}"))
        spark.range(1).select(F.lit(e.at).cast("bigint").alias("at")).write.mode("overwrite").parquet(self._path(batch, "at"))
        self._finish(spark, batch)
        self.last = batch

    def start(self, rows: DataFrame, checkpoint: str, available_now: bool = True, interval: str = "10 seconds") -> StreamingQuery:
        trigger = {"availableNow": True} if available_now else {"processingTime": interval}
        return rows.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(**trigger).start()


def events_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Event files as interactions (ts, seq, u, v)."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return interactions(raw)


def rate_stream(spark: SparkSession, rows_per_second: int = 100, n_users: int = 1000, n_items: int = 500) -> DataFrame:
    """Made-up interactions (ts, seq, u, v) at a steady rate, for load tests: users and items by hash of the row number."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    u, v = F.pmod(F.xxhash64("value"), F.lit(n_users)), F.pmod(F.xxhash64("value", F.lit(1)), F.lit(n_items))
    return raw.select(F.col("timestamp").alias("ts"), F.col("value").alias("seq"), u.alias("u"), F.concat(F.lit("i"), v.cast("string")).alias("v"))


def interactions(raw: DataFrame) -> DataFrame:
    k = F.get_json_object("props", "$.k")
    return raw.select("ts", F.col("event_id").alias("seq"), F.col("user_id").alias("u"), F.concat_ws(":", "event_type", k).alias("v"))


def once(rows: DataFrame, delay: str = "1 hour", key: str = "seq") -> DataFrame:
    """Replayed events dropped, as long as they come within the watermark."""
    return rows.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def windowed_edges(rows: DataFrame, span: str, step: str | None = None, delay: str | None = "1 hour") -> DataFrame:
    """Edges by event-time window; rows later than the watermark are dropped by Spark.
    ``delay=None``: the rows have a watermark already."""
    win = F.window("ts", span, step) if step else F.window("ts", span)
    marked = rows if delay is None else rows.withWatermark("ts", delay)
    return marked.groupBy(win.alias("win"), "u", "v").agg(F.count("*").alias("w")).select(F.col("win.start").alias("start"), F.col("win.end").alias("stop"), "u", "v", "w")


def user_sessions(rows: DataFrame, gap: str, delay: str = "1 hour") -> DataFrame:
    return rows.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("win"), "u").agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), F.col("win.end").alias("stop"), "u", "n")


def with_items(rows: DataFrame, item_kw: DataFrame, q: CommunityQuery) -> DataFrame:
    """Stream rows on items of the query (a stream-static semi-join)."""
    return rows.join(item_kw.filter(F.col("kw").isin(*q.keywords)).select("v").distinct(), "v", "left_semi")


def expiry_pairs(inserted: DataFrame, expired: DataFrame, span: str) -> DataFrame:
    """Stream-stream join: each expiry with the insertion it ends, ``span`` before."""
    a = inserted.withWatermark("ts", span).select(F.col("ts").alias("ts_in"), F.col("seq").alias("seq_in"), F.col("u").alias("u_in"), F.col("v").alias("v_in"))
    b = expired.withWatermark("ts", span).select(F.col("ts").alias("ts_out"), F.col("seq").alias("seq_out"), F.col("u").alias("u_out"), F.col("v").alias("v_out"))
    return a.join(b, (F.col("seq_in") == F.col("seq_out")) & (F.col("ts_out") >= F.col("ts_in")) & (F.col("ts_out") <= F.col("ts_in") + F.expr(f"interval {span}")))


def start(spark: SparkSession, path: str, base: DataFrame, item_kw: DataFrame, queries: list[CommunityQuery], state: str, checkpoint: str, config: EngineConfig = EngineConfig(), files_per_batch: int = 1) -> tuple[StreamingCommunities, StreamingQuery]:
    """Run registered queries over a folder of event files until it is read."""
    engine = CommunityEngine(base, item_kw, config)
    for q in queries:
        engine.register(q)
    runner = StreamingCommunities(engine, state)
    return runner, runner.start(events_stream(spark, path, files_per_batch), checkpoint)
