import time

import pytest
from fixtures import F1, block, frame, graph_of
from pyspark.sql import functions as F
from test_community import answers, kws

from bicommunity.functions import sqlapi
from bicommunity.model import CommunityQuery, EngineConfig, conform
from bicommunity.operators import graph, keywords, motifs
from bicommunity.plans import continuous, snapshot, workloads
from bicommunity.sources import files, generate, tables
from bicommunity.streaming import engine as streaming


@pytest.mark.parametrize("kind", ["parquet", "csv", "json", "orc"])
def test_edge_files(spark, tmp_path, kind):
    e = frame(spark, F1)
    files.write_rows(e, str(tmp_path / kind), kind)
    assert graph_of(files.read_edges(spark, str(tmp_path / kind), kind)) == F1


def test_partitioned_and_bucketed(spark, tmp_path):
    e = frame(spark, F1)
    files.write_rows(e, str(tmp_path / "p"), partition_by=("v",))
    assert spark.read.parquet(str(tmp_path / "p")).filter("v = 'v3'").count() == 2
    files.save_bucketed(e, "edges_by_item", "v", 4)
    a, b = spark.table("edges_by_item"), spark.table("edges_by_item")
    plan = a.join(b, "v")._jdf.queryExecution().toString()
    assert "Exchange hashpartitioning" not in plan
    spark.sql("drop table edges_by_item")


@pytest.mark.parametrize("name", sorted(tables.GRAPHS))
def test_graphs(spark, small, name):
    g = tables.graph(spark, small, name)
    conform(g.edges, "u bigint, v string, w bigint")
    conform(g.item_kw, "v string, kw string")
    assert g.edges.count() > 50 and g.edges.join(g.item_kw, "v", "left_anti").count() == 0


def test_generator(spark):
    for degree in ("powerlaw", "beta"):
        e, kw = generate.synthetic(spark, 2000, 500, degree, "lognormal", (1, 3), 3, 100)
        m = e.agg(F.avg("w").alias("mean"), F.min("w").alias("lo"), F.max("w").alias("hi"), F.countDistinct("u").alias("users")).first()
        assert abs(m["mean"] - 2.0) < 0.1 and (m.lo, m.hi) == (1, 3) and m.users == 2000
        k = kw.agg(F.max(F.col("kw").cast("int")).alias("hi"), F.count("*").alias("n")).first()
        assert k.hi < 100 and k.n <= 1500
        assert graph_of(e) == graph_of(generate.synthetic(spark, 2000, 500, degree, "lognormal", (1, 3), 3, 100)[0])
    with pytest.raises(ValueError):
        generate.degree_column("other", 1, 1, 1)


def test_beta_degrees(spark):
    """Degrees of the bounded law have the mean and spread of a Beta law with parameters 2 and 3."""
    d = spark.range(20_000).select(F.col("id").alias("u")).select(generate.degree_column("beta", 400.0, 42, 10**6).alias("d"))
    m = d.agg(F.avg("d").alias("mean"), F.stddev("d").alias("sd"), F.max("d").alias("most")).first()
    assert abs(m["mean"] - 400) < 8 and abs(m.sd - 200) < 8 and m.most <= 1000


def test_rate_stream(spark, tmp_path):
    q = streaming.rate_stream(spark, 50, 10, 5).writeStream.format("memory").queryName("rated").option("checkpointLocation", str(tmp_path)).start()
    try:
        for _ in range(60):
            if spark.table("rated").limit(1).count():
                break
            time.sleep(0.5)
    finally:
        q.stop()
    r = spark.table("rated").agg(F.min("u").alias("lo"), F.max("u").alias("hi"), F.countDistinct("v").alias("items")).first()
    assert 0 <= r.lo <= r.hi < 10 and 1 <= r["items"] <= 5


def test_query_sampler(spark):
    kw = spark.createDataFrame([(f"v{i}", "common") for i in range(90)] + [(f"v{i}", f"rare{i}") for i in range(10)], "v string, kw string")
    drawn = [workloads.sample_query(kw, 1, s) for s in range(20)]
    assert drawn == [workloads.sample_query(kw, 1, s) for s in range(20)]
    assert sum(d == ("common",) for d in drawn) > 12
    assert len(set(workloads.sample_query(kw, 5, 3))) == 5


def test_vectors(spark):
    kw = spark.createDataFrame([(f"v{i}", f"k{i % 7}") for i in range(30)], "v string, kw string")
    for r in keywords.bit_vectors(kw).collect():
        assert list(r.bv) == keywords.query_vector([f"k{int(r.v[1:]) % 7}"])
    hit = keywords.bit_vectors(kw).filter(keywords.overlaps(F.col("bv"), keywords.query_vector(["k1", "k2"])))
    assert {r.v for r in hit.collect()} >= {f"v{i}" for i in range(30) if i % 7 in (1, 2)}
    assert 0 < keywords.fill_factor(keywords.bit_vectors(kw)).first()[0] < 0.1
    assert keywords.bitmaps(kw).agg(F.sum(F.bitmap_count("bitmap"))).first()[0] == 30
    twin = keywords.bit_vectors(kw).groupBy().agg(sqlapi.or_vectors()("bv").alias("x")).first()
    assert list(twin.x) == list(keywords.bit_vectors(kw).agg(keywords.or_words("bv", 256).alias("y")).first().y)


def test_sql_surface(spark):
    e = frame(spark, F1)
    sqlapi.register(e, kws(spark, F1))
    assert spark.sql("select score from pairs where ui = 2 and uj = 3").first()[0] == 11
    assert spark.sql("select count(*) from edge_support where sup = 2").first()[0] == 6
    sqlapi.register_functions(spark)
    frame(spark, block((1, 2), "ab")).selectExpr("explode(array(1L, 2L)) as center", "u", "v", "w").createOrReplaceTempView("candidates")
    got = spark.sql("select * from community_of(table(candidates) partition by (center), 1, 1, 1)")
    assert got.count() == 8


def test_plans(spark, small):
    e = tables.graph(spark, small, "C").edges
    plan = motifs.wedges(e)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan and "Python" not in plan
    lines = tables.table(spark, small, "lineitem").filter("l_suppkey < 3").select("l_partkey")
    scan = lines._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_suppkey), LessThan(l_suppkey,3)]" in scan and "l_quantity" not in scan
    sql = spark.sql("select 1 where exists (select 1)")
    assert sql.count() == 1


def events(spark, rows):
    df = spark.createDataFrame(rows, "event_id bigint, s bigint, user_id bigint, k int")
    return df.selectExpr("event_id", "timestamp_seconds(1000020 + s) as ts", "user_id", "'click' as event_type", "0.0D as value", "concat('{\"k\": ', k, '}') as props")


def test_stream_equals_batches(spark, tmp_path):
    rows = [(i, 10 * i, i % 5, (i * 7) % 4) for i in range(24)]
    for part in range(3):
        events(spark, rows[part * 8 : part * 8 + 8]).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    base = frame(spark, block((0, 1, 2), ("click:0", "click:1", "click:2")))
    kw = spark.createDataFrame([(f"click:{i}", "x") for i in range(4)], "v string, kw string")
    q = CommunityQuery(1, 1, 1, ("x",))
    config = EngineConfig(window=10, tick=8)
    runner, query = streaming.start(spark, str(tmp_path / "in"), base, kw, [q], str(tmp_path / "state"), str(tmp_path / "ck"), config)
    query.awaitTermination()
    assert query.exception() is None and runner.engine.at == 24
    up = spark.read.parquet(*[str(tmp_path / f"state/v={b}/updates") for b in range(3)])
    now = graph.snapshot(base, up, 10, 24)
    assert graph_of(now) == graph_of(runner.engine.edges)
    assert answers(runner.engine.results("q")) == answers(snapshot.run(now, kw, q))
    runner.on_batch(events(spark, rows[:3]).transform(streaming.interactions), 2)
    assert runner.engine.at == 24
    # a new process on the same folders: more input goes on from the saved state
    more = events(spark, [(i, 10 * i, i % 5, (i * 7) % 4) for i in range(24, 32)])
    more.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    again, query = streaming.start(spark, str(tmp_path / "in"), base, kw, [q], str(tmp_path / "state"), str(tmp_path / "ck"), config)
    query.awaitTermination()
    assert query.exception() is None and again.engine.at == 32
    up = up.unionByName(spark.read.parquet(str(tmp_path / "state/v=3/updates")))
    now = graph.snapshot(base, up, 10, 32)
    assert graph_of(now) == graph_of(again.engine.edges)
    assert answers(again.engine.results("q")) == answers(snapshot.run(now, kw, q))


def run_memory(spark, df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def test_stream_windows_and_dedupe(spark, tmp_path):
    rows = [(1, 0, 1, 1), (2, 30, 1, 1), (2, 30, 1, 1), (3, 90, 2, 1), (4, 100000, 2, 2)]
    events(spark, rows).coalesce(1).write.parquet(str(tmp_path / "in"))
    s = streaming.events_stream(spark, str(tmp_path / "in"))
    assert run_memory(spark, streaming.once(s), "once").count() == 4
    got = run_memory(spark, streaming.windowed_edges(streaming.once(s, "10 seconds"), "1 minute", delay=None), "win")
    assert sorted((r.u, r.v, r.w) for r in got.collect()) == [(1, "click:1", 2), (2, "click:1", 1)]
    sess = run_memory(spark, streaming.user_sessions(s, "50 seconds", "10 seconds"), "sess")
    assert sorted((r.u, r.n) for r in sess.collect()) == [(1, 3), (2, 1)]
    kw = spark.createDataFrame([("click:2", "x")], "v string, kw string")
    assert run_memory(spark, streaming.with_items(s, kw, CommunityQuery(1, 1, 1, ("x",))), "items").count() == 1
    pairs = streaming.expiry_pairs(s, s.withColumn("ts", F.col("ts") + F.expr("interval 5 seconds")), "10 seconds")
    assert run_memory(spark, pairs, "pairs_out").count() == 7


def test_many_queries(spark):
    base = frame(spark, block((1, 2), "abc"))
    kw = spark.createDataFrame([("a", "x"), ("b", "x"), ("c", "y")], "v string, kw string")
    wanted = spark.createDataFrame([("one", 1, 1, 1, ["x"]), ("two", 2, 1, 3, ["x", "y"])], "qid string, k int, r int, sigma bigint, kws array<string>")
    up = spark.createDataFrame([(1, 3, "a"), (2, 3, "b")], "t bigint, u bigint, v string")
    e = continuous.run_many(base, up, kw, wanted, EngineConfig(tick=2))
    assert {u for u, _ in answers(e.results("one"))[1]} == {1, 2, 3}
    assert len(answers(e.results("two"))[1]) == 6
    assert {(r.qid, r.op) for r in e.changes().collect()} == {("one", "add"), ("one", "update")}
