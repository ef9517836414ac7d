"""Times headline queries; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from bicommunity.model import CommunityQuery, EngineConfig
from bicommunity.operators import graph, prune, score, support, truss
from bicommunity.operators import window as win
from bicommunity.plans import baselines, continuous, snapshot
from bicommunity.sources import tables
from bicommunity.store import written


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def timed(name: str, fn):
        t = time.perf_counter()
        out = fn()
        times[name] = round(time.perf_counter() - t, 3)
        return out

    c, e = tables.graph(spark, sf_dir, "C"), tables.graph(spark, sf_dir, "E")
    edges = timed("edges_c", lambda: written(c.edges, "edges"))
    pairs = timed("pairs_c", lambda: written(score.pairs(edges), "pairs"))
    timed("supports_c", lambda: written(support.exact(edges), "supports"))
    q = CommunityQuery(4, 2, 3, ("Brand#1", "ECONOMY", "small"), "c")
    mine = written(prune.keyword(edges, c.item_kw, q.keywords), "filtered")
    timed("core_c", lambda: truss.core(mine, q.k, q.sigma).count())
    timed("snapshot_c", lambda: snapshot.run(edges, c.item_kw, q).count())

    updates = timed("ranks_e", lambda: written(win.rank_updates(e.interactions), "updates"))
    half = updates.count() // 2
    base = written(graph.build_edges(updates.filter(f"t <= {half}")), "base")
    stream = updates.filter(f"t > {half}").selectExpr("t - %d as t" % half, "u", "v")
    kw = written(e.item_kw, "kw")
    busy = CommunityQuery(4, 1, 3, ("d1",), "busy")
    config = EngineConfig(window=500, tick=500)
    engine = continuous.CommunityEngine(base, kw, config)
    timed("register_e", lambda: engine.register(busy))
    ticks = 3
    timed("continuous_e", lambda: engine.feed(stream, ticks * config.tick))
    times["continuous_tick_e"] = round(times["continuous_e"] / ticks, 3)
    now = written(graph.snapshot(base, stream, config.window, config.tick), "now")
    timed("trussness_tick_e", lambda: baselines.trussness_query(baselines.trussness_index(now), kw, busy).count())
    changes = written(graph.changed_weights(edges, graph.net_changes(edges.limit(1000), edges.limit(0))), "changes")
    timed("maintain_pairs_c", lambda: written(score.maintain(pairs, edges, changes), "pairs"))
    total = round(sum(v for k, v in times.items() if k != "continuous_tick_e"), 3)
    updates_s = round(ticks * config.tick / times["continuous_e"], 1)
    print(json.dumps({"metric": "headline queries", "value": total, "unit": "sec", "queries": times, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "updates_per_s": updates_s}))


if __name__ == "__main__":
    main()
