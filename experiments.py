"""The published experiments as timed runs; prints one JSON line for each point.

    python experiments.py --graphs E C --parameters k r sigma --runs 3
    python experiments.py --graphs powerlaw-uniform --users 2000 --items 2000 --parameters window
    python experiments.py --graphs E --baseline
    python experiments.py --graphs E --threads 1 2 4 8

A point feeds a continuous query for some ticks and reports the mean seconds of a tick over runs with keyword sets
drawn by frequency, its answers, and with ``--baseline`` how many times longer a trussness index built
anew at each tick takes. One parameter varies at a time; the others keep their defaults.
"""

from __future__ import annotations

import argparse
import json
import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bicommunity.model import CommunityQuery, EngineConfig
from bicommunity.operators import graph
from bicommunity.operators import window as win
from bicommunity.plans import baselines, continuous, measures, workloads
from bicommunity.sources import generate, tables
from bicommunity.store import written

# The published points and defaults of each parameter.
POINTS = {"window": (200, 300, 500, 800, 1000), "k": (3, 4, 5), "r": (1, 2, 3), "sigma": (1, 2, 3, 4, 5), "keywords": (2, 3, 5, 8, 10), "domain": (100, 200, 500, 800, 1000), "per_item": (1, 2, 3, 4, 5), "weights": (2, 3, 4), "users": (10_000, 15_000, 25_000, 50_000, 100_000), "items": (10_000, 15_000, 25_000, 50_000, 100_000)}
DEFAULTS = {"window": 500, "k": 4, "r": 2, "sigma": 3, "keywords": 5, "domain": 500, "per_item": 3, "weights": 2, "users": 25_000, "items": 25_000}


def load(spark: SparkSession, name: str, sf_dir: str, p: dict) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Base edges, ranked updates and item keywords: the second half of a graph's interactions arrives."""
    if "-" in name:
        degree, keyword = name.split("-")
        edges, item_kw = generate.synthetic(spark, p["users"], p["items"], degree, keyword, (1, p["weights"]), p["per_item"], p["domain"])
        each = edges.select("u", "v", F.explode(F.sequence(F.lit(1).cast("bigint"), "w")).alias("seq"))
        rows = each.select(F.timestamp_seconds(F.pmod(F.xxhash64("u", "v", "seq"), F.lit(10**8))).alias("ts"), "seq", "u", "v")
    else:
        g = tables.graph(spark, sf_dir, name)
        rows, item_kw = g.interactions, g.item_kw
    ranked = written(win.rank_updates(rows).select("t", "u", "v"), "ranked")
    half = ranked.count() // 2
    base = written(graph.build_edges(ranked.filter(F.col("t") <= half)), "base")
    return base, ranked.filter(F.col("t") > half).select((F.col("t") - half).alias("t"), "u", "v"), written(item_kw, "kw")


def point(spark: SparkSession, name: str, sf_dir: str, p: dict, runs: int, ticks: int, baseline: bool) -> dict:
    base, updates, item_kw = load(spark, name, sf_dir, p)
    took, rebuilt, answers = [], [], []
    for run in range(runs):
        q = CommunityQuery(p["k"], p["r"], p["sigma"], workloads.sample_query(item_kw, p["keywords"], run + 1), "q")
        config = EngineConfig(window=p["window"], tick=p["window"])
        engine = continuous.CommunityEngine(base, item_kw, config)
        engine.register(q)
        took.append(measures.timed(lambda: engine.feed(updates, ticks * config.tick), 1)["mean"] / ticks)
        answers.append(engine.results("q").select("center").distinct().count())
        if baseline:
            rebuilt.append(measures.timed(lambda: baselines.trussness_query(baselines.trussness_index(engine.edges), item_kw, q).count(), 1)["mean"])
    row = {"graph": name, **p, "tick_s": round(sum(took) / runs, 3), "least_s": round(min(took), 3), "greatest_s": round(max(took), 3), "answers": answers}
    if baseline:
        row |= {"baseline_s": round(sum(rebuilt) / runs, 3), "speedup": round(measures.speedup({"mean": sum(rebuilt)}, {"mean": sum(took)}), 2)}
    return row


def session(threads: int) -> SparkSession:
    conf = {"spark.driver.memory": os.environ.get("BENCH_MEMORY", "6g"), "spark.sql.shuffle.partitions": str(2 * threads), "spark.sql.session.timeZone": "UTC", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}
    builder = SparkSession.builder.master(f"local[{threads}]")
    for k, v in conf.items():
        builder = builder.config(k, v)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    args = argparse.ArgumentParser(description=__doc__, formatter_class=argparse.RawDescriptionHelpFormatter)
    args.add_argument("--graphs", nargs="+", default=["E"], help="E C S N, or degree-keyword such as beta-pareto")
    args.add_argument("--parameters", nargs="*", default=[], choices=sorted(POINTS))
    args.add_argument("--sf-dir", default=os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"))
    args.add_argument("--runs", type=int, default=10)
    args.add_argument("--ticks", type=int, default=2)
    args.add_argument("--threads", type=int, nargs="+", default=[int(os.environ.get("BENCH_CPUS", "8"))])
    args.add_argument("--baseline", action="store_true")
    args.add_argument("--users", type=int, default=DEFAULTS["users"])
    args.add_argument("--items", type=int, default=DEFAULTS["items"])
    a = args.parse_args()
    default = DEFAULTS | {"users": a.users, "items": a.items}
    points = [default | {name: value} for name in a.parameters for value in POINTS[name]] or [default]
    for threads in a.threads:
        spark = session(threads)
        for name in a.graphs:
            for p in points:
                print(json.dumps({"threads": threads, **point(spark, name, a.sf_dir, p, a.runs, a.ticks, a.baseline)}), flush=True)
        spark.stop()


if __name__ == "__main__":
    main()
