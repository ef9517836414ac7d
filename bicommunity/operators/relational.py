"""Community extraction by joins: all centres advance in lock-step, keyed by centre."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import CommunityQuery
from ..store import Rounds, written
from . import hops

_KEY = ["center"]


def _distances(g: DataFrame, r: int) -> DataFrame:
    """``center, u, dist`` inside each centre's graph, up to r steps."""
    seen = g.filter("u = center").select("center", "u").distinct().withColumn("dist", F.lit(0))
    at = seen
    for step in range(1, r + 1):
        items = at.select("center", "u").join(g.select("center", "u", "v"), ["center", "u"]).select("center", "v").distinct()
        at = items.join(g.select("center", "u", "v"), ["center", "v"]).select("center", "u").distinct().join(seen, ["center", "u"], "left_anti").select("center", "u", F.lit(2 * step).alias("dist"))
        seen = seen.unionByName(at)
    return seen


def _wedges(g: DataFrame) -> DataFrame:
    a = g.select("center", "v", F.col("u").alias("ui"), F.col("w").alias("wi"))
    b = g.select("center", "v", F.col("u").alias("uj"), F.col("w").alias("wj"))
    return a.join(b, ["center", "v"]).filter("ui < uj").select("center", "ui", "uj", "v", F.least("wi", "wj").alias("wm"))


def _pairs(w: DataFrame) -> DataFrame:
    sums = w.groupBy("center", "ui", "uj").agg(F.count("*").alias("n"), F.sum("wm").alias("x"), F.sum(F.col("wm") * F.col("wm")).alias("y"))
    return sums.withColumn("score", F.shiftright(F.col("x") * F.col("x") - F.col("y"), 1))


def _settle(g: DataFrame, q: CommunityQuery, r: int, sigma: int, items: str, rounds: Rounds) -> tuple[DataFrame, int]:
    """Fixpoint of radius and support in every centre's graph; also its number of edges."""
    n = g.count()
    while n:
        near = written(_distances(g, r), "distances")
        at = g.join(near, ["center", "u"])
        limit = 2 * r - 2 if items == "inner" else 2 * r
        reach = at.filter(F.col("dist") <= limit).select("center", "v").distinct()
        cut = at.join(reach, ["center", "v"], "left_semi").select("center", "u", "v", "w")
        cut = written(cut, "cut")
        w = _wedges(cut)
        good = _pairs(w).filter((F.col("score") >= sigma) & (F.col("n") > 1)).select("center", "ui", "uj", (F.col("n") - 1).alias("b"))
        sup = w.join(good, ["center", "ui", "uj"]).select("center", F.explode(F.array("ui", "uj")).alias("u"), "v", "b").groupBy("center", "u", "v").agg(F.sum("b").alias("sup"))
        g = rounds.keep(cut.join(sup.filter(F.col("sup") >= q.k), ["center", "u", "v"], "left_semi"))
        left = g.count()
        if left == n:
            break
        n = left
    return g, n


def _radius(core: DataFrame, q: CommunityQuery, r: int, centers: DataFrame | None, drop: str, items: str, rounds: Rounds) -> DataFrame:
    """Answers at one radius: ``center, u, v, w``."""
    sigma = q.sigma if q.score_rule == "pair" else 0
    g = rounds.keep(hops.subgraph(core, r, centers, items))
    while True:
        g, n = _settle(g, q, r, sigma, items, rounds)
        if not n:
            return g
        pairs = _pairs(_wedges(g))
        if q.score_rule == "total":
            enough = pairs.groupBy("center").agg(F.sum("score").alias("s")).filter(F.col("s") >= q.p * q.sigma)
            return rounds.keep(g.join(enough, "center", "left_semi"))
        weak = pairs.filter(F.col("score") < sigma).select("center", "ui", "uj")
        both = rounds.keep(weak.select("center", F.col("ui").alias("u"), F.col("uj").alias("other")).unionByName(weak.select("center", F.col("uj").alias("u"), F.col("ui").alias("other"))))
        if not both.limit(1).count():
            return g
        near = written(_distances(g, r), "distances")
        rank = both.groupBy("center", "u").agg(F.count("*").alias("n")).join(near, ["center", "u"]).select("center", "u", F.struct("n", "dist", "u").alias("rank"))
        own = both.filter("u = center").select("center", F.col("other").alias("u"), F.col("u").alias("other"))
        peers = both.join(own.select("center").distinct(), "center", "left_anti")
        ranked = peers.join(rank, ["center", "u"]).join(rank.select("center", F.col("u").alias("other"), F.col("rank").alias("theirs")), ["center", "other"])
        worst = ranked.groupBy("center", "u").agg(F.max("rank").alias("rank"), F.max("theirs").alias("theirs")).filter(F.col("rank") > F.col("theirs"))
        losing = own.unionByName(peers.join(worst.select("center", "u"), ["center", "u"], "left_semi").select("center", "u", "other"))
        if drop == "user":
            g = rounds.keep(g.join(losing.select("center", "u").distinct(), ["center", "u"], "left_anti"))
        else:
            shared = losing.join(g.select("center", F.col("u").alias("other"), "v"), ["center", "other"]).select("center", "u", "v").distinct()
            g = rounds.keep(g.join(shared, ["center", "u", "v"], "left_anti"))


def extract(core: DataFrame, q: CommunityQuery, centers: DataFrame | None = None, drop: str = "user", items: str = "inner") -> DataFrame:
    """Same answers as the grouped kernel, without a bound on a candidate's size."""
    spark, found = core.sparkSession, None
    if q.k <= 0:
        return spark.createDataFrame([], "qid string, center bigint, u bigint, v string, w bigint, radius int")
    for r in range(1, q.r + 1):
        part = _radius(core, q, r, centers, drop, items, Rounds(spark, "extract")).withColumn("radius", F.lit(r))
        found = part if found is None else found.unionByName(part)
    sizes = found.groupBy("center", "radius").agg(F.countDistinct("u").alias("users"), F.count("*").alias("n"))
    best = sizes.withColumn("nth", F.row_number().over(Window.partitionBy("center").orderBy(F.desc("users"), F.desc("n"), "radius"))).filter("nth = 1").select("center", "radius")
    return found.join(best, ["center", "radius"], "left_semi").select(F.lit(q.qid).alias("qid"), "center", "u", "v", "w", "radius")
