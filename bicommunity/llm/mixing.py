"""Mixing sources to target weights by pivotal dependent rounding.

DataFrame functions only. Fractional copies of similar documents meet in small groups; in
each group probability mass moves between pairs until one of the two is integral, and the one
unit left over goes up a reduction tree to meet those of other groups.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .store import written

WORD = r"[^\x20\x09-\x0D]+"
#: Units that meet in one group of the tree.
FAN = 24
#: Documents whose sizes differ by less than this factor meet first.
SIZE_STEP = 1.1


def word_count(text: Column | str) -> Column:
    """Words of the contract's pattern; null text: 0."""
    return F.coalesce(F.regexp_count(F.col(text) if isinstance(text, str) else text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: Sequence[int], share: float, most: int) -> DataFrame:
    """``source, source_size, n_docs, target``: the budget, ``share`` times all sizes, by
    weight; no target over ``most`` times its source's size.

    Sources that reach their limit are those with the least limit a weight; the rest
    shares what they leave. The table has one row per source; both windows are over it,
    never over documents.
    """
    total = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = total.withColumn("w", F.element_at(F.array(*[F.lit(int(w)) for w in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int")).cast("long")).withColumn("cap", F.col("source_size") * most)
    by_limit = Window.orderBy((F.col("cap") / F.col("w")), F.col("source").asc_nulls_last())
    below = by_limit.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy(F.lit(1))
    level = (F.sum("source_size").over(everything) * F.lit(float(share)) - F.coalesce(F.sum("cap").over(below), F.lit(0))) / (F.sum("w").over(everything) - F.coalesce(F.sum("w").over(below), F.lit(0)))
    # along the order, the limit is met as long as a source's share of what is left is at least its limit
    filled = ranked.withColumn("level", level).withColumn("nth", F.row_number().over(by_limit)).withColumn("open", F.col("w") * F.col("level") < F.col("cap"))
    shared = F.min(F.when(F.col("open"), F.struct("nth", "level"))).over(everything)
    final = filled.withColumn("final", shared["level"])
    return final.select("source", "source_size", "n_docs", F.when(F.col("open") & F.col("final").isNotNull(), F.least(F.col("w") * F.col("final"), F.col("cap").cast("double"))).otherwise(F.col("cap").cast("double")).alias("target"))


def _chance(*cols: Column) -> Column:
    """Uniform in [0, 1) from a hash: reruns agree."""
    return F.shiftrightunsigned(F.xxhash64(*cols), 11).cast("double") / F.lit(float(1 << 53))


def _meet(units: Column, seed: Column) -> Column:
    """Fold units (size, uid, doc_id, p), largest first, into (left, done): all but one
    get a whole number, and the one left is small."""

    def duel(state: Column, x: Column) -> Column:
        left, p, q = state["left"], x["p"], state["left"]["p"]
        total, u = p + q, _chance(seed, x["uid"], left["uid"])
        under = total < 1
        x_first = F.when(under, u * total < p).otherwise(u * (F.lit(2.0) - total) < F.lit(1.0) - q)
        # under 1 the first keeps the mass and the other leaves with 0; from 1 on the first leaves with 1
        x_stays = F.when(under, x_first).otherwise(~x_first)
        stays = F.when(x_stays, x).otherwise(left)
        leaves = F.when(x_stays, left).otherwise(x)
        out = F.struct(leaves["uid"].alias("uid"), leaves["doc_id"].alias("doc_id"), leaves["size"].alias("size"), F.when(under, 0).otherwise(1).alias("extra"))
        kept = F.struct(stays["size"].alias("size"), stays["uid"].alias("uid"), stays["doc_id"].alias("doc_id"), F.when(under, total).otherwise(total - 1).alias("p"))
        return F.struct(kept.alias("left"), F.concat(state["done"], F.array(out)).alias("done"))

    none = F.expr("cast(array() as array<struct<uid:bigint,doc_id:bigint,size:bigint,extra:int>>)")
    start = F.struct(F.element_at(units, 1).alias("left"), none.alias("done"))
    return F.aggregate(F.slice(units, 2, F.size(units)), start, duel)


def mix(docs: DataFrame, weights: Sequence[int] = (3, 1, 2), share: float = 1.5, most: int = 2, seed: int = 42, text: str = "text", fan: int = FAN) -> DataFrame:
    """``doc_id, uid, source, size, source_size, target, copies``: a row per row of ``docs``.

    ``copies`` is 0 to ``most``, on average what its source's target asks for (a row's expected copies are its source's ideal
    number); over a source, the copies' sizes add up to nearly its
    target, as mass moves first between documents of nearly equal size. Null text: size 0; null
    source: a source of its own, last in order; sources of size 0: no copies;
    an empty table: an empty result. Rows that repeat a document (doc_id, text and source) are one unit with their common
    mass, and their copies differ by one at most. Random choices come from hashes, so reruns agree, and
    groups are dealt by hash, so that a hot source spreads over as many groups as it needs.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col(text)).alias("size"), F.xxhash64("doc_id", F.col(text), "source").alias("uid"))
    sizes = written(rows.groupBy("source", "doc_id", "uid", "size").agg(F.count("*").alias("times")), "mix-sizes")
    wanted = written(targets(sizes, weights, share, most), "mix-targets")
    ideal = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(most)))).otherwise(0.0)
    placed = sizes.join(wanted, sizes["source"].eqNullSafe(wanted["source"])).select("doc_id", "uid", sizes["source"], "size", "times", "source_size", "target", (ideal * F.col("times")).alias("ideal"))
    placed = placed.withColumn("sure", F.floor("ideal")).withColumn("p", F.col("ideal") - F.col("sure"))
    size_class = F.floor(F.log(SIZE_STEP, F.col("size") + 1)).cast("long")
    open_units = placed.filter("p > 0").select("source", size_class.alias("cls"), F.struct("size", "uid", "doc_id", "p").alias("unit"))
    counts = open_units.groupBy("source", "cls").agg(F.ceil(F.count("*") / fan).alias("parts")).withColumnRenamed("source", "s").withColumnRenamed("cls", "c")
    counts = written(counts, "mix-parts")
    level = open_units.join(counts, F.col("source").eqNullSafe(F.col("s")) & (F.col("cls") == F.col("c"))).select("source", "cls", F.expr("pmod(unit.uid, parts)").alias("slot"), "unit")
    slots = counts.agg(F.coalesce(F.max("parts"), F.lit(0))).first()[0]
    classes = counts.agg(F.coalesce(F.max("c"), F.lit(0))).first()[0] + 1
    cls, slot = F.col("cls"), F.col("slot")
    rounds = [(cls, slot)]
    while slots > 1:
        slots = -(-slots // fan)
        rounds.append((cls, F.expr(f"slot div {fan}")))
    while classes > 1:
        classes = -(-classes // fan)
        rounds.append((F.expr(f"cls div {fan}"), F.lit(0).cast("long")))
    done = []
    for to_cls, to_slot in rounds:
        met = level.groupBy("source", to_cls.alias("cls"), to_slot.alias("slot")).agg(F.sort_array(F.collect_list("unit"), asc=False).alias("units"))
        met = written(met.select("source", "cls", "slot", _meet(F.col("units"), F.lit(seed)).alias("met")), "mix-level")
        done.append(met.select("source", F.explode("met.done").alias("d")).select("source", "d.*"))
        level = met.select("source", "cls", "slot", F.col("met.left").alias("unit"))
    done.append(level.select("source", "unit.uid", "unit.doc_id", "unit.size", (_chance(F.lit(seed), F.col("unit.uid")) < F.col("unit.p")).cast("int").alias("extra")))
    extra = done[0]
    for x in done[1:]:
        extra = extra.unionByName(x)
    extra = extra.select(F.col("uid").alias("uid_"), F.col("doc_id").alias("doc_id_"), F.col("source").alias("source_"), "extra")
    same = (F.col("uid") == F.col("uid_")) & F.col("doc_id").eqNullSafe(F.col("doc_id_")) & F.col("source").eqNullSafe(F.col("source_"))
    units = placed.join(extra, same, "left").withColumn("given", F.col("sure") + F.coalesce("extra", F.lit(0)))
    # the rows of a unit share its copies as evenly as whole numbers can
    nth = F.explode(F.sequence(F.lit(1).cast("long"), F.col("times"))).alias("nth")
    each = units.select("doc_id", "uid", "source", "size", "source_size", "target", "given", "times", nth)
    return each.select("doc_id", "uid", "source", "size", "source_size", "target", (F.expr("given div times") + (F.col("nth") <= F.expr("given % times")).cast("long")).cast("int").alias("copies"))


def mixed_rows(docs: DataFrame, text: str = "text", **options) -> DataFrame:
    """Rows of ``docs``, each as often as the mix takes it; all columns as they are, whatever their names. Nulls, repeated
    rows and empty tables as in ``mix``."""
    copies = mix(docs, text=text, **options).groupBy("uid").agg(F.sum("copies").alias("given"), F.count("*").alias("times"))
    copies = written(copies, "mix-copies")
    row = docs.select(F.xxhash64(F.col("doc_id").cast("long"), F.col(text), F.col("source").cast("string")).alias("uid"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.spark_partition_id().alias("part"))
    met = row.join(copies, "uid")
    again = F.explode(F.array_repeat(F.lit(1), F.col("take").cast("int"))).alias("again")
    out = met.filter("times = 1").select("row", F.col("given").alias("take")).select("row", again)
    if copies.filter("times > 1").limit(1).count():
        # repeats are numbered by the task that reads them, and moved up by the numbers of the tasks before
        some = written(met.filter("times > 1"), "mix-repeats")
        sizes = some.groupBy("uid", "part").agg(F.count("*").alias("n"))
        before = sizes.select("uid", "part", (F.sum("n").over(Window.partitionBy("uid").orderBy("part")) - F.col("n")).alias("before"))
        own = F.row_number().over(Window.partitionBy("uid", "part").orderBy(F.lit(1)))
        nth = some.withColumn("own", own).join(before, ["uid", "part"]).withColumn("nth", F.col("own") + F.col("before"))
        take = F.expr("given div times") + (F.col("nth") <= F.expr("given % times")).cast("long")
        out = out.unionByName(nth.select("row", take.alias("take")).select("row", again))
    return out.select("row.*")
