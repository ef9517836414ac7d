"""The synopsis: per-user bounds over their surroundings, in a tree of id levels.

Leaf rows hold, for each radius r, the or of the keyword vectors of the items in a user's 2r-hop
sub-graph, the greatest support bound of its edges and the greatest score of its pairs.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import CommunityQuery
from . import hops, keywords, score
from .motifs import wedges

#: Edges that carry the vectors of one batch.
ROWS = 1 << 21
LEAF = ("u", "r", "bv", "ub_sup", "ub_score")


def _zeros(bits: int):
    return F.array_repeat(F.lit(0).cast("bigint"), bits // keywords.WORD_BITS)


def leaf_exact(edges: DataFrame, vectors: DataFrame, sup: DataFrame, pairs: DataFrame, r_max: int = 3, bits: int = 256, centers: DataFrame | None = None) -> DataFrame:
    """Leaf rows by definition, from materialised hops. The score bound is over all
    pairs of users in the hop."""
    out = None
    for r in range(1, r_max + 1):
        sub = hops.subgraph(edges, r, centers)
        near = hops.users(edges, r, centers).select("center", "u")
        items = sub.select("center", "v").distinct().join(vectors, "v").groupBy("center").agg(keywords.or_words("bv", bits).alias("bv"))
        most = sub.join(sup, ["u", "v"]).groupBy("center").agg(F.max("sup").alias("ub_sup"))
        ends = near.withColumnRenamed("u", "ui").join(pairs.select("ui", "uj", "score"), "ui").join(near.withColumnRenamed("u", "uj"), ["center", "uj"])
        best = ends.groupBy("center").agg(F.max("score").alias("ub_score"))
        row = near.select("center").distinct().join(items, "center", "left").join(most, "center", "left").join(best, "center", "left")
        row = row.select(F.col("center").alias("u"), F.lit(r).alias("r"), F.coalesce("bv", _zeros(bits)).alias("bv"), F.coalesce("ub_sup", F.lit(0).cast("bigint")).alias("ub_sup"), F.coalesce("ub_score", F.lit(0).cast("bigint")).alias("ub_score"))
        out = row if out is None else out.unionByName(row)
    return out


def item_values(edges: DataFrame, vectors: DataFrame, sup: DataFrame, pairs: DataFrame, bits: int = 256, hub_degree: int | None = None) -> DataFrame:
    """``v, bv, ub_sup, ub_score``: keyword vector, greatest support of an edge and greatest
    score of a pair on the item."""
    top = sup.groupBy("v").agg(F.max("sup").alias("ub_sup"))
    score = wedges(edges, hub_degree).join(pairs.select("ui", "uj", "score"), ["ui", "uj"]).groupBy("v").agg(F.max("score").alias("ub_score"))
    return top.join(vectors, "v", "left").join(score, "v", "left").select("v", F.coalesce("bv", _zeros(bits)).alias("bv"), "ub_sup", F.coalesce("ub_score", F.lit(0).cast("bigint")).alias("ub_score"))


def items_of_bounds(bounds: DataFrame, vectors: DataFrame, bits: int = 256) -> DataFrame:
    """The same from ``u, v, sup, best`` of all edges (``bounds.edge_bounds``), without pairs or wedges."""
    top = bounds.groupBy("v").agg(F.max("sup").alias("ub_sup"), F.max("best").alias("ub_score"))
    return top.join(vectors, "v", "left").select("v", F.coalesce("bv", _zeros(bits)).alias("bv"), "ub_sup", "ub_score")


def changed_items(old: DataFrame, new: DataFrame, changes: DataFrame) -> DataFrame:
    """``v``: items whose values can differ after changed edges: those of the changes and those that a pair shares whose
    sums differ (a support on an item moves only with a pair on that item)."""
    moved = score.pair_changes(old, changes).select("ui", "uj")
    near = new.join(moved.select(F.explode(F.array("ui", "uj")).alias("u")).distinct(), "u", "left_semi").select("u", "v")
    shared = moved.join(near.select(F.col("u").alias("ui"), "v"), "ui").join(near.select(F.col("u").alias("uj"), "v"), ["uj", "v"]).select("v")
    return shared.unionByName(changes.select("v")).distinct()


def maintain_items(items: DataFrame, new: DataFrame, vectors: DataFrame, sup: DataFrame, pairs: DataFrame, touched: DataFrame, bits: int = 256, hub_degree: int | None = None) -> DataFrame:
    """Item values after changes: those of the ``touched`` items are worked out again, the others stay."""
    own = new.join(touched, "v", "left_semi")
    again = item_values(own, vectors, sup.join(touched, "v", "left_semi"), pairs, bits, hub_degree)
    return items.join(touched, "v", "left_anti").select("v", "bv", "ub_sup", "ub_score").unionByName(again)


def _gather(link: DataFrame, values: DataFrame, by: str, to: str, bits: int) -> DataFrame:
    return link.join(values, by).groupBy(to).agg(keywords.or_words("bv", bits).alias("bv"), F.max("ub_sup").alias("ub_sup"), F.max("ub_score").alias("ub_score"))


def _gathered(link: DataFrame, values: DataFrame, by: str, to: str, bits: int, batches: int) -> DataFrame:
    """The same as a written table: each edge carries a vector through a shuffle, so they go in batches of the receiving side, and a batch's
    shuffle files go before the next."""
    from ..store import release, shared_dir, written

    if batches <= 1:
        return written(_gather(link, values, by, to, bits), "leaf")
    spark, path = link.sparkSession, f"{shared_dir(link.sparkSession)}/leaf-{uuid.uuid4().hex}"
    for i in range(batches):
        rows = _gather(link.filter(F.pmod(F.xxhash64(to), F.lit(batches)) == i), values, by, to, bits)
        rows.write.mode("append").parquet(path)
        schema = rows.schema
        del rows
        release(spark)
    return spark.read.schema(schema).parquet(path)


def leaf_propagated(edges: DataFrame, items: DataFrame, r_max: int = 3, bits: int = 256, centers: DataFrame | None = None) -> DataFrame:
    """Leaf rows by passing item values to users and back, one round a radius.

    Or and max don't mind repeats, so no hop is materialised. Vectors and support bounds equal
    those of ``leaf_exact``; the score bound covers just the pairs that share an item of the hop: lower,
    and still safe.
    """
    link = edges.select("u", "v")
    batches = -(-link.count() // ROWS) if centers is None else 1
    now, out = items, None
    for r in range(1, r_max + 1):
        own = _gathered(link, now, "v", "u", bits, batches)
        row = own if centers is None else own.join(centers.select(F.col("center").alias("u")).distinct(), "u", "left_semi")
        row = row.select("u", F.lit(r).alias("r"), "bv", "ub_sup", "ub_score")
        out = row if out is None else out.unionByName(row)
        if r < r_max:
            now = _gathered(link, own, "u", "v", bits, batches) if batches > 1 else _gather(link, own, "u", "v", bits)
    return out


def partition(leaf: DataFrame, gamma: int = 16, how: str = "scalable") -> DataFrame:
    """``u, leaf_id``: users sorted by their added score bounds, ``gamma`` to a leaf."""
    total = leaf.groupBy("u").agg(F.sum("ub_score").alias("total"))
    if how == "global":
        return total.select("u", F.expr(f"(row_number() over (order by total desc, u) - 1) div {gamma}").alias("leaf_id"))
    from ..store import written

    part = written(total.repartitionByRange(F.desc("total"), F.col("u")).withColumn("part", F.spark_partition_id()), "leaf-order")
    own = part.withColumn("own", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("total"), "u")) - 1)
    sizes = part.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    return own.join(F.broadcast(before), "part").select("u", F.expr(f"(own + before) div {gamma}").cast("bigint").alias("leaf_id"))


def build(leaf: DataFrame, placed: DataFrame, gamma: int = 16, bits: int = 256) -> tuple[DataFrame, DataFrame]:
    """Leaf table (u, leaf_id, ...) and node table (level, node_id, parent_id, r, ...).

    Level 0 has one node a leaf; a node's parent is its id divided by gamma, up to one
    root. The range of leaves keeps equal bounds together, so row groups are skipped by statistics.
    """
    leaves = leaf.join(placed, "u").select("u", "leaf_id", "r", "bv", "ub_sup", "ub_score")

    most = placed.agg(F.max("leaf_id")).first()[0]
    level, now = 0, _up(leaves, "leaf_id", 0, gamma, bits)
    nodes = now
    while most and most > 0:
        most //= gamma
        level += 1
        now = _up(now, "parent_id", level, gamma, bits)
        nodes = nodes.unionByName(now)
    return leaves, nodes


def _up(rows: DataFrame, key: str, level: int, gamma: int, bits: int) -> DataFrame:
    """Node rows of a level from the rows below."""
    merged = rows.groupBy(F.col(key).alias("node_id"), "r").agg(keywords.or_words("bv", bits).alias("bv"), F.max("ub_sup").alias("ub_sup"), F.max("ub_score").alias("ub_score"))
    return merged.select(F.lit(level).alias("level"), "node_id", F.expr(f"node_id div {gamma}").cast("bigint").alias("parent_id"), "r", "bv", "ub_sup", "ub_score")


def refresh(leaves: DataFrame, nodes: DataFrame, leaf: DataFrame, placed: DataFrame, touched: DataFrame, gamma: int = 16, bits: int = 256) -> tuple[DataFrame, DataFrame]:
    """Leaf and node tables after the rows of the ``touched`` users (u) have changed, come or gone: only the path from their
    leaves to the root is merged again. ``placed`` may have new users, but none that moved."""
    from ..store import written

    fresh = leaf.join(touched, "u", "left_semi").join(placed, "u").select("u", "leaf_id", "r", "bv", "ub_sup", "ub_score")
    now = written(leaves.join(touched, "u", "left_anti").unionByName(fresh), "leaves")
    dirty = leaves.join(touched, "u", "left_semi").select("leaf_id").unionByName(fresh.select("leaf_id")).distinct()
    dirty = written(dirty.select(F.col("leaf_id").alias("node_id")), "dirty")
    depth = nodes.agg(F.max("level")).first()[0] or 0
    below, key, out = now, "leaf_id", None
    for level in range(depth + 1):
        again = _up(below.join(dirty.withColumnRenamed("node_id", key), key, "left_semi"), key, level, gamma, bits)
        rows = written(nodes.filter(F.col("level") == level).join(dirty, "node_id", "left_anti").select(*again.columns).unionByName(again), "nodes")
        out = rows if out is None else out.unionByName(rows)
        below, key = rows, "parent_id"
        dirty = dirty.select(F.expr(f"node_id div {gamma}").cast("bigint").alias("node_id")).distinct()
    return now, out


def inverted(placed: DataFrame, gamma: int = 16) -> DataFrame:
    """``u, path``: node ids from the root down to the user's leaf."""
    most = placed.agg(F.max("leaf_id")).first()[0] or 0
    depth = 1
    while most > 0:
        most //= gamma
        depth += 1
    ids = [F.expr(f"leaf_id div {gamma ** i}").cast("bigint") for i in reversed(range(depth))]
    return placed.select("u", F.array(*ids).alias("path"))


def size_report(leaves: DataFrame, nodes: DataFrame, bits: int = 256) -> DataFrame:
    """``level, entries, bytes``: level -1 holds users; an entry has a vector and two numbers,
    an inner one also a pointer."""
    users = leaves.agg(F.count("*").alias("entries")).select(F.lit(-1).alias("level"), "entries", (F.col("entries") * (bits // 8 + 16)).alias("bytes"))
    inner = nodes.groupBy("level").agg(F.count("*").alias("entries")).select("level", "entries", (F.col("entries") * (bits // 8 + 24)).alias("bytes"))
    return users.unionByName(inner)


def prune_nodes(rows: DataFrame, q: CommunityQuery, bits: int = 256) -> DataFrame:
    """Rows (nodes or users) that may hold an answer: keyword, support and score bound at the radius."""
    sigma = q.sigma if q.score_rule == "pair" else 0
    return rows.filter((F.col("r") == q.r) & keywords.overlaps(F.col("bv"), keywords.query_vector(q.keywords, bits)) & (F.col("ub_sup") >= q.k) & (F.col("ub_score") >= sigma))


def traverse(leaves: DataFrame, nodes: DataFrame, q: CommunityQuery, bits: int = 256, log: list | None = None) -> DataFrame:
    """``center``: users that pass, level by level from the root.

    The children of surviving nodes are the next frontier; inner levels are gamma
    times smaller each, and a level's ids are joined, never collected. ``log`` gets (level, entries, kept).
    """
    depth = nodes.agg(F.max("level")).first()[0]
    if depth is None:
        return leaves.select(F.col("u").alias("center")).limit(0)
    frontier = None
    for level in range(depth, -1, -1):
        rows = nodes.filter((F.col("level") == level) & (F.col("r") == q.r))
        if frontier is not None:
            rows = rows.join(frontier, "parent_id", "left_semi")
        kept = prune_nodes(rows, q, bits)
        if log is not None:
            log.append((level, rows.count(), kept.count()))
        frontier = kept.select(F.col("node_id").alias("parent_id"))
    rows = leaves.filter(F.col("r") == q.r).join(frontier.withColumnRenamed("parent_id", "leaf_id"), "leaf_id", "left_semi")
    kept = prune_nodes(rows, q, bits)
    if log is not None:
        log.append((-1, rows.count(), kept.count()))
    return kept.select(F.col("u").alias("center"))


def affected(old: DataFrame, new: DataFrame, changes: DataFrame, r_max: int) -> DataFrame:
    """``center``: users within ``r_max`` steps of a changed edge's user, before or after: what
    goes is seen only in the old graph, what comes only in the new one."""
    touched = changes.select(F.col("u").alias("center")).distinct()
    before = hops.users(old, r_max, touched).select(F.col("u").alias("center"))
    after = hops.users(new, r_max, touched).select(F.col("u").alias("center"))
    return before.unionByName(after).unionByName(touched).distinct()


def maintain(leaf: DataFrame, old: DataFrame, new: DataFrame, changes: DataFrame, items: DataFrame, r_max: int = 3, bits: int = 256, policy: str = "exact") -> DataFrame:
    """Leaf rows after changed edges (u, v, w_old, w_new); ``items``: values on the new graph.

    ``exact`` works out the affected users' rows again. Bounds only move on items of
    the changed users, so no one farther is affected. ``merge`` only ors and maxes the
    changed items' values into the affected rows: it never drops what has gone, and with a new
    edge it misses what has come into reach behind it, so it is safe for growing weights of edges
    that were there before.
    """
    if policy == "merge":
        touched = changes.select(F.col("u").alias("center"), "v").distinct()
        gain = touched.join(items, "v").groupBy("center").agg(keywords.or_words("bv", bits).alias("gbv"), F.max("ub_sup").alias("gsup"), F.max("ub_score").alias("gscore"))
        out = None
        for r in range(1, r_max + 1):
            near = hops.users(new, r, touched.select("center")).select("center", "u")
            got = near.join(gain, "center").groupBy("u").agg(keywords.or_words("gbv", bits).alias("gbv"), F.max("gsup").alias("gsup"), F.max("gscore").alias("gscore"))
            row = leaf.filter(F.col("r") == r).join(got, "u", "left")
            merged = F.when(F.col("gbv").isNull(), F.col("bv")).otherwise(F.zip_with("bv", "gbv", lambda a, b: a.bitwiseOR(b)))
            row = row.select("u", "r", merged.alias("bv"), F.greatest("ub_sup", "gsup").alias("ub_sup"), F.greatest("ub_score", "gscore").alias("ub_score"))
            out = row if out is None else out.unionByName(row)
        return out
    touched = affected(old, new, changes, r_max)
    again = leaf_propagated_near(new, items, touched, r_max, bits)
    gone = leaf.join(touched.withColumnRenamed("center", "u"), "u", "left_anti")
    return gone.select(*LEAF).unionByName(again.select(*LEAF))


def leaf_propagated_near(edges: DataFrame, items: DataFrame, centers: DataFrame, r_max: int, bits: int) -> DataFrame:
    """Leaf rows of some users: propagation over just the edges in their reach."""
    near = hops.users(edges, max(0, r_max - 1), centers).select("u").distinct() if r_max > 1 else centers.select(F.col("center").alias("u")).distinct()
    reach = edges.join(near, "u", "left_semi")
    return leaf_propagated(reach, items, r_max, bits, centers)


def add_users(placed: DataFrame, leaf: DataFrame, fresh: DataFrame) -> DataFrame:
    """Place new users into the leaf whose mean added score bound is closest.

    Leaves and new users are sorted together in ranges, and each user looks at its neighbours in order, so no user is compared
    with every leaf; a range hands on its last and first leaf, which is one row a range. ``fresh``: leaf rows of the new users.
    """
    from ..store import written

    total = leaf.groupBy("u").agg(F.sum("ub_score").alias("total"))
    means = placed.join(total, "u").groupBy("leaf_id").agg(F.avg("total").alias("x"))
    new = fresh.groupBy("u").agg(F.sum("ub_score").cast("double").alias("x"))
    line = means.select("x", "leaf_id", F.lit(None).cast("bigint").alias("u")).unionByName(new.select("x", F.lit(None).cast("bigint").alias("leaf_id"), "u"))
    spot = F.when(F.col("leaf_id").isNotNull(), F.struct("x", "leaf_id"))
    order = [F.col("x"), F.col("leaf_id").asc_nulls_last(), F.col("u")]
    line = written(line.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "line")
    ends = line.groupBy("part").agg(F.max(spot).alias("last"), F.min(spot).alias("first"))
    before = F.last("last", ignorenulls=True).over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    after = F.first("first", ignorenulls=True).over(Window.orderBy("part").rowsBetween(1, Window.unboundedFollowing))
    carried = ends.select("part", before.alias("before"), after.alias("after"))
    inside = Window.partitionBy("part").orderBy(*order)
    below = F.last(spot, ignorenulls=True).over(inside.rowsBetween(Window.unboundedPreceding, 0))
    above = F.first(spot, ignorenulls=True).over(inside.rowsBetween(0, Window.unboundedFollowing))
    seen = line.withColumn("lo", below).withColumn("hi", above).filter("u is not null").join(F.broadcast(carried), "part")
    seen = seen.withColumn("lo", F.coalesce("lo", "before")).withColumn("hi", F.coalesce("hi", "after"))
    pick = F.when(F.col("hi").isNull() | (F.col("x") - F.col("lo.x") <= F.col("hi.x") - F.col("x")), F.col("lo.leaf_id")).otherwise(F.col("hi.leaf_id"))
    return placed.unionByName(seen.select("u", pick.alias("leaf_id")))


def rebalance(placed: DataFrame, leaf: DataFrame, gamma: int = 16) -> DataFrame:
    """Placement as it is, or cut anew if a leaf holds more than twice ``gamma`` users."""
    most = placed.groupBy("leaf_id").count().agg(F.max("count")).first()[0]
    return partition(leaf, gamma) if most and most > 2 * gamma else placed
