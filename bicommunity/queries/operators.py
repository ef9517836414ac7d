"""The surrounding operators, one query each, over the graphs and tables the methods use."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import hops, score
from ..sources import tables
from .base import Registry, edges_cte, pairs_cte
from .graphs import edges, epoch

reg = Registry()
QUERIES, SQL = reg.queries, reg.sql
T = tables.table


@reg("op_scan", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 40 AND l_suppkey < 20")
def op_scan(spark, sf):
    return T(spark, sf, "lineitem").filter("l_quantity >= 40 and l_suppkey < 20").select("l_orderkey", "l_partkey")


@reg("op_project", "SELECT event_id, user_id * 2 + 1 AS odd, upper(event_type) AS kind FROM events")
def op_project(spark, sf):
    return T(spark, sf, "events").select("event_id", (F.col("user_id") * 2 + 1).alias("odd"), F.upper("event_type").alias("kind"))


@reg("op_predicates", "SELECT p_partkey FROM part WHERE (p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#1', 'Brand#2')) OR (p_type LIKE '%ECO%' AND NOT p_size < 45) OR p_name IS NOT DISTINCT FROM NULL")
def op_predicates(spark, sf):
    p = T(spark, sf, "part")
    return p.filter((F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#1", "Brand#2")) | (F.col("p_type").like("%ECO%") & ~(F.col("p_size") < 45)) | F.col("p_name").eqNullSafe(F.lit(None))).select("p_partkey")


_JOIN = "SELECT c_custkey, CAST(count(o_orderkey) AS BIGINT) AS n FROM customer {how} JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey"
for _how, _hint in (("inner", "merge"), ("left", "shuffle_hash")):
    def _join(spark, sf, how=_how, hint=_hint):
        c, o = T(spark, sf, "customer"), T(spark, sf, "orders").select("o_orderkey", "o_custkey")
        return c.join(o.hint(hint), F.col("c_custkey") == F.col("o_custkey"), how).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))

    reg(f"op_join_{_how}", _JOIN.format(how=_how))(_join)


@reg("op_join_right", "SELECT n_name, CAST(count(s_suppkey) AS BIGINT) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def op_join_right(spark, sf):
    return T(spark, sf, "supplier").join(F.broadcast(T(spark, sf, "nation")), F.col("s_nationkey") == F.col("n_nationkey"), "right").groupBy("n_name").agg(F.count("s_suppkey").alias("n"))


@reg("op_join_full", "SELECT coalesce(a.u, b.u) AS u, coalesce(a.n, 0) AS orders, coalesce(b.n, 0) AS events FROM (SELECT o_custkey AS u, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1) a FULL JOIN (SELECT user_id AS u, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1) b ON a.u = b.u")
def op_join_full(spark, sf):
    a = T(spark, sf, "orders").groupBy(F.col("o_custkey").alias("u")).agg(F.count("*").alias("orders"))
    b = T(spark, sf, "events").groupBy(F.col("user_id").alias("u")).agg(F.count("*").alias("events"))
    return a.join(b, "u", "full").select("u", F.coalesce("orders", F.lit(0)).alias("orders"), F.coalesce("events", F.lit(0)).alias("events"))


@reg("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) AND c_mktsegment = (SELECT min(c_mktsegment) FROM customer)")
def op_join_semi(spark, sf):
    c = T(spark, sf, "customer")
    low = c.agg(F.min("c_mktsegment").alias("low"))
    return c.join(T(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").join(F.broadcast(low), F.col("c_mktsegment") == F.col("low")).select("c_custkey")


@reg("op_join_anti", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def op_join_anti(spark, sf):
    return T(spark, sf, "part").join(T(spark, sf, "lineitem").filter("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey")


@reg("op_join_theta", f"WITH {edges_cte('E')} SELECT CAST(count(*) AS BIGINT) AS n FROM edges a JOIN edges b ON a.v = b.v AND a.u < b.u AND a.w <> b.w")
def op_join_theta(spark, sf):
    e = edges(spark, sf, "E")
    a, b = e.select("v", "u", "w"), e.select("v", F.col("u").alias("u2"), F.col("w").alias("w2"))
    return a.join(b, "v").filter("u < u2 and w <> w2").agg(F.count("*").alias("n"))


@reg("op_asof_join", "SELECT c.event_id, p.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') c ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') p ON c.user_id = p.user_id AND c.event_id >= p.event_id")
def op_asof_join(spark, sf):
    """Each purchase with its user's latest view: one sort of both kinds, no range join."""
    e = T(spark, sf, "events").filter("event_type in ('purchase', 'view')")
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    seen = F.last(view, ignorenulls=True).over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0))
    return e.withColumn("last_view", seen).filter("event_type = 'purchase'").select("event_id", "last_view")


@reg("op_range_join", "SELECT a.o_orderkey, CAST(count(*) AS BIGINT) AS n FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate BETWEEN a.o_orderdate - INTERVAL 30 DAY AND a.o_orderdate GROUP BY a.o_orderkey")
def op_range_join(spark, sf):
    o = T(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    b = o.select(F.col("o_custkey").alias("c2"), F.col("o_orderdate").alias("d2"))
    met = o.join(b, (F.col("o_custkey") == F.col("c2")) & F.col("d2").between(F.col("o_orderdate") - F.expr("interval 30 days"), F.col("o_orderdate")))
    return met.groupBy("o_orderkey").agg(F.count("*").alias("n"))


@reg("op_cross_small", "SELECT r_name, n_name FROM region CROSS JOIN nation WHERE r_regionkey <> n_regionkey")
def op_cross_small(spark, sf):
    return T(spark, sf, "nation").crossJoin(F.broadcast(T(spark, sf, "region"))).filter("r_regionkey <> n_regionkey").select("r_name", "n_name")


@reg("op_explode", "SELECT p_partkey, word, CAST(pos - 1 AS INTEGER) AS pos FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word, generate_subscripts(string_split(p_name, ' '), 1) AS pos FROM part)")
def op_explode(spark, sf):
    return T(spark, sf, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word"))


@reg("op_aggregate", "SELECT l_suppkey, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q, min(l_partkey) AS lo, max(l_partkey) AS hi FROM lineitem GROUP BY l_suppkey")
def op_aggregate(spark, sf):
    return T(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("q"), F.min("l_partkey").alias("lo"), F.max("l_partkey").alias("hi"))


@reg("op_distinct", "SELECT event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events GROUP BY event_type")
def op_distinct(spark, sf):
    return T(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@reg("op_approx_distinct")
def op_approx_distinct(spark, sf):
    return T(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@reg("op_conditional", "SELECT CAST(count(*) FILTER (event_type = 'click') AS BIGINT) AS clicks, CAST(sum(CASE WHEN event_type = 'view' THEN user_id ELSE 0 END) AS BIGINT) AS views FROM events")
def op_conditional(spark, sf):
    return T(spark, sf, "events").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.sum(F.when(F.col("event_type") == "view", F.col("user_id")).otherwise(0)).alias("views"))


@reg("op_bits", "SELECT event_type, bit_or(user_id) AS o, bit_and(user_id) AS a, bit_xor(user_id) AS x, CAST(bit_count(bit_or(user_id)) AS INTEGER) AS ones FROM events GROUP BY event_type")
def op_bits(spark, sf):
    return T(spark, sf, "events").groupBy("event_type").agg(F.bit_or("user_id").alias("o"), F.bit_and("user_id").alias("a"), F.bit_xor("user_id").alias("x")).withColumn("ones", F.bit_count("o"))


@reg("op_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def op_collect(spark, sf):
    return T(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names"))


@reg("op_min_by", f"WITH {edges_cte('S')}, {pairs_cte()} SELECT ui, arg_max(uj, score * 100000 - uj) AS partner, max(score) AS best, CAST(quantile_disc(score, 0.5) AS BIGINT) AS median FROM pairs GROUP BY ui")
def op_min_by(spark, sf):
    p = score.pairs(edges(spark, sf, "S"))
    return p.groupBy("ui").agg(F.max_by("uj", F.struct("score", -F.col("uj"))).alias("partner"), F.max("score").alias("best"), F.expr("percentile_disc(0.5) within group (order by score)").cast("bigint").alias("median"))


@reg("op_ranking", "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS n, CAST(rank() OVER d AS INTEGER) AS r, CAST(dense_rank() OVER d AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), d AS (PARTITION BY o_custkey ORDER BY date_trunc('month', o_orderdate))")
def op_ranking(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    d = Window.partitionBy("o_custkey").orderBy(F.date_trunc("month", "o_orderdate"))
    return T(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("n"), F.rank().over(d).alias("r"), F.dense_rank().over(d).alias("dr"), F.ntile(4).over(w).alias("q"))


@reg("op_analytic", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER w AS first, CAST(sum(user_id) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS last4 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def op_analytic(spark, sf):
    w = Window.partitionBy("user_id").orderBy("event_id")
    f = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(-3, 0)
    return T(spark, sf, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.sum("user_id").over(f).alias("last4"))


@reg("op_range_frame", "SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 200 PRECEDING AND CURRENT ROW) AS BIGINT) AS recent FROM events")
def op_range_frame(spark, sf):
    return T(spark, sf, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-200, 0)).alias("recent"))


@reg("op_top", f"WITH {edges_cte('S')}, {pairs_cte()} SELECT ui, uj, score FROM pairs ORDER BY score DESC, ui, uj LIMIT 20 OFFSET 5")
def op_top(spark, sf):
    return score.pairs(edges(spark, sf, "S")).select("ui", "uj", "score").orderBy(F.desc("score"), "ui", "uj").offset(5).limit(20)


@reg("op_sample")
def op_sample(spark, sf):
    return T(spark, sf, "orders").sampleBy("o_orderstatus", {"O": 0.1, "F": 0.1}, seed=1).select("o_orderkey")


@reg("op_sets", "SELECT k, 'i' AS op FROM (SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events) UNION ALL SELECT k, 'e' FROM (SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders) UNION ALL SELECT k, 'a' FROM (SELECT n_regionkey AS k FROM nation EXCEPT ALL SELECT r_regionkey FROM region)")
def op_sets(spark, sf):
    i = T(spark, sf, "orders").select(F.col("o_custkey").alias("k")).intersect(T(spark, sf, "events").select("user_id"))
    e = T(spark, sf, "customer").select(F.col("c_custkey").alias("k")).subtract(T(spark, sf, "orders").select("o_custkey"))
    a = T(spark, sf, "nation").select(F.col("n_regionkey").alias("k")).exceptAll(T(spark, sf, "region").select("r_regionkey"))
    out = i.withColumn("op", F.lit("i")).unionByName(e.withColumn("op", F.lit("e")))
    return out.unionByName(a.select(F.col("k").cast(i.schema["k"].dataType), F.lit("a").alias("op")))


@reg("op_pivot", "SELECT user_id, CAST(count(*) FILTER (event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (event_type = 'view') AS BIGINT) AS view FROM events GROUP BY user_id")
def op_pivot(spark, sf):
    wide = T(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return wide.select("user_id", *[F.coalesce(c, F.lit(0)).cast("bigint").alias(c) for c in ("click", "view")])


@reg("op_unpivot", "SELECT p_partkey, 'brand' AS what, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part")
def op_unpivot(spark, sf):
    return T(spark, sf, "part").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("type")).unpivot("p_partkey", ["brand", "type"], "what", "value")


@reg("op_cube", "SELECT r_name, c_mktsegment, CAST(count(*) AS BIGINT) AS n, CAST(grouping(r_name) * 2 + grouping(c_mktsegment) AS BIGINT) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)")
def op_cube(spark, sf):
    c = T(spark, sf, "customer").join(F.broadcast(T(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(T(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@reg("op_rollup", "SELECT n_regionkey, n_nationkey, CAST(count(*) AS BIGINT) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)")
def op_rollup(spark, sf):
    return T(spark, sf, "supplier").join(F.broadcast(T(spark, sf, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


@reg("op_strings", "SELECT p_partkey, lower(p_brand) || '-' || substr(p_type, 1, 3) AS code, md5(p_name) AS h, regexp_extract(p_brand, '([0-9]+)', 1) AS digits FROM part")
def op_strings(spark, sf):
    return T(spark, sf, "part").select("p_partkey", F.concat_ws("-", F.lower("p_brand"), F.substring("p_type", 1, 3)).alias("code"), F.md5("p_name").alias("h"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"))


@reg("op_dates", "SELECT strftime(o_orderdate, '%Y-%m') AS month, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1, 2")
def op_dates(spark, sf):
    return T(spark, sf, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.year("o_orderdate").alias("y")).agg(F.count("*").alias("n"))


@reg("op_math", "SELECT l_orderkey, l_linenumber, CAST(floor(sqrt(l_quantity)) AS BIGINT) AS root, CAST(least(l_partkey, l_suppkey) AS BIGINT) AS lo, CAST(greatest(l_partkey, l_suppkey) AS BIGINT) AS hi, CAST(l_partkey % 7 AS BIGINT) AS m FROM lineitem")
def op_math(spark, sf):
    return T(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.floor(F.sqrt("l_quantity")).alias("root"), F.least("l_partkey", "l_suppkey").alias("lo"), F.greatest("l_partkey", "l_suppkey").alias("hi"), F.pmod("l_partkey", F.lit(7)).cast("bigint").alias("m"))


@reg("op_arrays", "SELECT p_partkey, array_to_string(list_sort(list_distinct(list_filter(string_split(p_name, ' '), lambda x: length(x) > 4))), ',') AS long, list_contains(string_split(p_name, ' '), 'small') AS small FROM part")
def op_arrays(spark, sf):
    words = F.split("p_name", " ")
    return T(spark, sf, "part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(F.filter(words, lambda x: F.length(x) > 4))), ",").alias("long"), F.array_contains(words, "small").alias("small"))


@reg("op_maps", "SELECT p_partkey, p_brand AS brand, CAST(2 AS INTEGER) AS n FROM part")
def op_maps(spark, sf):
    m = F.create_map(F.lit("brand"), F.col("p_brand"), F.lit("type"), F.col("p_type"))
    return T(spark, sf, "part").select("p_partkey", m["brand"].alias("brand"), F.size(F.map_keys(m)).alias("n"))


@reg("op_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def op_json(spark, sf):
    return T(spark, sf, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@reg("op_structs", "SELECT event_id, coalesce(nullif(event_type, 'view'), 'seen') AS kind FROM events")
def op_structs(spark, sf):
    s = F.struct("event_id", F.nullif("event_type", F.lit("view")).alias("kind"))
    return T(spark, sf, "events").select(s.alias("s")).select("s.event_id", F.coalesce("s.kind", F.lit("seen")).alias("kind"))


@reg("op_recursive", f"WITH RECURSIVE {edges_cte('E')}, walk(u, d) AS (SELECT 1::BIGINT, 0 UNION SELECT b.u, walk.d + 1 FROM walk JOIN edges a ON a.u = walk.u JOIN edges b ON a.v = b.v WHERE walk.d < 2) SELECT u, CAST(min(d) AS INTEGER) AS d FROM walk GROUP BY u")
def op_recursive(spark, sf):
    """Reach from one user, a step at a time. Spark's recursive SQL only has UNION ALL, which counts every way to a user and
    passes the engine's limit of rows; here a step starts from the users that are new."""
    one = spark.range(1).select(F.lit(1).cast("bigint").alias("center"))
    near = hops.users(edges(spark, sf, "E"), 2, one).select("u", F.expr("dist div 2").cast("int").alias("d"))
    return near.unionByName(one.select(F.col("center").alias("u"), F.lit(0).alias("d"))).distinct()


@reg("op_subquery", "SELECT o_orderkey FROM orders o WHERE o_orderdate = (SELECT max(o_orderdate) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def op_subquery(spark, sf):
    view = f"orders_{abs(hash(sf)) % 10**8}"
    T(spark, sf, "orders").createOrReplaceTempView(view)
    return spark.sql(f"SELECT o_orderkey FROM {view} o WHERE o_orderdate = (SELECT max(o_orderdate) FROM {view} i WHERE i.o_custkey = o.o_custkey)")


@reg("op_sessions_batch", "WITH x AS (SELECT user_id AS u, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events), y AS (SELECT u, ts, sum(fresh) OVER (PARTITION BY u ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM x) SELECT CAST(u AS BIGINT) AS u, epoch_us(min(ts)) // 1000000 AS start, CAST(count(*) AS BIGINT) AS n FROM y GROUP BY u, s")
def op_sessions_batch(spark, sf):
    from ..operators.window import sessions

    return sessions(tables.graph(spark, sf, "E").interactions, "1 hour").select("u", epoch("start").alias("start"), "n")


@reg("op_views", f"WITH {edges_cte('E')}, {pairs_cte()} SELECT ui, uj, score FROM pairs WHERE ui < 5")
def op_views(spark, sf):
    from ..functions import sqlapi

    sqlapi.register(edges(spark, sf, "E"), tables.graph(spark, sf, "E").item_kw)
    return spark.sql("SELECT ui, uj, score FROM pairs WHERE ui < 5")
