"""Graphs on the given tables: interactions (u, v, ts, seq) and item keywords (v, kw)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import build_edges


@dataclass(frozen=True)
class Graph:
    name: str
    interactions: DataFrame
    item_kw: DataFrame
    weight: str = "count"

    @property
    def edges(self) -> DataFrame:
        return build_edges(self.interactions, weight=self.weight)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def events_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """E: users and the kinds of event they cause."""
    e = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("bigint").alias("k"))
    e = e.filter("k is not null")
    v = F.concat_ws(":", "event_type", F.col("k").cast("string"))
    inter = e.select(F.col("user_id").cast("bigint").alias("u"), v.alias("v"), "ts", F.col("event_id").cast("bigint").alias("seq"))
    words = F.array(F.col("event_type"), F.concat(F.lit("d"), F.expr("k div 10").cast("string")), F.concat(F.lit("m"), (F.col("k") % 7).cast("string")))
    return Graph("E", inter, e.select("event_type", "k").distinct().select(v.alias("v"), F.explode(words).alias("kw")).distinct())


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])


def _part_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand", "p_type")
    words = F.concat(F.array("p_brand", "p_type"), F.split("p_name", " "))
    return part.select(F.col("p_partkey").cast("string").alias("v"), F.explode(words).alias("kw")).distinct()


def customer_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """C: customers and the parts they order."""
    inter = _lines(spark, sf_dir).select(F.col("o_custkey").cast("bigint").alias("u"), F.col("l_partkey").cast("string").alias("v"), F.col("o_orderdate").alias("ts"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("bigint").alias("seq"), "l_quantity")
    return Graph("C", inter, _part_words(spark, sf_dir))


def supplier_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """S: suppliers and the parts they sell."""
    inter = _lines(spark, sf_dir).select(F.col("l_suppkey").cast("bigint").alias("u"), F.col("l_partkey").cast("string").alias("v"), F.col("o_orderdate").alias("ts"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("bigint").alias("seq"), "l_quantity")
    return Graph("S", inter, _part_words(spark, sf_dir))


def brand_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """N: customers and kinds of part; few items, each with very many users."""
    part = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    lines = _lines(spark, sf_dir).join(part, F.col("l_partkey") == F.col("p_partkey"))
    v = F.concat_ws("/", "p_brand", "p_type")
    inter = lines.select(F.col("o_custkey").cast("bigint").alias("u"), v.alias("v"), F.col("o_orderdate").alias("ts"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("bigint").alias("seq"))
    return Graph("N", inter, part.select(v.alias("v"), F.explode(F.array("p_brand", "p_type")).alias("kw")).distinct())


def word_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """W: documents and their words of six letters or more."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    words = docs.select(F.col("doc_id").cast("bigint").alias("u"), "lang", F.posexplode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}{6,}"), 0)).alias("seq", "v"))
    inter = words.select("u", "v", F.lit(None).cast("timestamp").alias("ts"), F.col("seq").cast("bigint").alias("seq"))
    first = words.groupBy("v").agg(F.min_by("lang", "u").alias("lang"))
    kw = first.select("v", F.explode(F.array_compact(F.array(F.col("lang"), F.concat(F.lit("n"), F.length("v").cast("string")), F.substring("v", 1, 1)))).alias("kw"))
    return Graph("W", inter, kw.distinct())


def vector_graph(spark: SparkSession, sf_dir: str, m: int = 6) -> Graph:
    """V: vectors and the places of their ``m`` largest coordinates."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("u"), "embedding")
    ranked = F.slice(F.array_sort(F.transform("embedding", lambda x, i: F.struct((-x).alias("x"), i.alias("i")))), 1, m)
    inter = e.select("u", F.explode(ranked).alias("c")).select("u", F.col("c.i").cast("string").alias("v"), F.lit(None).cast("timestamp").alias("ts"), F.col("c.i").cast("bigint").alias("seq"))
    kw = inter.select("v").distinct().select("v", F.concat(F.lit("i"), F.expr("cast(v as bigint) div 8").cast("string")).alias("kw"))
    return Graph("V", inter, kw)


def conversation_graph(spark: SparkSession, sf_dir: str) -> Graph:
    """P: conversations and their words."""
    rows = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("bigint").alias("u"), "turn", "role", "text")
    words = rows.select("u", "turn", "role", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}{4,}"), 0)).alias("v"))
    inter = words.select("u", "v", F.lit(None).cast("timestamp").alias("ts"), F.col("turn").cast("bigint").alias("seq"))
    return Graph("P", inter, words.select("v", F.col("role").alias("kw")).distinct())


GRAPHS = {"E": events_graph, "C": customer_graph, "S": supplier_graph, "N": brand_graph, "W": word_graph, "V": vector_graph, "P": conversation_graph}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return GRAPHS[name](spark, sf_dir)


def integer_keywords(items: DataFrame, domain: int, per_item: int) -> DataFrame:
    """Portable keywords for items with numeric names, for sweeps over domain and number."""
    j = F.explode(F.sequence(F.lit(0), F.lit(per_item - 1))).alias("j")
    return items.select("v", j).select("v", ((F.col("v").cast("bigint") * 7919 + F.col("j") * 104729) % domain).cast("string").alias("kw")).distinct()
