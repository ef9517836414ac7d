"""Synthetic graphs of six kinds: two degree laws by three keyword laws."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Mean and deviation of the weights for each range.
WEIGHTS = {(1, 2): (1.5, 0.25), (1, 3): (2.0, 0.5), (1, 4): (2.5, 0.75)}


def _uniform(seed: int, *cols: str | Column) -> Column:
    """Uniform in (0, 1) by hash, so that reruns and any partitioning agree."""
    h = F.xxhash64(F.lit(seed), *cols)
    return (F.shiftrightunsigned(h, 11).cast("double") + 0.5) / F.lit(float(1 << 53))


def _normal(seed: int, *cols: str | Column) -> Column:
    return F.sqrt(-2 * F.log(_uniform(seed, *cols))) * F.cos(2 * F.pi() * _uniform(seed + 1, *cols))


def _keyword(law: str, domain: int, seed: int, *cols: str | Column) -> Column:
    """A keyword number in [0, domain)."""
    u = _uniform(seed, *cols)
    if law == "uniform":
        x = F.floor(u * domain)
    elif law == "lognormal":
        x = F.floor(F.exp(_normal(seed, *cols)) * domain / 10)
    elif law == "pareto":
        x = F.floor((F.pow(u, F.lit(-1 / 1.5)) - 1) * domain / 10)
    else:
        raise ValueError(law)
    return F.pmod(x.cast("bigint"), F.lit(domain))


def attach_keywords(items: DataFrame, law: str = "lognormal", domain: int = 500, per_item: int = 3, seed: int = 7) -> DataFrame:
    """``v, kw``: ``per_item`` draws by item (repeats fall together)."""
    drawn = items.select("v").distinct().select("v", F.explode(F.sequence(F.lit(1), F.lit(per_item))).alias("j"))
    return drawn.select("v", _keyword(law, domain, seed, "v", "j").cast("string").alias("kw")).distinct()


def degree_column(law: str, mean: float, seed: int, most: int) -> Column:
    u = _uniform(seed, "u")
    if law == "powerlaw":
        d = F.pow(1 - u, F.lit(-1 / 1.5)) * (mean / 3)
    elif law == "beta":
        # of four uniforms the second smallest follows the Beta law with parameters 2 and 3, of mean 2/5
        second = F.sort_array(F.array(u, *[_uniform(seed + j, "u") for j in (5, 6, 7)]))[1]
        d = second * (mean * 5 / 2)
    else:
        raise ValueError(law)
    return F.least(F.greatest(F.round(d), F.lit(1)), F.lit(most)).cast("int")


def synthetic(spark: SparkSession, n_users: int = 25_000, n_items: int = 25_000, degree: str = "powerlaw", keyword: str = "uniform", weight_range: tuple[int, int] = (1, 2), kw_per_item: int = 3, domain: int = 500, mean_degree: float = 6.0, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Edges and item keywords. Users get degrees by the law, neighbours at random, and
    weights from a Gaussian rounded and clipped to the range; repeated neighbours fall together."""
    users = spark.range(n_users).select(F.col("id").alias("u"))
    items = spark.range(n_items).select(F.col("id").alias("v"))
    return _drawn(users, items, 0, n_items, degree, keyword, weight_range, kw_per_item, domain, mean_degree, seed)


def synthetic_on(users: DataFrame, items: DataFrame, degree: str = "powerlaw", keyword: str = "uniform", weight_range: tuple[int, int] = (1, 2), kw_per_item: int = 3, domain: int = 500, mean_degree: float = 6.0, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """The same between given users (u) and items (v), both of whole numbers. A neighbour is drawn from the range of the items; a number in
    it that no item has gives no edge."""
    ends = items.agg(F.min("v").alias("low"), F.max("v").alias("high")).first()
    low, n = (0, 0) if ends.low is None else (ends.low, ends.high - ends.low + 1)
    edges, kw = _drawn(users, items, low, n, degree, keyword, weight_range, kw_per_item, domain, mean_degree, seed)
    return edges.join(items.select(F.col("v").cast("string").alias("v")).distinct(), "v", "left_semi").select("u", "v", "w"), kw


def _drawn(users: DataFrame, items: DataFrame, low: int, n_items: int, degree: str, keyword: str, weight_range: tuple[int, int], kw_per_item: int, domain: int, mean_degree: float, seed: int) -> tuple[DataFrame, DataFrame]:
    mean, sd = WEIGHTS[weight_range]
    drawn = users.select("u", F.explode(F.sequence(F.lit(1), degree_column(degree, mean_degree, seed, n_items))).alias("j"))
    placed = drawn.select("u", (F.floor(_uniform(seed + 11, "u", "j") * n_items) + low).cast("bigint").cast("string").alias("v")).distinct()
    w = F.greatest(F.least(F.round(F.lit(mean) + F.lit(sd) * _normal(seed + 23, "u", "v")), F.lit(weight_range[1])), F.lit(weight_range[0]))
    edges = placed.select("u", "v", w.cast("bigint").alias("w"))
    return edges, attach_keywords(items.select(F.col("v").cast("string").alias("v")), keyword, domain, kw_per_item, seed + 31)
