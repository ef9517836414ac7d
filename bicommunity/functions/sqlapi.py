"""SQL views over a graph, and community extraction as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from ..model import CommunityQuery
from ..operators import motifs, score, support
from ..operators.community import kernel


def register(edges: DataFrame, item_kw: DataFrame, synopsis: DataFrame | None = None, communities: DataFrame | None = None) -> None:
    """Views edges, item_kw, wedges, pairs and edge_support; the last three are plain plans, so
    predicates on users and items move below their joins. Views synopsis (node or leaf rows) and communities (answers) if given."""
    for name, table in (("synopsis", synopsis), ("communities", communities)):
        if table is not None:
            table.createOrReplaceTempView(name)
    edges.createOrReplaceTempView("edges")
    item_kw.createOrReplaceTempView("item_kw")
    motifs.wedges(edges).createOrReplaceTempView("wedges")
    score.pairs(edges).createOrReplaceTempView("pairs")
    support.exact(edges).createOrReplaceTempView("edge_support")


@udtf(returnType="center bigint, u bigint, v string, w bigint")
class CommunityOf:
    """``SELECT * FROM community_of(TABLE(candidates) PARTITION BY (center), k, r, sigma)``."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, str, int]] = []
        self.args: tuple[int, int, int] | None = None

    def eval(self, row: Row, k: int, r: int, sigma: int) -> None:
        self.rows.append((row["center"], row["u"], row["v"], row["w"]))
        self.args = (k, r, sigma)

    def terminate(self) -> Iterator[tuple[int, int, str, int]]:
        if not self.rows:
            return
        g = pd.DataFrame(self.rows, columns=["center", "u", "v", "w"])
        k, r, sigma = self.args
        got = kernel(int(g.center[0]), g.u.to_numpy(), g.v.to_numpy().astype(str), g.w.to_numpy(), CommunityQuery(k, r, sigma))
        if got is not None:
            for u, v, w in zip(*got[:3]):
                yield int(g.center[0]), int(u), str(v), int(w)


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("community_of", CommunityOf)


def or_vectors():
    """Grouped-aggregate pandas twin of ``keywords.or_words``, for comparison."""

    @pandas_udf("array<bigint>")
    def merge(vectors: pd.Series) -> list[int]:
        out: list[int] = []
        for v in vectors:
            out = [a | b for a, b in zip(out, v)] if out else list(v)
        return out

    return merge
