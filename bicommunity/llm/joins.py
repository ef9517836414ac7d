"""Joins with tables of groups where one group may hold a large share of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key with a thousandth of all rows (and LEAST at least) is hot: there are at most a thousand such keys, whatever
#: the input.
SHARE, LEAST = 1000, 1024


def met(rows: DataFrame, table: DataFrame, on: list[str], weight: str, total: int, least: int | None = None, how: str = "inner") -> DataFrame:
    """``rows`` joined with ``table``, which has each key once and says in ``weight`` how many rows it has of
    ``total``. Hot keys are broadcast, a thousand at most; the others are merged. With ``how='left'``
    rows with a null key go round the join."""
    limit = max(LEAST if least is None else least, total // SHARE)
    hot, cold = table.filter(F.col(weight) >= limit), table.filter(F.col(weight) < limit).drop(weight)
    some = hot.limit(1).count() > 0
    out = None
    if how == "left":
        null = " or ".join(f"{c} is null" for c in on)
        new = [f for f in cold.schema.fields if f.name not in on]
        out = rows.filter(null).select("*", *[F.lit(None).cast(f.dataType).alias(f.name) for f in new])
        rows = rows.filter(f"not ({null})")
        out = out.select(*on, *[c for c in out.columns if c not in on])
    usual = rows.join(F.broadcast(hot.select(*on)), on, "left_anti") if some else rows
    merged = usual.join(cold, on, how)
    if some:
        merged = merged.unionByName(rows.join(F.broadcast(hot.drop(weight)), on, "left_semi" if how == "left_semi" else "inner"))
    return merged if out is None else out.unionByName(merged)
