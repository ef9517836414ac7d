"""Schemas, queries and settings."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import types as T

EDGES = "u bigint, v string, w bigint"
ITEM_KW = "v string, kw string"
UPDATES = "t bigint, ts timestamp, u bigint, v string"
PAIRS = "ui bigint, uj bigint, n bigint, x bigint, y bigint, score bigint"
COMMUNITY = "qid string, center bigint, u bigint, v string, w bigint"
CHANGES = "t bigint, qid string, center bigint, op string"


def conform(df: DataFrame, ddl: str) -> DataFrame:
    """Select and check the columns of a declared schema."""
    want = T._parse_datatype_string(ddl)
    out = df.select(*want.fieldNames())
    for have, field_ in zip(out.schema.fields, want.fields, strict=True):
        if have.dataType != field_.dataType:
            raise TypeError(f"{have.name} is {have.dataType.simpleString()}, not {field_.dataType.simpleString()}")
    return out


@dataclass(frozen=True)
class CommunityQuery:
    """Thresholds and keywords of one community query.

    ``k``: butterflies on each edge; ``r``: radius in user-to-user steps; ``sigma``: relationship
    score of each two users that share an item; ``keywords``: each item has one of them (empty: any item).
    ``score_rule='total'`` asks for a total score of ``p * sigma`` over those pairs instead.
    """

    k: int
    r: int
    sigma: int
    keywords: tuple[str, ...] = ()
    qid: str = "q"
    score_rule: str = "pair"
    p: int = 1

    def __post_init__(self) -> None:
        if self.k < 0 or self.r < 1 or self.sigma < 0 or self.score_rule not in ("pair", "total"):
            raise ValueError(f"bad query {self}")

    def but(self, **changes) -> CommunityQuery:
        return replace(self, **changes)


@dataclass(frozen=True)
class EngineConfig:
    bits: int = 256
    gamma: int = 16
    r_max: int = 3
    drop: str = "user"
    items: str = "inner"
    candidates: str = "core"
    engine: str = "auto"
    hub_degree: int | None = 4096
    kernel_limit: int = 200_000
    max_rounds: int = 500
    window: int = 500
    tick: int = 50
    policy: str = "exact"
    order: Sequence[str] = field(default=("ts", "seq", "u", "v"))
