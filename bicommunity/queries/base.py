"""Registration, and SQL pieces that queries share."""

from __future__ import annotations

from collections.abc import Callable

INTER = {
    "E": "SELECT user_id AS u, event_type || ':' || json_extract_string(props, '$.k') AS v, ts, event_id AS seq FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL",
    "C": "SELECT o_custkey AS u, CAST(l_partkey AS VARCHAR) AS v, o_orderdate AS ts, l_orderkey * 8 + l_linenumber AS seq FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "S": "SELECT l_suppkey AS u, CAST(l_partkey AS VARCHAR) AS v, o_orderdate AS ts, l_orderkey * 8 + l_linenumber AS seq FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "N": "SELECT o_custkey AS u, p_brand || '/' || p_type AS v, o_orderdate AS ts, l_orderkey * 8 + l_linenumber AS seq FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
}
_PART_KW = "SELECT DISTINCT CAST(p_partkey AS VARCHAR) AS v, unnest([p_brand, p_type] || string_split(p_name, ' ')) AS kw FROM part"
ITEM_KW = {
    "E": "SELECT DISTINCT v, unnest([event_type, 'd' || CAST(k // 10 AS VARCHAR), 'm' || CAST(k % 7 AS VARCHAR)]) AS kw FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, event_type || ':' || json_extract_string(props, '$.k') AS v FROM events)",
    "C": _PART_KW,
    "S": _PART_KW,
    "N": "SELECT DISTINCT p_brand || '/' || p_type AS v, unnest([p_brand, p_type]) AS kw FROM part",
}


def edges_cte(name: str) -> str:
    """inter, edges"""
    return f"inter AS ({INTER[name]}), edges AS MATERIALIZED (SELECT CAST(u AS BIGINT) AS u, v, CAST(count(*) AS BIGINT) AS w FROM inter GROUP BY ALL)"


def pairs_cte(edges: str = "edges", wedges: str = "wedges", pairs: str = "pairs") -> str:
    """wedges and pairs over edges"""
    return (
        f"{wedges} AS MATERIALIZED (SELECT a.u AS ui, b.u AS uj, a.v, least(a.w, b.w) AS wm FROM {edges} a JOIN {edges} b ON a.v = b.v AND a.u < b.u), "
        f"{pairs} AS MATERIALIZED (SELECT ui, uj, CAST(count(*) AS BIGINT) AS n, CAST(sum(wm) AS BIGINT) AS x, CAST(sum(wm * wm) AS BIGINT) AS y, CAST((sum(wm) * sum(wm) - sum(wm * wm)) // 2 AS BIGINT) AS score FROM {wedges} GROUP BY ui, uj)"
    )


def support_cte(edges: str = "edges", wedges: str = "wedges", pairs: str = "pairs", sup: str = "sup") -> str:
    met = f"SELECT w.ui, w.uj, w.v, p.n - 1 AS b FROM {wedges} w JOIN {pairs} p ON w.ui = p.ui AND w.uj = p.uj"
    return f"{sup} AS MATERIALIZED (SELECT e.u, e.v, CAST(coalesce(s.sup, 0) AS BIGINT) AS sup FROM {edges} e LEFT JOIN (SELECT u, v, sum(b) AS sup FROM (SELECT ui AS u, v, b FROM ({met}) UNION ALL SELECT uj, v, b FROM ({met})) GROUP BY u, v) s ON e.u = s.u AND e.v = s.v)"


def core_cte(start: str, k: int, sigma: int, rounds: int) -> tuple[str, str]:
    """Unrolled peeling rounds; the last must change nothing. Returns the CTEs and the last name."""
    parts, now = [], start
    for i in range(rounds):
        parts.append(f"cw{i} AS MATERIALIZED (SELECT a.u AS ui, b.u AS uj, a.v, least(a.w, b.w) AS wm FROM {now} a JOIN {now} b ON a.v = b.v AND a.u < b.u)")
        parts.append(f"cp{i} AS MATERIALIZED (SELECT ui, uj, count(*) - 1 AS b FROM cw{i} GROUP BY ui, uj HAVING count(*) > 1 AND (sum(wm) * sum(wm) - sum(wm * wm)) // 2 >= {sigma})")
        parts.append(f"cs{i} AS MATERIALIZED (SELECT u, v FROM (SELECT w.ui AS u, w.v, p.b FROM cw{i} w JOIN cp{i} p ON w.ui = p.ui AND w.uj = p.uj UNION ALL SELECT w.uj, w.v, p.b FROM cw{i} w JOIN cp{i} p ON w.ui = p.ui AND w.uj = p.uj) GROUP BY u, v HAVING sum(b) >= {k})")
        parts.append(f"ce{i} AS MATERIALIZED (SELECT e.* FROM {now} e SEMI JOIN cs{i} s ON e.u = s.u AND e.v = s.v)")
        now = f"ce{i}"
    return ", ".join(parts), now


def bits_cte(name: str, words: int = 8) -> str:
    """item_kw and vectors (v, w0 .. w7) of 32-bit words."""
    bit = f"(CAST(('0x' || substr(md5(kw), 1, 8)) AS BIGINT) % {words * 32})"
    cols = ", ".join(f"coalesce(bit_or(CASE WHEN bit // 32 = {i} THEN 1::BIGINT << CAST(bit % 32 AS INTEGER) END), 0) AS w{i}" for i in range(words))
    return f"item_kw AS ({ITEM_KW[name]}), vectors AS MATERIALIZED (SELECT v, {cols} FROM (SELECT v, {bit} AS bit FROM item_kw) GROUP BY v)"


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Callable] = {}
        self.sql: dict[str, str] = {}

    def __call__(self, name: str, sql: str | None = None) -> Callable:
        def add(fn: Callable) -> Callable:
            self.queries[name] = fn
            if sql:
                self.sql[name] = sql
            return fn

        return add
