"""Communities in SQL: the rules of an answer as unrolled rounds, for checks on small graphs.

Rounds are unrolled a fixed number of times; more rounds than a graph needs change nothing, so a
result is right as soon as one round more gives the same.
"""

from __future__ import annotations

from ..model import CommunityQuery
from .base import core_cte


def _table(name: str, body: str) -> str:
    return f"{name} AS MATERIALIZED ({body})"


def _near(g: str, r: int, tag: str) -> tuple[list[str], str]:
    """center, u, dist of the users that g's own edges reach from each centre in r steps."""
    out = [_table(f"{tag}d0", f"SELECT DISTINCT center, u, 0 AS dist FROM {g} WHERE u = center")]
    for s in range(1, r + 1):
        out.append(_table(f"{tag}d{s}", f"SELECT center, u, min(dist) AS dist FROM (SELECT * FROM {tag}d{s - 1} UNION ALL SELECT DISTINCT b.center, b.u, {2 * s} FROM (SELECT DISTINCT x.center, x.v FROM {g} x JOIN {tag}d{s - 1} n ON x.center = n.center AND x.u = n.u) a JOIN {g} b ON a.center = b.center AND a.v = b.v) GROUP BY center, u"))
    return out, f"{tag}d{r}"


def _pairs(g: str, tag: str) -> list[str]:
    wedges = f"SELECT a.center, a.u AS ui, b.u AS uj, a.v, least(a.w, b.w) AS m FROM {g} a JOIN {g} b ON a.center = b.center AND a.v = b.v AND a.u < b.u"
    pairs = f"SELECT center, ui, uj, count(*) AS n, (sum(m) * sum(m) - sum(m * m)) // 2 AS score FROM {tag}w GROUP BY center, ui, uj"
    return [_table(f"{tag}w", wedges), _table(f"{tag}p", pairs)]


def _settled(g: str, q: CommunityQuery, r: int, sigma: int, items: str, rounds: int, tag: str) -> tuple[list[str], str, str]:
    """Rounds of radius and support; also the distances of the last one."""
    out, near = [], ""
    for i in range(rounds):
        t = f"{tag}s{i}"
        parts, near = _near(g, r, t)
        limit = 2 * r - 2 if items == "inner" else 2 * r
        at = f"SELECT x.*, n.dist FROM {g} x JOIN {near} n ON x.center = n.center AND x.u = n.u"
        out += [*parts, _table(f"{t}a", at), _table(f"{t}c", f"SELECT center, u, v, w FROM {t}a SEMI JOIN (SELECT center, v FROM {t}a WHERE dist <= {limit}) USING (center, v)"), *_pairs(f"{t}c", t)]
        ends = f"SELECT w.center, w.ui, w.uj, w.v, p.n - 1 AS b FROM {t}w w JOIN {t}p p ON w.center = p.center AND w.ui = p.ui AND w.uj = p.uj WHERE p.n > 1 AND p.score >= {sigma}"
        out.append(_table(f"{t}e", ends))
        out.append(_table(f"{t}g", f"SELECT * FROM {t}c SEMI JOIN (SELECT center, u, v FROM (SELECT center, ui AS u, v, b FROM {t}e UNION ALL SELECT center, uj, v, b FROM {t}e) GROUP BY ALL HAVING sum(b) >= {q.k}) USING (center, u, v)"))
        g = f"{t}g"
    return out, g, near


def _radius(start: str, q: CommunityQuery, r: int, drop: str, items: str, settle: int, drops: int) -> tuple[list[str], str]:
    tag, sigma = f"r{r}", q.sigma if q.score_rule == "pair" else 0
    # every centre starts from the edges of the users it reaches
    out = [_table(f"{tag}h0", f"SELECT DISTINCT u AS center, u FROM {start}")]
    for s in range(1, r + 1):
        out.append(_table(f"{tag}h{s}", f"SELECT DISTINCT a.center, y.u FROM (SELECT DISTINCT h.center, x.v FROM {tag}h{s - 1} h JOIN {start} x ON h.u = x.u) a JOIN {start} y ON a.v = y.v"))
    out.append(_table(f"{tag}g", f"SELECT h.center, x.u, x.v, x.w FROM {tag}h{r} h JOIN {start} x ON h.u = x.u"))
    g = f"{tag}g"
    for d in range(drops + 1):
        t = f"{tag}x{d}"
        parts, g, near = _settled(g, q, r, sigma, items, settle, t)
        out += parts
        if q.score_rule == "total":
            out += [*_pairs(g, f"{t}t"), _table(f"{t}z", f"SELECT * FROM {g} SEMI JOIN (SELECT center FROM {t}tp GROUP BY center HAVING sum(score) >= {q.p * q.sigma}) USING (center)")]
            return out, f"{t}z"
        if d == drops:
            break
        out += _pairs(g, f"{t}k")
        weak = f"SELECT center, ui AS u, uj AS other FROM {t}kp WHERE score < {sigma} UNION ALL SELECT center, uj, ui FROM {t}kp WHERE score < {sigma}"
        out.append(_table(f"{t}weak", weak))
        out.append(_table(f"{t}rank", f"SELECT k.center, k.u, row_number() OVER (PARTITION BY k.center ORDER BY count(*), n.dist, k.u) AS place FROM {t}weak k JOIN {near} n ON k.center = n.center AND k.u = n.u GROUP BY k.center, k.u, n.dist"))
        lost = f"SELECT center, other AS u, u AS other FROM {t}weak WHERE u = center UNION ALL SELECT k.center, k.u, k.other FROM {t}weak k JOIN {t}rank a ON k.center = a.center AND k.u = a.u WHERE k.center NOT IN (SELECT center FROM {t}weak WHERE u = center) AND a.place > (SELECT max(b.place) FROM {t}weak o JOIN {t}rank b ON o.center = b.center AND o.other = b.u WHERE o.center = k.center AND o.u = k.u)"
        out.append(_table(f"{t}lost", lost))
        if drop == "user":
            out.append(_table(f"{t}z", f"SELECT * FROM {g} ANTI JOIN {t}lost USING (center, u)"))
        else:
            out.append(_table(f"{t}z", f"SELECT * FROM {g} ANTI JOIN (SELECT l.center, l.u, x.v FROM {t}lost l JOIN {g} x ON l.center = x.center AND l.other = x.u) USING (center, u, v)"))
        g = f"{t}z"
    return out, g


def communities(start: str, q: CommunityQuery, drop: str = "user", items: str = "inner", settle: int = 4, drops: int = 2, name: str = "comm") -> str:
    """CTEs that end in ``comm`` (qid, center, u, v, w, radius): every centre's answer on the graph ``start``, the largest over the radii."""
    parts, every = [], []
    for r in range(1, q.r + 1):
        own, last = _radius(start, q, r, drop, items, settle, drops)
        parts += own
        every.append(f"SELECT center, u, v, w, {r} AS radius FROM {last}")
    parts.append(_table(f"{name}_all", " UNION ALL ".join(every)))
    parts.append(_table(f"{name}_best", f"SELECT center, radius FROM (SELECT center, radius, row_number() OVER (PARTITION BY center ORDER BY count(DISTINCT u) DESC, count(*) DESC, radius) AS nth FROM {name}_all GROUP BY center, radius) WHERE nth = 1"))
    parts.append(_table(name, f"SELECT '{q.qid}' AS qid, center, u, v, w, radius FROM {name}_all SEMI JOIN {name}_best USING (center, radius)"))
    return ", ".join(parts)


ANSWER = "SELECT qid, center, CAST(count(DISTINCT u) AS BIGINT) AS users, CAST(count(DISTINCT v) AS BIGINT) AS items, CAST(count(*) AS BIGINT) AS edges, CAST(sum(w) AS BIGINT) AS weight FROM {0} GROUP BY qid, center"


def prints(comm: str = "comm") -> str:
    """prints: qid, center, n_edges and fingerprint; firsts: the smallest centre of each edge set; once: communities once each."""
    edge = "CAST(u AS VARCHAR) || chr(31) || v"
    return ", ".join([
        _table("prints", f"SELECT qid, center, count(*) AS n_edges, sha256(array_to_string(list_sort(list({edge})), chr(30))) AS fingerprint FROM {comm} GROUP BY qid, center"),
        _table("firsts", "SELECT qid, min(center) AS center, any_value(n_edges) AS n_edges, fingerprint FROM prints GROUP BY qid, fingerprint"),
        _table("once", f"SELECT * FROM {comm} SEMI JOIN firsts USING (qid, center)"),
    ])


def measures(comm: str, r: int, name: str = "sizes") -> str:
    """CTEs that end in ``sizes``: users, items, edges, least support and score, greatest distance of each community."""
    t = f"{name}_"
    parts = _pairs(comm, t)
    near, last = _near(comm, r, t)
    ends = f"SELECT w.center, w.ui, w.uj, w.v, p.n - 1 AS b FROM {t}w w JOIN {t}p p ON w.center = p.center AND w.ui = p.ui AND w.uj = p.uj"
    parts += [*near, _table(f"{t}e", ends)]
    parts.append(_table(f"{t}sup", f"SELECT c.center, c.u, c.v, coalesce(sum(e.b), 0) AS sup FROM {comm} c LEFT JOIN (SELECT center, ui AS u, v, b FROM {t}e UNION ALL SELECT center, uj, v, b FROM {t}e) e ON c.center = e.center AND c.u = e.u AND c.v = e.v GROUP BY c.center, c.u, c.v"))
    size = f"SELECT qid, center, count(DISTINCT u) AS n_users, count(DISTINCT v) AS n_items, count(*) AS n_edges FROM {comm} GROUP BY qid, center"
    low = f"SELECT center, min(score) AS min_score, sum(score) AS sum_score FROM {t}p GROUP BY center"
    far = f"SELECT center, max(dist) AS far, count(*) AS reached FROM {last} GROUP BY center"
    parts.append(_table(name, f"SELECT s.qid, s.center, CAST(n_users AS BIGINT) AS n_users, CAST(n_items AS BIGINT) AS n_items, CAST(n_edges AS BIGINT) AS n_edges, CAST((SELECT min(sup) FROM {t}sup x WHERE x.center = s.center) AS BIGINT) AS min_sup, CAST(min_score AS BIGINT) AS min_score, CAST(sum_score AS BIGINT) AS sum_score, CASE WHEN reached = n_users THEN CAST(far AS INTEGER) END AS max_dist FROM ({size}) s LEFT JOIN ({low}) l ON s.center = l.center LEFT JOIN ({far}) f ON s.center = f.center"))
    return ", ".join(parts)


def counts(value: object, graph: str, q: CommunityQuery, rounds: int, answers: bool = True, **options) -> str:
    """One row of a sweep over ``mine``, the last CTE of ``graph``."""
    ctes, last = core_cte("mine", q.k, q.sigma, rounds)
    found = f", {communities(last, q, **options)}" if answers else ""
    more = ", (SELECT count(DISTINCT center) FROM comm) AS answers, (SELECT count(*) FROM comm) AS answer_edges" if answers else ""
    return f"SELECT * FROM (WITH {graph}, {ctes}{found} SELECT '{value}' AS value, (SELECT count(*) FROM mine) AS matching, (SELECT count(*) FROM {last}) AS core_edges, (SELECT count(DISTINCT u) FROM {last}) AS core_users{more})"


def sweep(points: list[tuple[object, str, CommunityQuery]], rounds: int, answers: bool = True, **options) -> str:
    return " UNION ALL ".join(counts(value, graph, q, rounds, answers, **options) for value, graph, q in points)
