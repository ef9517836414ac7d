"""Plain-Python reference for small graphs."""

from __future__ import annotations

from itertools import combinations


def wedges(g: dict) -> dict:
    out = {}
    for (u1, v1), w1 in g.items():
        for (u2, v2), w2 in g.items():
            if v1 == v2 and u1 < u2:
                out[u1, u2, v1] = min(w1, w2)
    return out


def butterflies(g: dict) -> dict:
    w = wedges(g)
    out = {}
    for (a, b, v), x in w.items():
        for (c, d, t), y in w.items():
            if (a, b) == (c, d) and v < t:
                out[a, b, v, t] = x * y
    return out


def scores(g: dict) -> dict:
    out = {(a, b): 0 for a, b, _ in wedges(g)}
    for (a, b, _, _), s in butterflies(g).items():
        out[a, b] += s
    return out


def supports(g: dict) -> dict:
    out = dict.fromkeys(g, 0)
    for a, b, v, t in butterflies(g):
        for e in ((a, v), (a, t), (b, v), (b, t)):
            out[e] += 1
    return out


def distances(g: dict, c: int) -> dict:
    dist, at, step = {c: 0}, {c}, 0
    while at:
        step += 2
        items = {v for u, v in g if u in at}
        at = {u for u, v in g if v in items} - dist.keys()
        dist |= dict.fromkeys(at, step)
    return dist


def valid(g: dict, c: int, k: int, r: int, sigma: int, inner: bool = True) -> bool:
    """Is g a community of centre c?"""
    if not g or all(u != c for u, _ in g):
        return False
    dist = distances(g, c)
    users = {u for u, _ in g}
    if not users <= dist.keys() or any(dist[u] > 2 * r for u in users):
        return False
    if inner and any(min(dist[u] for u, x in g if x == v) > 2 * r - 2 for _, v in g):
        return False
    s = scores(g)
    return all(x >= sigma for x in s.values()) and all(x >= k for x in supports(g).values())


def exists(g: dict, c: int, k: int, r: int, sigma: int) -> int:
    """Edges of the largest community of c among all sub-graphs; 0 if there is none."""
    edges = list(g.items())
    for n in range(len(edges), 0, -1):
        for part in combinations(edges, n):
            if valid(dict(part), c, k, r, sigma):
                return n
    return 0


def core(g: dict, k: int, sigma: int) -> dict:
    while True:
        good = {p for p, s in scores(g).items() if s >= sigma}
        count = dict.fromkeys(g, 0)
        for a, b, v, t in butterflies(g):
            if (a, b) in good:
                for e in ((a, v), (a, t), (b, v), (b, t)):
                    count[e] += 1
        left = {e: w for e, w in g.items() if count[e] >= k}
        if len(left) == len(g):
            return g
        g = left
