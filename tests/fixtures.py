"""Small graphs with known answers."""

import random

F1 = {(1, "v1"): 2, (2, "v1"): 4, (3, "v1"): 2, (2, "v2"): 5, (3, "v2"): 1, (2, "v3"): 6, (3, "v3"): 3}
F2 = [
    {(1, "v2"): 2, (2, "v1"): 3, (2, "v2"): 3, (3, "v1"): 3, (3, "v2"): 1},
    {(1, "v2"): 2, (2, "v1"): 3, (2, "v2"): 3, (3, "v1"): 3, (1, "v1"): 1},
    {(1, "v2"): 2, (2, "v1"): 3, (2, "v2"): 3, (3, "v1"): 2, (1, "v1"): 2},
]
F5 = {(u, v): 1 for us, vs in (((1, 2), "abcd"), ((3, 4), "defg")) for u in us for v in vs}


def block(users, items, w=1):
    return {(u, v): w for u in users for v in items}


def random_graph(seed: int, users: int = 6, items: int = 6, edges: int = 18, weight: int = 3) -> dict:
    rng = random.Random(seed)
    cells = rng.sample([(u, f"i{v}") for u in range(users) for v in range(items)], edges)
    return {e: rng.randint(1, weight) for e in cells}


def frame(spark, g: dict):
    return spark.createDataFrame([(u, v, w) for (u, v), w in g.items()], "u bigint, v string, w bigint")


def graph_of(df) -> dict:
    return {(r.u, r.v): r.w for r in df.collect()}
