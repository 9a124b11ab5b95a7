import random

import pytest

from edgeconn.operators.components import star_components


def brute(edges):
    comp = {}
    adj = {}
    for a, b in edges:
        adj.setdefault(a, set()).add(b)
        adj.setdefault(b, set()).add(a)
    for v in sorted(adj):
        if v not in comp:
            todo = [v]
            while todo:
                x = todo.pop()
                if x not in comp:
                    comp[x] = v
                    todo += adj[x]
    return comp


@pytest.mark.parametrize("kind", ["random", "path", "star"])
def test_star_components(spark, kind):
    rng = random.Random(1)
    edges = {"random": [(rng.randrange(300), rng.randrange(300)) for _ in range(200)], "path": [(i, i + 1) for i in range(120)], "star": [(500, i) for i in range(200)]}[kind]
    edges = [e for e in edges if e[0] != e[1]]
    df = spark.createDataFrame([*edges, *edges[:5], (7, 7), (None, 3)], "src long, dst long")
    got = {r.v: r.comp for r in star_components(df).collect()}
    assert got == brute(edges)


def test_empty(spark):
    assert star_components(spark.createDataFrame([], "src long, dst long")).count() == 0
