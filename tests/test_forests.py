"""Nested forests on arrays, against all cuts of small graphs."""

import numpy as np

from edgeconn.operators import sparse as K
from edgeconn.operators.forests import Forests, compact, tied
from edgeconn.sources import workloads as W


def cut_sizes(n, a, b):
    """A row per side: whether each edge crosses it."""
    sides = (np.arange(1, 1 << (n - 1))[:, None] >> np.arange(n)) & 1
    return sides, sides[:, a] != sides[:, b]


def test_forests_keep_small_cuts_over_batches():
    rng = np.random.default_rng(1)
    for _ in range(60):
        n, m, k = int(rng.integers(2, 8)), int(rng.integers(1, 30)), int(rng.integers(1, 5))
        a, b = rng.integers(0, n, m), rng.integers(0, n, m)
        forests, half = Forests(k), m // 2
        first = forests.kept(10**12 * a[:half] - 7, 10**12 * b[:half] - 7)  # ids of too wide a span for a table
        kept = np.r_[first, half + forests.kept(10**12 * a[half:] - 7, 10**12 * b[half:] - 7)]
        assert len(kept) == len(set(kept.tolist())) <= k * (n - 1)
        sides, crosses = cut_sizes(n, a, b)
        assert (crosses[:, kept].sum(1) >= np.minimum(k, crosses.sum(1))).all()
        small = sides[crosses.sum(1) < k]
        assert (small == small[:, tied(n, a, b, k)]).all()


def test_compact_in_both_ways():
    for far in (1, 10**15):
        ids, x, y = compact(np.array([5, -3]) * far, np.array([-3, 9]) * far)
        assert (ids == np.array([-3, 5, 9]) * far).all() and x.tolist() == [1, 0] and y.tolist() == [0, 2]


def test_forests_come_before_orders(monkeypatch):
    """A graph of many vertices is contracted by forests; an order, which goes
    vertex by vertex, only sees what they leave."""
    rng, seen, real = np.random.default_rng(2), [], K.adjacency_scan
    monkeypatch.setattr(K, "adjacency_scan", lambda k, bound: seen.append(k[0]) or real(k, bound))
    a, b = rng.integers(0, 2000, (2, 60_000))
    block = lambda i: (a + 2000 * i, b + 2000 * i)
    u, v = (np.concatenate([x, y, z]) for x, y, z in zip(block(0), block(1), ([0, 1, 2], [2000, 2001, 2002]), strict=True))
    kernel, _ = K.from_rows(u, v, np.ones(len(u)))
    value, side = K.solve_scan(kernel)
    assert value == 3 and sorted((side[:2000].sum(), side[2000:].sum())) == [0, 2000]
    small, label = K.shrink(kernel, 8)
    assert small[0] == 2 and len(set(label[:2000].tolist())) == 1 and max(seen) <= K.MANY


def test_thinned_counts_weights():
    """Edges of weight under one prove less than an edge each."""
    n = 600
    rng = np.random.default_rng(3)
    ends = [(rng.integers(0, 300, (2, 9000)) + 300 * i) for i in (0, 1)]
    u, v = np.r_[ends[0][0], ends[1][0], 0], np.r_[ends[0][1], ends[1][1], 300]
    kernel = K.merged(n, u, v, np.full(len(u), 0.25))
    assert K.solve_scan(kernel)[0] == 0.25


def test_two_cells_meet_once(spark, small, monkeypatch):
    """The join of cells makes each pair once, not from both of its ends."""
    want = W.nation_cliques(spark, small).count()
    monkeypatch.setattr(W, "CELL", 3)
    made = W.nation_cliques(spark, small)
    join = made._jdf.queryExecution().optimizedPlan().toString().split("Join")[1].split("\n")[0]
    assert "<" in join and "<=" not in join and "OR" in join
    rows = list(map(tuple, made.collect()))
    assert len(rows) == len({tuple(sorted(r)) for r in rows}) == want


def test_few_passes_where_forests_join_little(monkeypatch):
    """Sparse graphs, of which forests contract little, go on to orders at once,
    and edges that stay open are taken in parts that double."""
    rng, thin, takes = np.random.default_rng(4), [], []
    real, take = K.thinned, Forests._take
    monkeypatch.setattr(K, "thinned", lambda k, bound: thin.append(k[0]) or real(k, bound))
    monkeypatch.setattr(Forests, "_take", lambda self, x, y, places: takes.append(len(places)) or take(self, x, y, places))
    u, v = rng.integers(0, 800, (2, 30_000))
    Forests(3).kept(u % 7 * 100, v)
    assert len(takes) <= 7
    kernel = K.merged(800, np.r_[np.arange(800), u[:900]], np.r_[(np.arange(800) + 1) % 800, v[:900]], np.ones(1700))
    value, side = K.solve_scan(kernel)
    assert len(thin) <= 10 and value == (side[kernel[1]] != side[kernel[2]]) @ kernel[3] == K.degrees(kernel).min()
