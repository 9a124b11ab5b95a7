import itertools

import numpy as np
import pytest

from edgeconn.operators import solve as S
from edgeconn.operators.cactus import build_cactus, star_cactus
from edgeconn.operators.certificate import peel_certificate, scan_certificate


def random_multigraph(seed):
    rng = np.random.default_rng(seed)
    n = int(rng.integers(2, 12))
    w = np.triu(rng.integers(0, 6, (n, n)) * (rng.random((n, n)) < 0.6), 1).astype(float)
    return w + w.T


def value_of(w, side):
    return w[side][:, ~side].sum()


def brute_cuts(w, bound):
    n = len(w)
    out = set()
    for bits in range(1, 1 << (n - 1)):
        side = np.array([bool(bits >> i & 1) for i in range(n)])
        if side[0]:
            side = ~side
        if value_of(w, side) <= bound + 1e-9:
            out.add(side.tobytes())
    return out


@pytest.mark.parametrize("seed", range(40))
def test_exact_solvers_agree(seed):
    w = random_multigraph(seed)
    want, side = S.solve_brute(w)
    assert value_of(w, side) == want
    for solver in (S.solve_max_adjacency, S.solve_tree_packing):
        got, side = solver(w)
        assert got == want and value_of(w, side) == want
    capped, side = S.solve_capped(w, want + 3)
    assert capped == want
    assert S.solve_capped(w, want)[0] == want
    assert want <= S.solve_recursive(w, seed, 8)[0] <= w.sum(1).min()
    assert want <= S.approx_connectivity(w, 0.5) <= 2.5 * want + 1e-9


@pytest.mark.parametrize("seed", range(25))
def test_all_minimum_cuts_and_cactus(seed):
    w = random_multigraph(seed)
    if len(w) < 3:
        return
    value, _ = S.solve_brute(w)
    if value == 0:
        return
    cuts = S.enumerate_cuts(w, value)
    assert {c.tobytes() for c in cuts} == brute_cuts(w, value)
    c = build_cactus(w, list(range(len(w))), value)
    assert c.cut_count() == len(cuts)
    assert sorted(v for node in c.nodes for v in node) == list(range(len(w)))
    assert {s.tobytes() for s in S.small_cuts(w, 1.5 * value)} == brute_cuts(w, 1.5 * value)


def cycle(n):
    w = np.zeros((n, n))
    for i in range(n):
        w[i, (i + 1) % n] = w[(i + 1) % n, i] = 1
    return w


def test_known_cactuses():
    c = build_cactus(cycle(6), list(range(6)), 2)
    assert c.cut_count() == 15 and len(c.nodes) == 6 and all(m == 1 for *_, m in c.edges)
    path = np.diag([1.0] * 4, 1) + np.diag([1.0] * 4, -1)
    c = build_cactus(path, list(range(5)), 1)
    assert len(c.edges) == 4 and all(m == 2 for *_, m in c.edges)
    assert star_cactus([1, 2, 3], 2, [2, 3]).cut_count() == 2


def test_known_graphs():
    complete = np.ones((7, 7)) - np.eye(7)
    assert S.solve_max_adjacency(complete)[0] == 6
    cube = np.array([[float(bin(i ^ j).count("1") == 1) for j in range(16)] for i in range(16)])
    assert S.solve_tree_packing(cube)[0] == S.solve_max_adjacency(cube)[0] == 4
    for t in range(1, 8):
        two = np.zeros((16, 16))
        two[:8, :8] = two[8:, 8:] = 1
        np.fill_diagonal(two, 0)
        for i in range(t):
            two[i, 8 + i] = two[8 + i, i] = 1
        assert S.solve_max_adjacency(two)[0] == min(t, 7)


@pytest.mark.parametrize("method", [scan_certificate, peel_certificate])
@pytest.mark.parametrize("k", [1, 2, 4])
def test_certificates_keep_small_cuts(method, k):
    rng = np.random.default_rng(k)
    n = 9
    pairs = [tuple(map(int, rng.choice(n, 2, replace=False))) for _ in range(60)]
    kept = method(pairs, k)
    assert len(kept) <= k * (n - 1)
    for bits in itertools.product([0, 1], repeat=n - 1):
        side = (0, *bits)
        size = sum(side[a] != side[b] for a, b in pairs)
        assert sum(side[pairs[i][0]] != side[pairs[i][1]] for i in kept) >= min(k, size)
