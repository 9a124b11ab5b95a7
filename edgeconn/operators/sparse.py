"""Cut solvers on kernels as edge arrays, in memory linear in the edges.

A kernel is (n, u, v, w): vertices 0..n-1 and the ends and weights of its
edges, u < v, each pair once. Solvers return (value, side), side being a
boolean array over the vertices.
"""

from __future__ import annotations

from edgeconn.operators.components import local_labels
from edgeconn.operators.forests import tied

INF = float("inf")

#: Vertices from which on forests contract before orders do, and most forests.
MANY, FEW_FORESTS = 512, 64


def from_rows(u, v, w):
    """((n, u, v, w), names) of edges between any integers; loops go, parallel
    edges add up."""
    import numpy as np

    u, v, w = np.asarray(u, np.int64), np.asarray(v, np.int64), np.asarray(w, float)
    names, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    return merged(len(names), at[: len(u)], at[len(u) :], w), names


def merged(n: int, u, v, w):
    import numpy as np

    a, b = np.minimum(u, v), np.maximum(u, v)
    real = a != b
    key, at = np.unique(a[real] * np.int64(max(1, n)) + b[real], return_inverse=True)
    return n, key // max(1, n), key % max(1, n), np.bincount(at, w[real], len(key))


def relabelled(k, label):
    """(kernel, compact labels): the kernel with vertices of equal label as one."""
    import numpy as np

    names, at = np.unique(label, return_inverse=True)
    return merged(len(names), at[k[1]], at[k[2]], k[3]), at


def joined(n: int, a, b):
    """Labels of 0..n-1 after uniting the pairs."""
    import numpy as np

    label = np.arange(n)
    if len(a):
        v, c = local_labels(np.asarray(a), np.asarray(b))
        label[v] = c
    return label


def degrees(k):
    import numpy as np

    n, u, v, w = k
    return np.bincount(u, w, n) + np.bincount(v, w, n)


def _rows(k):
    """Neighbours of each vertex as (starts, neighbours, weights)."""
    import numpy as np

    n, u, v, w = k
    a, b, x = np.concatenate([u, v]), np.concatenate([v, u]), np.concatenate([w, w])
    order = np.argsort(a, kind="stable")
    return np.searchsorted(a[order], np.arange(n + 1)), b[order], x[order]


def adjacency_scan(k, bound: float):
    """One maximum adjacency order: (pairs at least ``bound`` connected, as two
    lists; the vertices reached before the order first leaves a component, or
    None). The last two vertices are as connected as the last one's degree."""
    import numpy as np

    n = k[0]
    start, nbr, wt = _rows(k)
    pull, seen = np.zeros(n), np.zeros(n, bool)
    a, b, last, before = [], [], -1, -1
    for step in range(n):
        v = int(np.argmax(pull))
        if step and pull[v] <= 0:
            return a, b, seen
        if not step:
            v = 0
        pull[v] = -1.0
        seen[v] = True
        before, last = last, v
        x = nbr[start[v] : start[v + 1]]
        fresh = ~seen[x]
        x = x[fresh]
        pull[x] += wt[start[v] : start[v + 1]][fresh]
        near = x[pull[x] >= bound]
        if len(near):
            a += [v] * len(near)
            b += near.tolist()
    return [*a, before], [*b, last], None


def thinned(k, bound: float):
    """(kernel, labels) after contracting what nested forests prove connected by
    ``bound``, until they join under a tenth of the vertices. They take array
    operations for each forest, where an order takes them for each vertex."""
    import numpy as np

    label = np.arange(k[0])
    while k[0] > MANY and len(k[3]) and k[3].min() > 0:
        level = max(1, int(np.ceil(min(bound / k[3].min(), FEW_FORESTS + 1))))
        if level > FEW_FORESTS:
            break
        before = k[0]
        heavy = k[3] >= bound
        k, at = relabelled(k, joined(k[0], k[1][heavy], k[2][heavy]))
        label = at[label]
        k, at = relabelled(k, tied(k[0], k[1], k[2], level))
        label = at[label]
        if k[0] > 0.9 * before:
            break
    return k, label


def solve_scan(k) -> tuple[float, object]:
    """The minimum cut: every edge that a maximum adjacency order proves to be
    as connected as the least degree seen so far is contracted, until one
    vertex is left. Exact; few orders are needed in practice."""
    import numpy as np

    n = k[0]
    if n < 2:
        return INF, np.zeros(n, bool)
    label, best, side, thin = np.arange(n), INF, np.zeros(n, bool), True
    while k[0] > 1:
        deg = degrees(k)
        i = int(np.argmin(deg))
        if deg[i] < best:
            best, side = float(deg[i]), label == i
        if thin:
            before = k[0]
            k, at = thinned(k, best)
            label, thin = at[label], k[0] <= 0.9 * before  # else orders do more
            continue
        a, b, part = adjacency_scan(k, best)
        if part is not None:
            return 0.0, part[label]
        k, at = relabelled(k, joined(k[0], a, b))
        label = at[label]
    return best, side


def estimate(k, eps: float = 0.5) -> float:
    """A value from the minimum cut to (2 + eps) times it: contract what is
    connected by more than degree / (2 + eps), keep the least degree seen."""
    import numpy as np

    best = INF
    while k[0] > 1:
        best = min(best, float(degrees(k).min()))
        if best == 0:
            return 0.0
        a, b, part = adjacency_scan(k, np.floor(np.ceil(best / (2 + eps))) + 1)
        if part is not None:
            return 0.0
        before = k[0]
        k, _ = relabelled(k, joined(k[0], a[:-1], b[:-1]))
        if k[0] == before:
            return best
    return best


def shrink(k, bound: float):
    """(kernel, labels) after contracting all that forests and scans prove
    connected by ``bound`` or more, until nothing changes: cuts under the bound
    stay."""
    k, label = thinned(k, bound)
    while k[0] > 1:
        a, b, part = adjacency_scan(k, bound)
        if part is not None or len(a) < 2:
            break
        k, at = relabelled(k, joined(k[0], a[:-1], b[:-1]))
        label = at[label]
    return k, label


def contract_random(k, stop: int, rng):
    """(kernel, labels) of contracting random edges, by weight, down to
    ``stop`` vertices: edges in the order of exponential clocks."""
    import numpy as np

    n, u, v, w = k
    up, left = list(range(n)), n
    order = np.argsort(rng.exponential(size=len(w)) / np.maximum(w, 1e-300), kind="stable")
    for i in range(0, len(order), 4096):
        for a, b in zip(u[order[i : i + 4096]].tolist(), v[order[i : i + 4096]].tolist(), strict=True):
            while up[a] != a:
                up[a] = up[up[a]]
                a = up[a]
            while up[b] != b:
                up[b] = up[up[b]]
                b = up[b]
            if a != b:
                if left <= stop:
                    break
                up[b] = a
                left -= 1
        if left <= stop:
            break
    root = np.array(up)
    while (root[root] != root).any():
        root = root[root]
    return relabelled(k, root)


def solve_uniform(k, seed: int = 1) -> tuple[float, object]:
    """One run of uniform contraction down to two vertices."""
    import numpy as np

    if k[0] < 2:
        return INF, np.zeros(k[0], bool)
    small, label = contract_random(k, 2, np.random.default_rng(seed))
    return (0.0 if small[0] > 2 else float(small[3].sum())), label == 0


def solve_recursive(k, seed: int = 1) -> tuple[float, object]:
    """Contract to n over the root of two, branch in two, recurse."""
    import math

    import numpy as np

    rng = np.random.default_rng(seed)

    def go(k):
        if k[0] <= 11:
            return _brute(k)
        stop = math.ceil(k[0] / math.sqrt(2)) + 1
        best = (INF, np.zeros(k[0], bool))
        for _ in range(2):
            small, label = contract_random(k, stop, rng)
            value, side = go(small)
            if value < best[0]:
                best = (value, side[label])
        return best

    return go(k)


def _brute(k) -> tuple[float, object]:
    import numpy as np

    n, u, v, w = k
    if n < 2:
        return INF, np.zeros(n, bool)
    sides = (np.arange(1, 1 << (n - 1))[:, None] >> np.arange(n)) & 1
    value = (sides[:, u] != sides[:, v]) @ w
    i = int(np.argmin(value))
    return float(value[i]), sides[i].astype(bool)


def sweep_cuts(k, steps: int = 20, share: float = 0.25):
    """(value, signatures): the least cut among random-walk sweeps, and for
    each vertex which sparse sweep sides hold it. A walk starts at the vertex
    of least degree that no sparse side holds yet; a side is sparse where its
    cut is under ``share`` of its volume, and no side holds over half of it."""
    import numpy as np

    n, u, v, w = k
    deg = np.maximum(degrees(k), 1e-300)
    best, held, signature, todo = float(deg.min()), np.zeros(n, bool), np.zeros(n, np.int64), np.argsort(deg, kind="stable")
    no = 0
    for s in todo.tolist():
        if held[s]:
            continue
        held[s] = True
        x = np.zeros(n)
        x[s] = 1.0
        for _ in range(steps):
            flow = x / deg
            x = 0.5 * x + 0.5 * (np.bincount(u, w * flow[v], n) + np.bincount(v, w * flow[u], n))
        order = np.argsort(-x / deg, kind="stable")
        place = np.empty(n, np.int64)
        place[order] = np.arange(n)
        lo, hi = np.minimum(place[u], place[v]), np.maximum(place[u], place[v])
        cut = np.cumsum(np.bincount(lo, w, n) - np.bincount(hi, w, n))[:-1]
        volume = np.cumsum(deg[order])[:-1]
        best = min(best, float(cut.min()))
        ratio = np.where(2 * volume <= deg.sum(), cut / volume, INF)
        i = int(np.argmin(ratio))
        if ratio[i] <= share:
            no += 1
            side = order[: i + 1]
            held[side] = True
            signature[side] = signature[side] * np.int64(1_000_003) + no
    return best, signature
