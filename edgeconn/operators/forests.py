"""Nested forests on arrays.

An edge goes to the first forest that does not join its ends yet, so what a
forest joins, all before it join too: vertices that the k-th joins have a path
in each of k forests, and no cut under k edges separates them.
"""

from __future__ import annotations

#: Span of vertex ids that are looked up in a table.
SPAN = 1 << 22


def compact(a, b):
    """(ids in order, places of a, places of b among them)."""
    import numpy as np

    if not len(a):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    low, high = min(int(a.min()), int(b.min())), max(int(a.max()), int(b.max()))
    if high - low >= SPAN:
        ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        return ids, at[: len(a)], at[len(a) :]
    a, b = a - low, b - low
    there = np.zeros(high - low + 1, bool)
    there[a] = there[b] = True
    at = np.cumsum(there) - 1
    return np.flatnonzero(there) + low, at[a], at[b]


def spanning(n: int, a, b):
    """(places of the edges of a maximal forest of the vertices 0..n-1, labels):
    each component takes its first edge to another, until there is none."""
    import numpy as np

    label, at, out = np.arange(n), np.arange(len(a)), []
    while True:
        real = a != b
        a, b, at = a[real], b[real], at[real]
        m = len(at)
        if not m:
            return np.concatenate(out) if out else at, label
        back = np.arange(m)[::-1]
        first, other = np.full(n, m), np.full(n, m)
        first[a[::-1]] = back  # of repeated places the last written stays
        other[b[::-1]] = back
        np.minimum(first, other, out=first)
        c = np.flatnonzero(first < m)
        e = first[c]
        out.append(at[np.unique(e)])
        up = np.arange(n)
        up[c] = a[e] + b[e] - c
        both = c[(up[up[c]] == c) & (c < up[c])]  # two that took one edge
        up[both] = both
        while not np.array_equal(top := up[up], up):
            up = top
        label, a, b = up[label], up[a], up[b]


class Forests:
    """k nested forests, to which edges between any integers are given."""

    def __init__(self, k: int):
        import numpy as np

        self.k, self.names, self.labels = k, np.zeros(0, np.int64), []

    def _known(self, ids):
        """Places of the ids among the names, with new ones as vertices alone."""
        import numpy as np

        names = np.union1d(self.names, ids)
        if len(names) > len(self.names):
            at = np.searchsorted(names, self.names)
            for i, old in enumerate(self.labels):
                self.labels[i] = np.arange(len(names))
                self.labels[i][at] = at[old]
            self.names = names
        return np.searchsorted(names, ids)

    def _open(self, x, y, places):
        """The places whose ends the last forest does not join: no others can
        be taken."""
        if len(self.labels) < self.k:
            return places
        top = self.labels[-1]
        return places[top[x[places]] != top[y[places]]]

    def kept(self, a, b):
        """Places of the edges that some forest takes. About k edges a vertex go
        first: after them most others of a dense graph are joined already."""
        import numpy as np

        ids, x, y = compact(a, b)
        at = self._known(ids)
        x, y = at[x], at[y]
        out, left = [np.zeros(0, np.int64)], self._open(x, y, np.flatnonzero(x != y))
        share = self.k * len(ids) / max(1, len(left))
        while len(left):
            first = (left * 0x9E3779B1 & 0xFFFFFFFF) < share * 2**32
            share *= 2
            out += self._take(x, y, left[first])
            left = self._open(x, y, left[~first])
        return np.sort(np.concatenate(out))

    def _take(self, x, y, places) -> list:
        import numpy as np

        n, out = len(self.names), []
        for i in range(self.k):
            if not len(places):
                break
            if i == len(self.labels):
                self.labels.append(np.arange(n))
            label = self.labels[i]
            took, new = spanning(n, label[x[places]], label[y[places]])
            if len(took):
                self.labels[i] = new[label]
                out.append(places[took])
                places = np.delete(places, took)
        return out


def tied(n: int, u, v, level: int):
    """Labels of 0..n-1: equal where ``level`` nested forests of the edges join."""
    import numpy as np

    forests = Forests(level)
    forests.kept(u, v)
    label = np.arange(n)
    if len(forests.labels) == level:
        label[forests.names] = forests.names[forests.labels[-1]]
    return label
