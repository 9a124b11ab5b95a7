"""Edges as pairs of blocks of vertices, written out where they are read.

A dense graph has far more edges than a shared folder should hold. Its blocks
are written instead, and each task makes the edges of its blocks as arrays, all
of them, every time that an operator reads the graph.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators.forests import SPAN, Forests

#: part int, kind int, a binary, b binary: vertices as 64-bit integers. ``part``
#: is the task that reads the block.
SCHEMA = "part int, kind int, a binary, b binary"
#: Each of a with each of b; each two of a; places of a with the same of b.
ACROSS, WITHIN, ALONG = 0, 1, 2
#: Edges that a task makes at a time (few, so that they stay in a core's cache),
#: and that it reads in all, about.
CHUNK, TASK_EDGES = 1 << 16, 1 << 27


def pairs_of(kind: int, a, b) -> Iterator[tuple]:
    """(src, dst) of a block, src < dst, about CHUNK at a time."""
    import numpy as np

    if kind == ALONG:
        made = [(a, b)]
    elif kind == ACROSS:
        step = max(1, CHUNK // max(1, len(b)))
        made = ((np.repeat(x, len(b)), np.tile(b, len(x))) for x in (a[i : i + step] for i in range(0, len(a), step)))
    else:
        step = max(1, CHUNK // max(1, len(a)))
        made = _within(a, step)
    for x, y in made:
        yield np.minimum(x, y), np.maximum(x, y)


def _within(a, step: int) -> Iterator[tuple]:
    import numpy as np

    for i in range(0, len(a), step):
        more = len(a) - 1 - np.arange(i, min(i + step, len(a)))  # partners of each
        x = np.repeat(a[i : i + step], more)
        if len(x):
            yield x, np.concatenate([a[j + 1 :] for j in range(i, min(i + step, len(a)))])


def expanded(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    import numpy as np

    for t in batches:
        for kind, a, b in zip(*(t.column(c).to_pylist() for c in ("kind", "a", "b")), strict=True):
            yield from pairs_of(kind, np.frombuffer(a, np.int64), np.frombuffer(b, np.int64))


def on_arrays(blocks: DataFrame, run, schema: str) -> DataFrame:
    """``run`` on the edges of the tasks' blocks, as an iterator of (src, dst)."""
    parts = blocks.agg(F.max("part")).first()[0]
    dealt = blocks if parts is None else blocks.repartitionById(parts + 1, F.col("part"))
    return dealt.select("kind", "a", "b").mapInArrow(lambda b: run(expanded(b)), schema)


def edges_of(blocks: DataFrame) -> DataFrame:
    """(src, dst), a row for each edge."""

    def run(pairs):
        for src, dst in pairs:
            yield from pa.table({"src": src, "dst": dst}).to_batches(1 << 16)

    return on_arrays(blocks, run, "src long, dst long")


def degrees_of(blocks: DataFrame) -> DataFrame:
    """(v, deg): each task counts the ends that it reads."""

    def run(pairs):
        import numpy as np

        dense, rest = np.zeros(0, np.int64), []
        for src, dst in pairs:
            if len(src) and src.min() >= 0 and (top := int(dst.max())) < SPAN:
                if top >= len(dense):
                    dense = np.concatenate([dense, np.zeros(top + 1, np.int64)])
                np.add.at(dense, src, 1)
                np.add.at(dense, dst, 1)
            elif len(src):
                rest.append(pa.table(dict(zip(("v", "deg"), np.unique(np.concatenate([src, dst]), return_counts=True), strict=True))))
        at = np.flatnonzero(dense)
        for t in [pa.table({"v": at, "deg": dense[at]}), *rest]:
            yield from t.to_batches(1 << 16)

    return on_arrays(blocks, run, "v long, deg long").groupBy("v").agg(F.sum("deg").alias("deg"))


class Sieve:
    """Nested forests of the edges read so far, with a table of what the last
    one joins: most edges of a dense graph are dropped by two looks at it."""

    def __init__(self, k: int):
        self.forests, self.table = Forests(k), None

    def kept(self, src, dst):
        """Places of the edges that some forest takes."""
        import numpy as np

        f = self.forests
        small = len(src) and src.min() >= 0 and dst.max() < SPAN
        if not small or len(f.labels) < f.k:
            self.table = None
            return f.kept(src, dst)
        top = int(dst.max()) + 1
        if self.table is None or len(self.table) < top:
            self.table = -1 - np.arange(max(top, min(int(f.names[-1]) + 1, SPAN)), dtype=np.int32)  # alone
            there = (f.names >= 0) & (f.names < len(self.table))
            self.table[f.names[there]] = f.labels[-1][there]
        at = np.flatnonzero(self.table.take(src) != self.table.take(dst))
        if not len(at):
            return at
        at = at[f.kept(src[at], dst[at])]
        if len(at):
            self.table = None
        return at

    def ties(self):
        """(vertices, heads) of what the last forest joins: k forests have a
        path between them, so no cut under k edges separates them."""
        import numpy as np

        f = self.forests
        if len(f.labels) < f.k:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        head = f.names[f.labels[-1]]
        real = head != f.names
        return f.names[real], head[real]


def sieved(blocks: DataFrame, k: int) -> DataFrame:
    """(tie, a, b): the edges that each task's certificate of level k keeps,
    and the vertices that its last forest ties."""

    def run(pairs):
        import numpy as np

        sieve = Sieve(k)

        def rows(tie, a, b):
            return pa.table({"tie": np.full(len(a), tie), "a": a, "b": b}).to_batches(1 << 16)

        for src, dst in pairs:
            at = sieve.kept(src, dst)
            if len(at):
                yield from rows(False, src[at], dst[at])
        yield from rows(True, *sieve.ties())

    return on_arrays(blocks, run, "tie boolean, a long, b long")
