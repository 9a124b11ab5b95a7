"""Single-edge contraction of graphs of more edges than a task holds.

Each edge has an exponential clock in each repetition, and the edges that do
not join what earlier ones joined yet are contracted in the order of the clocks
until two vertices are left. Clocks up to a time are drawn as they are, which
is few edges; the minimum forest of those is what they contract. Clocks have no
memory, so the edges between different vertices of that contraction, all of
which are then read, are contracted as a graph of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators import blocks as X
from edgeconn.operators import sparse as K
from edgeconn.operators.components import with_singletons
from edgeconn.operators.contract import collapse, kernel_edges, widen
from edgeconn.operators.forests import compact, spanning
from edgeconn.operators.graph import Graph
from edgeconn.operators.sample import chunks
from edgeconn.plans.staging import stage

#: Edges a vertex that are drawn up to that time, and draws that a task holds.
DRAWN, HELD = 6, 1 << 21


def least_forest(clock, a, b):
    """(places of the minimum forest by clock, in its order; vertices; labels)."""
    import numpy as np

    order = np.argsort(clock, kind="stable")
    ids, x, y = compact(a[order], b[order])
    took, label = spanning(len(ids), x, y)
    return order[np.sort(took)], ids, label


def first_edges(pairs: Iterator[tuple], share: float, repeats: int, seed: int) -> Iterator[pa.RecordBatch]:
    """(rep, clock, a, b): of the edges whose clock is under -log(1 - share) the
    minimum forest of each repetition."""
    import numpy as np

    held: list[tuple] = []

    def thin() -> None:
        rep, clock, a, b = map(np.concatenate, zip(*held, strict=True))
        held.clear()
        for r in range(repeats):
            at = np.flatnonzero(rep == r)
            at = at[least_forest(clock[at], a[at], b[at])[0]]
            held.append((rep[at], clock[at], a[at], b[at]))

    n = 0
    for src, dst in pairs:
        if not len(src):
            continue
        rng = np.random.default_rng([seed, len(src), *(int(x) & 0xFFFFFFFFFFFFFFFF for x in (src[0], dst[0], src[-1], dst[-1]))])
        all_, at = len(src) * repeats, []
        last = -1
        while last < all_:  # the drawn of all edges in all repetitions, by the gaps between them
            gaps = rng.geometric(share, int(1.1 * share * all_) + 16)
            at.append(last + np.cumsum(gaps))
            last = int(at[-1][-1])
        at = np.concatenate(at)
        at = at[at < all_]
        rep, place = np.divmod(at, len(src))
        held.append((rep.astype(np.int32), -np.log1p(-share * rng.random(len(at))), src[place], dst[place]))
        n += len(at)
        if n > HELD:
            thin()
            n = sum(len(x[0]) for x in held) // 2  # what a forest keeps is not thinned again at once
    if held:
        thin()
        for x in held:
            yield from pa.table(dict(zip(("rep", "clock", "a", "b"), x, strict=True))).to_batches(1 << 16)


def first_labels(g: Graph, share: float, repeats: int, seed: int) -> DataFrame:
    """(rep, v, comp), of the vertices other than the least of theirs, of the
    contraction by the edges drawn first, which stops at two vertices."""
    schema, n = "rep int, clock double, a long, b long", g.profile["n"]
    if g.blocks is not None:
        drawn = X.on_arrays(g.blocks, lambda pairs: first_edges(pairs, share, repeats, seed), schema)
    else:
        rows = g.edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
        arrays = lambda batches: ((t.column("src").to_numpy(), t.column("dst").to_numpy()) for t in chunks(batches, X.CHUNK))
        drawn = rows.mapInArrow(lambda b: first_edges(arrays(b), share, repeats, seed), schema)

    def run(key, pdf):
        import pandas as pd

        clock, a, b = (pdf[c].to_numpy() for c in ("clock", "a", "b"))
        took, ids, label = least_forest(clock, a, b)
        if len(took) == n - 1:  # one vertex would be left: its last edge is not contracted
            ids, x, y = compact(a[took], b[took])
            label = spanning(len(ids), x[:-1], y[:-1])[1]
        comp = K.relabelled((len(ids), label[:0], label[:0], label[:0]), label)[1]
        head = ids[pd.Series(range(len(ids))).groupby(comp).min().to_numpy()][comp]
        real = head != ids
        return pd.DataFrame({"rep": key[0], "v": ids[real], "comp": head[real]}).astype({"rep": "int32"})

    return drawn.groupBy("rep").applyInPandas(run, "rep int, v long, comp long")


def block_kernel(g: Graph, labels: DataFrame) -> DataFrame:
    """(rep, cu, cv): ``kernel_edges`` of a graph of blocks. A task reads the
    labels of the vertices that its blocks have, then all of their edges."""

    def vertices(batches):
        import numpy as np

        for t in batches:
            part = t.column("part").to_numpy()
            a, b = t.column("a").to_pylist(), t.column("b").to_pylist()
            for p in np.unique(part).tolist():
                v = np.unique(np.concatenate([np.frombuffer(x[i], np.int64) for i in np.flatnonzero(part == p) for x in (a, b)]))
                yield from pa.table({"part": np.full(len(v), p, np.int32), "v": v}).to_batches(1 << 16)

    def run(batches):
        import numpy as np

        names, comps, ready = [], [], None
        for t in batches:
            kind = t.column("kind").to_numpy()
            own = t.filter(pa.array(kind < 0))
            if own.num_rows:
                names.append(own.column("v").to_numpy())
                comps.append(own.column("comps").flatten().to_numpy().reshape(own.num_rows, -1))
            rest = t.filter(pa.array(kind >= 0))
            if not rest.num_rows:
                continue
            if ready is None:
                ready = Marked(np.concatenate(names), np.concatenate(comps))
            for src, dst in X.expanded(iter([rest])):
                rep, cu, cv = ready.between(src, dst)
                if len(rep):
                    yield from pa.table({"rep": rep, "cu": cu, "cv": cv}).to_batches(1 << 16)

    where = g.blocks.mapInArrow(vertices, "part int, v long").distinct()
    marks = where.join(widen(labels).select("v", "comps"), "v").select("part", F.lit(-1).alias("kind"), F.lit(None).cast("binary").alias("a"), F.lit(None).cast("binary").alias("b"), "v", "comps")
    both = g.blocks.select("part", "kind", "a", "b", F.lit(None).cast("long").alias("v"), F.lit(None).cast("array<long>").alias("comps")).unionByName(marks)
    parts = g.blocks.agg(F.max("part")).first()[0]
    dealt = both.repartitionById(parts + 1, F.col("part")).sortWithinPartitions("kind")
    return dealt.select("kind", "a", "b", "v", "comps").mapInArrow(run, "rep int, cu long, cv long")


class Marked:
    """Labels of all repetitions, and for each vertex a number that it shares
    with those of equal labels: most edges are told by two looks at that."""

    def __init__(self, names, comps):
        import numpy as np

        order = np.argsort(names)
        self.names = names[order]
        self.comps, self.same = np.unique(comps[order], axis=0, return_inverse=True)
        self.same = self.same.reshape(-1).astype(np.int32)
        self.table = None
        if self.names[0] >= 0 and self.names[-1] < X.SPAN:
            self.table = np.zeros(self.names[-1] + 1, np.int32)
            self.table[self.names] = self.same

    def between(self, src, dst):
        """(rep, cu, cv) of the edges between different components."""
        import numpy as np

        if self.table is not None:
            a, b = self.table.take(src), self.table.take(dst)
        else:
            a, b = (self.same[np.searchsorted(self.names, x)] for x in (src, dst))
        at = np.flatnonzero(a != b)
        ca, cb = self.comps[a[at]], self.comps[b[at]]
        place, rep = np.nonzero(ca != cb)
        ca, cb = ca[place, rep], cb[place, rep]
        return rep.astype(np.int32), np.minimum(ca, cb), np.maximum(ca, cb)


def uniform_runs(g: Graph, repeats: int, seed: int = 1) -> DataFrame:
    """(rep, value): single-edge contractions of the whole graph down to two
    vertices, and the edges between those."""
    p = g.profile
    share = min(0.5, DRAWN * p["n"] / max(1, p["m"]))
    labels = stage(first_labels(g, share, repeats, seed), "uniform-labels").df
    whole = with_singletons(labels, g.vertices, repeats)
    between = block_kernel(g, whole) if g.blocks is not None else kernel_edges(g, whole)
    kernel = stage(collapse(between, "rep"), "uniform-kernel").df

    def run(key, pdf):
        import pandas as pd

        rest, names = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        return pd.DataFrame({"rep": [key[0]], "value": [K.solve_uniform(rest, seed + key[0])[0]], "seen": [len(names)]})

    solved = kernel.groupBy("rep").applyInPandas(run, "rep int, value double, seen long")
    reps = g.vertices.sparkSession.range(repeats).select(F.col("id").cast("int").alias("rep"))
    left = reps.join(labels.groupBy("rep").count(), "rep", "left").select("rep", (F.lit(p["n"]) - F.coalesce("count", F.lit(0))).alias("left"))
    # A vertex of the contraction without an edge: the graph is in parts.
    return left.join(solved, "rep", "left").select("rep", F.when(F.col("seen") == F.col("left"), F.col("value")).otherwise(F.lit(0.0)).alias("value"))
