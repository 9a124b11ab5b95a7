"""Sparse connectivity certificates: few edges that keep every small cut."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators.forests import Forests
from edgeconn.plans.staging import stage

#: Edges of one repetition that a task certifies at the first level.
PART_ROWS = 1 << 18


class Forest:
    """Union-find over any hashable vertices, with path halving."""

    def __init__(self):
        self.up: dict = {}

    def find(self, v):
        up = self.up
        if v not in up:
            up[v] = v
            return v
        while up[v] != v:
            up[v] = up[up[v]]
            v = up[v]
        return v

    def joined(self, a, b) -> bool:
        return self.find(a) == self.find(b)

    def union(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def scan_certificate(pairs: list[tuple], k: int) -> list[int]:
    """Places of the pairs that k nested forests take, in one pass.

    A pair goes to the first forest that does not join its ends yet. What a
    forest joins, the ones before it join too, so that forest is found by
    halving. Each cut keeps the lesser of k and its size.
    """
    forests: list[Forest] = []
    kept = []
    for i, (a, b) in enumerate(pairs):
        lo, hi = 0, len(forests)
        while lo < hi:
            mid = (lo + hi) // 2
            if forests[mid].joined(a, b):
                lo = mid + 1
            else:
                hi = mid
        if lo == len(forests):
            if lo == k:
                continue
            forests.append(Forest())
        forests[lo].union(a, b)
        kept.append(i)
    return kept


def sieved(batches: Iterator[pa.RecordBatch], k: int, rows: int = 1 << 19) -> Iterator[pa.RecordBatch]:
    """Of (rep, eid, cu, cv) a certificate of level k of each repetition, about
    ``rows`` edges at a time."""
    import numpy as np

    sieves: dict[int, Forests] = {}
    held: list[pa.RecordBatch] = []
    n = 0

    def part() -> pa.Table:
        t = pa.Table.from_batches(held).combine_chunks()
        rep, u, v = (t.column(c).to_numpy() for c in ("rep", "cu", "cv"))
        take = []
        for r in [int(rep[0])] if rep.min() == rep.max() else np.unique(rep).tolist():
            at = slice(None) if rep.min() == rep.max() else np.flatnonzero(rep == r)
            places = sieves.setdefault(r, Forests(k)).kept(u[at], v[at])
            take.append(places if isinstance(at, slice) else at[places])
        held.clear()
        return t.take(pa.array(np.concatenate(take)))

    for b in batches:
        if b.num_rows:
            held.append(b)
            n += b.num_rows
        if n >= rows:
            n = 0
            yield from part().to_batches(1 << 14)
    if held:
        yield from part().to_batches(1 << 14)


def peel_certificate(pairs: list[tuple], k: int) -> list[int]:
    """The same by k rounds: take a maximal forest of what is left."""
    left, kept = list(enumerate(pairs)), []
    for _ in range(k):
        forest, rest = Forest(), []
        for i, (a, b) in left:
            (kept if forest.union(a, b) else rest).append(i)
        left = [(i, pairs[i]) for i in rest]
        if not left:
            break
    return sorted(kept)


def certificate(kernel: DataFrame, k: int, strategy: str = "merge", fan_in: int = 8, part_rows: int | None = None) -> DataFrame:
    """(rep, eid, cu, cv): at most k * (vertices - 1) edges per repetition with
    min(k, size) edges of every cut. Parallel edges have ids of their own.

    ``scan`` and ``peel`` work in one task per repetition. ``merge`` first lets
    each task drop, while it reads, the edges that its own certificate does
    without, where there are more than a part; then it counts what is left and certifies parts of about ``part_rows`` (``PART_ROWS`` if not
    given) everywhere, then unions of ``fan_in`` certificates, until a part per
    repetition is left: a certificate of certificates is one of the whole. No
    task holds more than about part_rows or fan_in * k * (vertices - 1) edges,
    whichever is more, however many there are.
    """
    rows = kernel.select("rep", "eid", "cu", "cv")
    schema = "rep int, eid long, cu long, cv long"
    method = peel_certificate if strategy == "peel" else scan_certificate

    def run(pdf):
        pdf = pdf.sort_values("eid")
        if strategy == "merge":
            return pdf.iloc[Forests(k).kept(pdf["cu"].to_numpy(), pdf["cv"].to_numpy())][["rep", "eid", "cu", "cv"]]
        return pdf.iloc[method(list(zip(pdf["cu"], pdf["cv"], strict=True)), k)][["rep", "eid", "cu", "cv"]]

    if strategy == "merge":
        most = rows.groupBy("rep").count().agg(F.max("count")).first()[0] or 0
        size = PART_ROWS if part_rows is None else part_rows
        if most > size:
            rows = stage(rows.withColumn("rep", F.col("rep").cast("int")).mapInArrow(lambda b: sieved(b, k), schema), "sieved").df
            most = rows.groupBy("rep").count().agg(F.max("count")).first()[0] or 0
        parts = -(-most // size)
        while parts > 1:
            cell = F.pmod(F.xxhash64("eid"), F.lit(parts))
            rows = rows.groupBy("rep", cell.alias("cell")).applyInPandas(run, schema)
            parts = -(-parts // fan_in)
    return rows.groupBy("rep").applyInPandas(run, schema)
