"""Random edges: k draws per vertex, and a uniform share of all edges."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgeconn.functions.hashing import hash_below, hash_key, hash_mod, hex_bound
from edgeconn.functions.md5 import Numbers
from edgeconn.operators.graph import Graph, half_edges

#: Edges that are hashed together, and candidates of draws that a task holds.
CHUNK, HELD = 1 << 18, 1 << 21

#: Draws up to which edges are drawn from where they lie, edges per vertex and
#: draw up to which they are brought together else, and edges of a hub that
#: one task may hash.
FEW_DRAWS, SPARSE, HUB = 4, 8, 2_000_000


def together(g: Graph, draws: int) -> bool:
    """Whether moving each edge end once is less than moving its draws."""
    if draws <= FEW_DRAWS:
        return False
    row = g.degrees.agg(F.avg("deg").alias("mean"), F.max("deg").alias("most")).first()
    return row.mean is not None and row.mean <= SPARSE * draws and row.most <= HUB


def chunks(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def candidates(edges: DataFrame, k: int, reps: int, seed: int) -> DataFrame:
    """(i, v, nbr, eid): of the edges of each vertex that a task reads, those
    whose md5 for try i begins with the least eight digits. The edge of least
    md5 is always among them."""

    def run(batches):
        import numpy as np

        held: list[tuple] = []

        def least(i, v, nbr, eid, h) -> tuple:
            order = np.lexsort((h, v, i))
            i, v, nbr, eid, h = (x[order] for x in (i, v, nbr, eid, h))
            new = np.r_[True, (i[1:] != i[:-1]) | (v[1:] != v[:-1])]
            keep = h == h[np.flatnonzero(new)][np.cumsum(new) - 1]
            return tuple(x[keep] for x in (i, v, nbr, eid, h))

        def out() -> Iterator[pa.RecordBatch]:
            i, v, nbr, eid, _ = held.pop()
            yield from pa.table({"i": i.astype(np.int32), "v": v, "nbr": nbr, "eid": eid}).to_batches(1 << 16)

        for t in chunks(batches, CHUNK):
            src, dst, eid = (t.column(c).to_numpy() for c in ("src", "dst", "eid"))
            v, nbr, eid = np.r_[src, dst], np.r_[dst, src], np.r_[eid, eid]
            order = np.argsort(v)
            v, nbr, eid = v[order], nbr[order], eid[order]
            start = np.flatnonzero(np.r_[True, v[1:] != v[:-1]])
            sizes = np.diff(np.r_[start, len(v)])
            texts = Numbers(v, nbr)
            for i in range(k * reps):
                h = texts.first(f"{seed}:{i // k}:{i % k}")
                at = np.flatnonzero(h == np.repeat(np.minimum.reduceat(h, start), sizes))
                held.append((np.full(len(at), i), v[at], nbr[at], eid[at], h[at]))
            if sum(len(x[0]) for x in held) > HELD:
                held[:] = [least(*map(np.concatenate, zip(*held, strict=True)))]
                if len(held[0][0]) > HELD // 2:
                    yield from out()
        if held:
            held[:] = [least(*map(np.concatenate, zip(*held, strict=True)))]
            yield from out()

    return _ends(edges).mapInArrow(run, "i int, v long, nbr long, eid long")


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select("eid", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))


def k_out_draws(g: Graph, k: int = 2, reps: int = 1, seed: int = 1, replace: bool = True, draw: str = "minhash", hashing: str = "md5") -> DataFrame:
    """(rep, j, v, nbr, eid): k uniform incident edges of every vertex.

    ``minhash`` takes the incident edge of least hash for each (rep, j): one
    aggregation with map-side combine, so hubs don't skew it; where vertices
    have few edges for the number of draws, which a combine over scattered
    edges would multiply, edges are brought together by vertex first. Else, of
    md5, a first pass on arrays leaves the few edges of least first digits. ``rank`` numbers
    a vertex's edges once and picks place hash mod degree: the work per rep is
    the number of vertices, not of edges. Without replacement the k least of
    one hash are taken. Vertices without an edge draw nothing.
    """
    half = half_edges(g.edges)
    if not replace:
        each = half.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
        h = hash_key(hashing, F.lit(seed), F.col("rep"), F.lit("d"), F.col("v"), F.col("nbr"))
        order = Window.partitionBy("rep", "v").orderBy("h", "nbr")
        return each.withColumn("h", h).withColumn("j", F.row_number().over(order) - 1).filter(F.col("j") < k).select("rep", "j", "v", "nbr", "eid")
    tries = F.explode(F.sequence(F.lit(0), F.lit(reps * k - 1)))
    rep, j = F.floor(F.col("i") / k).cast("int").alias("rep"), (F.col("i") % k).cast("int").alias("j")
    if draw == "minhash":
        if together(g, reps * k):
            each = half.repartition("v").withColumn("i", tries)
        else:
            each = candidates(g.edges, k, reps, seed) if hashing == "md5" else half.withColumn("i", tries)
        each = each.select(rep, j, "v", "nbr", "eid")
        h = hash_key(hashing, F.lit(seed), F.col("rep"), F.col("j"), F.col("v"), F.col("nbr"))
        return each.groupBy("rep", "j", "v").agg(F.min(F.struct(h.alias("h"), F.col("nbr"), F.col("eid"))).alias("d")).select("rep", "j", "v", "d.nbr", "d.eid")
    if draw == "rank":
        placed = half.withColumn("at", F.row_number().over(Window.partitionBy("v").orderBy("eid")).cast("long") - 1)
        picks = half.groupBy("v").count().withColumn("i", tries).select(rep, j, "v", "count")
        x = F.pmod(F.xxhash64(F.lit(seed), "rep", "j", "v"), F.col("count")) if hashing != "md5" else F.conv(F.substring(hash_key("md5", F.lit(seed), F.col("rep"), F.col("j"), F.col("v")), 1, 8), 16, 10).cast("long") % F.col("count")
        return picks.withColumn("at", x).join(placed, ["v", "at"]).select("rep", "j", "v", "nbr", "eid")
    raise ValueError(f"no such draw: {draw}")


def edge_sample(g: Graph, p: float | None = None, reps: int = 1, seed: int = 1, hashing: str = "md5") -> DataFrame:
    """(rep, eid, src, dst): each edge with probability p, 1/(2 min degree)
    if not given; a filter, no shuffle."""
    if p is None:
        p = 1 / (2 * max(1, g.profile["min_degree"]))
    if hashing == "md5" and p < 1:
        return sampled_by_md5(g.edges, p, reps, seed)
    each = g.edges.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    return each.filter(hash_below(hashing, p, F.lit(seed), F.col("rep"), F.lit("e"), F.col("src"), F.col("dst"))).select("rep", "eid", "src", "dst")


def sampled_by_md5(edges: DataFrame, p: float, reps: int, seed: int) -> DataFrame:
    """``edge_sample`` by md5, on arrays."""
    bound = int(hex_bound(p), 16)

    def run(batches):
        import numpy as np

        for t in chunks(batches, CHUNK):
            columns = [t.column(c).to_numpy() for c in ("eid", "src", "dst")]
            texts = Numbers(*columns[1:])
            for r in range(reps):
                at = np.flatnonzero(texts.first(f"{seed}:{r}:e") < bound)
                if len(at):
                    yield from pa.table({"rep": np.full(len(at), r, np.int32), **{c: x[at] for c, x in zip(("eid", "src", "dst"), columns, strict=True)}}).to_batches(1 << 16)

    return _ends(edges).mapInArrow(run, "rep int, eid long, src long, dst long")


def forest_of(edge_cols: list[str], cells: int, seed: int, hashing: str = "md5"):
    """The forest that an edge draws in a repetition."""
    return hash_mod(hashing, cells, F.lit(seed), F.col("rep"), F.lit("f"), *(F.col(c) for c in edge_cols))
