"""Connected components by alternating star contractions.

Every step is an aggregation and an equi-join on a vertex column, so a hub's
neighbours never have to sit in one task's memory, and AQE may split the hub's
join partition. Nothing but two scalars per round reaches the driver.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgeconn.plans.staging import stage


#: Pairs of one group that a single task may hold.
TASK_ROWS = 20_000_000


def _step(edges: DataFrame, by: list[str], keep_larger: bool) -> DataFrame:
    """Point the chosen neighbours of each vertex at its least neighbour.

    ``edges`` has (*by, a, b). With ``keep_larger`` the larger neighbours of
    each vertex move; without it the vertex and its smaller neighbours do.
    """
    if keep_larger:
        ends = edges.select(*by, F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("e")).select(*by, "e.a", "e.b")
    else:
        ends = edges.select(*by, F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = ends.groupBy(*by, "a").agg(F.min("b").alias("m")).select(*by, "a", F.least("a", "m").alias("m"))
    joined = ends.join(least, [*by, "a"])
    if keep_larger:
        moved = joined.filter(F.col("b") > F.col("a")).select(*by, F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        moved = joined.select(*by, F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select(*by, "a", F.col("m").alias("b")))
    return moved.filter(F.col("a") != F.col("b")).distinct()


def _mark(edges: DataFrame, by: list[str]) -> tuple[int, int]:
    row = edges.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(F.xxhash64(*by, "a", "b")), F.lit(0).cast("long"))).first()
    return row[0], row[1]


def star_components(edges: DataFrame, src: str = "src", dst: str = "dst", by: list[str] | None = None, max_rounds: int = 60) -> DataFrame:
    """Label each vertex of ``edges`` with the least vertex it can reach.

    Returns (*by, v, comp), one row per vertex that has an edge other than a
    loop; vertices without edges are the caller's to add. Loops, repeated and
    reversed edges and null ends are harmless (null ends are ignored). ``by``
    keeps several graphs apart in one run. Vertex type: anything orderable.
    """
    by = list(by or [])
    cur = edges.select(*by, F.col(src).alias("a"), F.col(dst).alias("b")).filter(F.col("a") != F.col("b")).distinct()
    held = stage(cur, "star")
    mark = _mark(held.df, by)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        nxt = stage(_step(_step(held.df, by, True), by, False), "star")
        new = _mark(nxt.df, by)
        held.drop()
        held, (mark, old) = nxt, (new, mark)
        if new == old:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    leaf = held.df.select(*by, F.col("a").alias("v"), F.col("b").alias("comp"))
    return leaf.unionByName(leaf.select(*by, F.col("comp").alias("v"), "comp").distinct())


def label_or_self(v: Column, comp: Column) -> Column:
    """Component of a vertex that may have no edge."""
    return F.coalesce(comp, v)


def local_labels(a, b):
    """(vertices, labels): least reachable vertex of every end of the pairs,
    by repeated minimum and pointer jumping on arrays."""
    import numpy as np

    v, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(v))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        while True:
            jump = new[new]
            if (jump == new).all():
                break
            new = jump
        if (new == label).all():
            return v, v[label]
        label = new


def components(edges: DataFrame, by: tuple[str, ...] = ("rep",), strategy: str = "auto", src: str = "src", dst: str = "dst", task_rows: int | None = None, seed: int = 1, rate: float | None = None) -> DataFrame:
    """(*by, v, comp): least vertex reachable, for every vertex with an edge.

    ``local``: one task per value of ``by``; for pairs that fit a task.
    ``star``: star contractions across the cluster. ``sampled``: components of
    a share ``rate`` of the edges (one over the logarithm of their number if
    not given), then of those edges alone that cross them. ``auto``: the pairs
    are written once and counted; local while the largest group has at most
    ``task_rows`` (``TASK_ROWS`` if not given), star beyond.
    """
    if strategy == "auto":
        task_rows = TASK_ROWS if task_rows is None else task_rows
        edges = stage(edges.select(*by, src, dst), "pairs").df
        most = edges.groupBy(*by).count().agg(F.max("count")).first()[0] or 0
        strategy = "local" if most <= task_rows else "star"
    kind = edges.schema[src].dataType.simpleString()
    if strategy == "local":
        keys = ", ".join(f"{c} {edges.schema[c].dataType.simpleString()}" for c in by)
        narrow = edges.select(*by, F.col(src).alias("a"), F.col(dst).alias("b"))

        def run(key, pdf):
            import pandas as pd

            v, comp = local_labels(pdf["a"].to_numpy(), pdf["b"].to_numpy())
            return pd.DataFrame({**dict(zip(by, key, strict=True)), "v": v, "comp": comp})

        return narrow.groupBy(*by).applyInPandas(run, f"{keys}, v {kind}, comp {kind}")
    if strategy == "star":
        return star_components(edges, src, dst, list(by))
    if strategy == "sampled":
        if rate is None:
            rate = 1 / max(1.0, math.log(max(2, edges.count())))
        part = edges.filter(F.pmod(F.xxhash64(F.lit(seed), *by, src, dst), F.lit(1 << 20)) < int(rate * (1 << 20)))
        first = stage(star_components(part, src, dst, list(by)), "sampled").df
        a = first.withColumnsRenamed({"v": src, "comp": "ca"})
        b = first.withColumnsRenamed({"v": dst, "comp": "cb"})
        raised = edges.join(a, [*by, src], "left").join(b, [*by, dst], "left").select(*by, F.coalesce("ca", src).alias("a"), F.coalesce("cb", dst).alias("b"))
        rest = star_components(raised.filter("a <> b").distinct(), "a", "b", list(by)).select(*by, F.col("v").alias("comp"), F.col("comp").alias("top"))
        whole = edges.select(*by, F.explode(F.array(src, dst)).alias("v")).distinct().join(first, [*by, "v"], "left").select(*by, "v", F.coalesce("comp", "v").alias("comp"))
        return whole.join(rest, [*by, "comp"], "left").select(*by, "v", F.coalesce("top", "comp").alias("comp"))
    raise ValueError(f"no such strategy: {strategy}")


def with_singletons(labels: DataFrame, vertices: DataFrame, reps: int) -> DataFrame:
    """Labels of every vertex in every repetition; alone where it has no edge."""
    grid = vertices.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    return grid.join(labels, ["rep", "v"], "left").select("rep", "v", F.coalesce("comp", "v").alias("comp"))
