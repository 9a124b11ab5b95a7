"""Diameters, balls and low-diameter covers of 2-out samples."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgeconn.operators.components import components
from edgeconn.plans.staging import stage


def _bfs(adjacent: dict, start) -> dict:
    far, front = {start: 0}, [start]
    while front:
        nxt = []
        for v in front:
            for x in adjacent[v]:
                if x not in far:
                    far[x] = far[v] + 1
                    nxt.append(x)
        front = nxt
    return far


def component_diameters(draws: DataFrame, labels: DataFrame, exact_up_to: int = 2000) -> DataFrame:
    """(rep, comp, size, lower, upper): hop diameter of each component of the
    sampled edges. Exact up to ``exact_up_to`` vertices; beyond, the last level
    of a double sweep from below and twice its first from above."""
    pairs = draws.select("rep", "v", "nbr").join(labels, ["rep", "v"]).select("rep", "comp", "v", "nbr")

    def run(key, pdf):
        import pandas as pd

        adjacent: dict = {}
        for a, b in zip(pdf["v"], pdf["nbr"], strict=True):
            adjacent.setdefault(a, set()).add(b)
            adjacent.setdefault(b, set()).add(a)
        if len(adjacent) <= exact_up_to:
            low = high = max(max(_bfs(adjacent, v).values()) for v in adjacent)
        else:
            first = _bfs(adjacent, min(adjacent))
            end = max(first, key=first.get)
            low = max(_bfs(adjacent, end).values())
            high = 2 * max(first.values())
        return pd.DataFrame({"rep": [key[0]], "comp": [key[1]], "size": [len(adjacent)], "lower": [low], "upper": [high]})

    return pairs.groupBy("rep", "comp").applyInPandas(run, "rep int, comp long, size long, lower int, upper int")


def ball_growth(draws: DataFrame, radius: int, centers: DataFrame | None = None) -> DataFrame:
    """(rep, v, i, level, ball): vertices that out-draws reach from v in exactly
    i and in at most i steps. Each step is a join of the outermost level with
    the draws, less what was reached before."""
    out = draws.select("rep", F.col("v").alias("at"), F.col("nbr").alias("to")).distinct()
    start = (centers.crossJoin(F.broadcast(out.select("rep").distinct())) if centers is not None else out.select("rep", F.col("at").alias("v")).distinct()).select("rep", "v")  # repetitions: few rows
    seen = stage(start.select("rep", "v", F.col("v").alias("at"), F.lit(0).alias("i")), "ball").df
    for i in range(1, radius + 1):
        edge = seen.filter(F.col("i") == i - 1).join(out, ["rep", "at"]).select("rep", "v", F.col("to").alias("at")).distinct()
        fresh = edge.join(seen.select("rep", "v", "at"), ["rep", "v", "at"], "left_anti").withColumn("i", F.lit(i))
        seen = stage(seen.unionByName(fresh.select("rep", "v", "at", "i")), "ball").df
    level = seen.groupBy("rep", "v", "i").agg(F.count(F.lit(1)).alias("level"))
    grid = start.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(radius))))
    whole = grid.join(level, ["rep", "v", "i"], "left").withColumn("level", F.coalesce("level", F.lit(0)))
    return whole.withColumn("ball", F.sum("level").over(Window.partitionBy("rep", "v").orderBy("i").rowsBetween(Window.unboundedPreceding, 0))).select("rep", "v", "i", "level", "ball")


def ball_members(draws: DataFrame, radius: int) -> DataFrame:
    """(rep, v, at): what lies within ``radius`` out-draws of v."""
    out = draws.select("rep", F.col("v").alias("at"), F.col("nbr").alias("to")).distinct()
    seen = out.select("rep", F.col("at").alias("v"), "at").distinct()
    for _ in range(radius):
        seen = stage(seen.unionByName(seen.join(out, ["rep", "at"]).select("rep", "v", F.col("to").alias("at"))).distinct(), "members").df
    return seen


def disjoint_balls(members: DataFrame, seed: int = 1, rounds: int = 50) -> DataFrame:
    """(rep, v): a maximal set of centers whose balls share no vertex.

    In each round a center enters if its priority is the least among all balls
    that cover any of its vertices; balls that meet a chosen one leave.
    """
    left = members.withColumn("rank", F.struct(F.xxhash64(F.lit(seed), "rep", "v").alias("h"), F.col("v").alias("c")))
    left = stage(left, "balls").df
    chosen = None
    for _ in range(rounds):
        least = left.groupBy("rep", "at").agg(F.min("rank").alias("m"))
        wins = left.join(least, ["rep", "at"]).groupBy("rep", "v").agg(F.min((F.col("rank") == F.col("m")).cast("int")).alias("w")).filter("w = 1").select("rep", "v")
        wins = stage(wins, "wins").df
        chosen = wins if chosen is None else chosen.unionByName(wins)
        taken = left.join(wins, ["rep", "v"], "left_semi").select("rep", "at").distinct()
        lost = left.join(taken, ["rep", "at"], "left_semi").select("rep", "v").distinct()
        left = stage(left.join(lost, ["rep", "v"], "left_anti"), "balls").df
        if left.isEmpty():
            break
    return chosen


def low_diameter_cover(draws: DataFrame, n: int, delta: int, c: float = 4.0, seed: int = 1, mode: str = "simple") -> tuple[DataFrame, DataFrame]:
    """(forest rep, v, parent, root, depth; centers rep, v, special).

    A forest of sampled edges that covers all vertices by trees of depth
    O(log n). ``simple``: each vertex is a center with probability c ln n /
    degree; the rest joins the nearest center level by level; what no center
    reaches within the radius gives one special center per component left, and
    goes on. ``staged``: only the first draw of each vertex and the lower three
    fifths of its other draws are open at first, the rest once pieces have
    formed. With a least degree of O(log n) every vertex is a center.
    """
    verts = draws.select("rep", "v").distinct()
    rate = min(1.0, c * math.log(max(2, n)) / max(1, delta))
    radius = max(1, math.ceil(c * math.log(max(2, n))))
    chance = F.xxhash64(F.lit(seed), "rep", "v").cast("double") / 2.0**64 + 0.5
    centers = verts.filter(chance < rate).withColumn("special", F.lit(False))
    ends = F.explode(F.array(F.struct(F.col("v").alias("a"), F.col("nbr").alias("b")), F.struct(F.col("nbr").alias("a"), F.col("v").alias("b"))))
    open_first = draws.filter((F.col("j") == 0) | (F.pmod(F.xxhash64(F.lit(seed), "rep", "eid"), F.lit(5)) < 3)) if mode == "staged" else draws
    tree = stage(centers.select("rep", "v", F.lit(None).cast("long").alias("parent"), F.col("v").alias("root"), F.lit(0).alias("depth")), "cover").df
    for sample in [open_first, draws] if mode == "staged" else [draws]:
        sides = stage(sample.select("rep", ends.alias("e")).select("rep", "e.a", "e.b").distinct(), "cover-edges").df
        tree = _spread(tree, sides, radius)
    while True:  # once for all components left; again only for what lies beyond the radius
        alone = stage(verts.join(tree.select("rep", "v"), ["rep", "v"], "left_anti"), "cover-alone").df
        if alone.isEmpty():
            break
        inner = sides.join(alone.withColumnRenamed("v", "a"), ["rep", "a"], "left_semi").join(alone.withColumnRenamed("v", "b"), ["rep", "b"], "left_semi")
        top = components(inner.filter("a < b"), src="a", dst="b")
        least = alone.join(top, ["rep", "v"], "left").select("rep", F.coalesce("comp", "v").alias("v")).distinct()
        first = stage(least, "cover-special").df
        centers = centers.unionByName(first.withColumn("special", F.lit(True)))
        tree = _spread(tree.unionByName(first.select("rep", "v", F.lit(None).cast("long").alias("parent"), F.col("v").alias("root"), F.lit(0).alias("depth"))), sides, radius)
    return tree, centers


def _spread(tree: DataFrame, sides: DataFrame, radius: int) -> DataFrame:
    """Level by level from what the tree has; a vertex joins the least parent."""
    tree = stage(tree, "cover").df
    for _ in range(radius):
        step = tree.select("rep", F.col("v").alias("a"), "root", "depth").filter(F.col("depth") < radius).join(sides, ["rep", "a"])
        new = step.join(tree.select("rep", F.col("v").alias("b")), ["rep", "b"], "left_anti").groupBy("rep", F.col("b").alias("v")).agg(F.min(F.struct("depth", "a", "root")).alias("m"))
        new = stage(new.select("rep", "v", F.col("m.a").alias("parent"), "m.root", (F.col("m.depth") + 1).alias("depth")), "cover-level").df
        if new.isEmpty():
            return tree
        tree = stage(tree.unionByName(new), "cover").df
    return tree
