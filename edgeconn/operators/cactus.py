"""All minimum cuts of a kernel as a cactus, and its lift to the graph."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators import solve as S
from edgeconn.operators import sparse as K
from edgeconn.operators.graph import Graph, numbered
from edgeconn.operators.mincut import DENSE_VERTICES
from edgeconn.plans.staging import stage


@dataclass(frozen=True)
class Cactus:
    """nodes: frozensets of kernel vertices (may be empty). edges: (node, node,
    cycle number or None, multiplicity): tree edges carry 2, cycle edges 1."""

    value: float
    nodes: list[frozenset]
    edges: list[tuple[int, int, int | None, int]]

    def cut_count(self) -> int:
        cycles: dict[int, int] = {}
        for _, _, c, _ in self.edges:
            if c is not None:
                cycles[c] = cycles.get(c, 0) + 1
        return sum(c is None for _, _, c, _ in self.edges) + sum(n * (n - 1) // 2 for n in cycles.values())


def _cross(a: frozenset, b: frozenset, everything: frozenset) -> bool:
    return bool(a & b and a - b and b - a and everything - a - b)


def build_cactus(w, names: list, value: float) -> Cactus:
    """Cuts that no other crosses are tree edges; each class of crossing cuts
    is a cycle of the vertex groups that the class tells apart."""
    everything = frozenset(names)
    cuts = [frozenset(n for n, s in zip(names, side, strict=True) if s) for side in S.enumerate_cuts(w, value)]
    cuts = sorted(set(cuts), key=lambda c: (len(c), sorted(c)))
    root = names[0]  # no listed shore has it
    klass = list(range(len(cuts)))

    def find(i: int) -> int:
        while klass[i] != i:
            klass[i] = klass[klass[i]]
            i = klass[i]
        return i

    for i, a in enumerate(cuts):
        for j in range(i):
            if _cross(a, cuts[j], everything):
                klass[find(i)] = find(j)
    members: dict[int, list[frozenset]] = {}
    for i, c in enumerate(cuts):
        members.setdefault(find(i), []).append(c)
    family: set[frozenset] = set()
    cycles: list[list[frozenset]] = []
    for group in members.values():
        if len(group) == 1:
            continue
        parts: dict[tuple, set] = {}
        for v in names:
            parts.setdefault(tuple(v in c for c in group), set()).add(v)
        ring = [frozenset(x) for x in parts.values()]
        known = set(cuts)
        order = [next(x for x in ring if root in x)]
        rest = sorted((x for x in ring if root not in x), key=sorted)
        while rest:
            here = order[-1]
            near = [x for x in rest if (everything - (here | x) if root in here | x else here | x) in known]
            step = near[0] if near else rest[0]
            order.append(step)
            rest.remove(step)
        cycles.append(order[1:])
        family |= set(order[1:])
    # A single group against the rest is two edges of its cycle already.
    on_cycle = family | {frozenset().union(*ring) for ring in cycles}
    trees = [g[0] for g in members.values() if len(g) == 1 and g[0] not in on_cycle]
    family |= set(trees)
    sets = sorted(family, key=lambda c: (len(c), sorted(c)))
    parent = {c: next((d for d in sets if c < d), None) for c in sets}
    index = {None: 0} | {c: i + 1 for i, c in enumerate(sets)}
    nodes = [everything - frozenset().union(*(c for c in sets if parent[c] is None))]
    nodes += [c - frozenset().union(*(d for d in sets if parent[d] == c)) for c in sets]
    edges: list[tuple[int, int, int | None, int]] = [(index[c], index[parent[c]], None, 2) for c in trees]
    for no, ring in enumerate(cycles):
        at = [index[parent[ring[0]]], *(index[c] for c in ring)]
        edges += [(a, b, no, 1) for a, b in zip(at, at[1:] + at[:1], strict=True)]
    return Cactus(value, nodes, edges)


def star_cactus(vertices: list[int], delta: float, low: list[int]) -> Cactus:
    """The cactus where every minimum cut is one vertex: a center and a double
    edge to each vertex of least degree."""
    hub = frozenset(vertices) - frozenset(low)
    if len(vertices) == 2:
        return Cactus(delta, [frozenset([vertices[0]]), frozenset([vertices[1]])], [(0, 1, None, 2)])
    return Cactus(delta, [hub, *(frozenset([v]) for v in low)], [(i + 1, 0, None, 2) for i in range(len(low))])


def lift(c: Cactus | None, groups: dict[int, list[int]], delta: float, low: list[int]) -> Cactus:
    """A kernel's cactus for the graph: nodes get the vertices of their groups;
    where the least degree equals the minimum, each vertex of that degree that
    shares its node hangs off it by a double edge."""
    if c is None or c.value > delta:
        return star_cactus(sorted(v for g in groups.values() for v in g), delta, low)
    nodes = [frozenset(v for k in node for v in groups.get(k, [k])) for node in c.nodes]
    edges = list(c.edges)
    if c.value == delta:
        for v in low:
            at = next(i for i, x in enumerate(nodes) if v in x)
            degree = sum(at in e[:2] for e in edges)
            if len(nodes[at]) > 1 or degree > 2 and nodes[at] == {v}:
                nodes[at] = nodes[at] - {v}
                nodes.append(frozenset([v]))
                edges.append((len(nodes) - 1, at, None, 2))
    return Cactus(c.value, nodes, edges)


def min_cut_cactus(g: Graph, labels: DataFrame, kernel_w: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cactus_nodes, cactus_edges) of all minimum cuts of the graph.

    ``labels`` (v, comp) and ``kernel_w`` (cu, cv, mult) come from a contraction
    that keeps all non-trivial minimum cuts. The kernel is solved in one task;
    member lists are joined in afterwards, so that task never holds vertices.
    """
    delta = g.profile["min_degree"]
    low = g.degrees.filter(F.col("deg") == delta).select("v")

    def run(pdf):
        import numpy as np
        import pandas as pd

        if not len(pdf):  # the contraction left one vertex: all minimum cuts are single vertices
            return pd.DataFrame(columns=["node", "comp", "a", "b", "cycle_id", "mult", "value"])
        kernel, names = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        value, _ = K.solve_scan(kernel)
        rows = []
        if value <= delta:
            # What is connected by more than the minimum no minimum cut separates.
            kernel, label = K.shrink(kernel, value + 1)
            group = {int(names[i]): int(names[label == c].min()) for c in range(kernel[0]) for i in np.flatnonzero(label == c)}
            names = np.array([int(names[label == c].min()) for c in range(kernel[0])])
            if len(names) > DENSE_VERTICES:
                raise ValueError(f"{len(names)} groups of kernel vertices are too many for one task")
            w = S.square(kernel)
            c = build_cactus(w, [int(x) for x in names], value)
            inside: dict[int, list[int]] = {}
            for v, head in group.items():
                inside.setdefault(head, []).append(v)
            rows += [(i, k, None, None, None, None, value) for i, node in enumerate(c.nodes) for k in (sorted(x for head in node for x in inside[head]) or [None])]
            rows += [(None, None, a, b, cyc, m, value) for a, b, cyc, m in c.edges]
        return pd.DataFrame(rows, columns=["node", "comp", "a", "b", "cycle_id", "mult", "value"]).astype({c: "Int64" for c in ("node", "comp", "a", "b", "cycle_id", "mult")})

    spark = g.vertices.sparkSession
    made = stage(kernel_w.groupBy().applyInPandas(run, "node int, comp long, a int, b int, cycle_id int, mult int, value double"), "cactus").df
    value = made.agg(F.min("value")).first()[0]
    edges = made.filter("a IS NOT NULL").select("a", "b", "cycle_id", "mult")
    if value is None:  # every minimum cut is one vertex
        base = labels.select("v", F.lit(0).alias("node"))
        edges = spark.createDataFrame([], "a int, b int, cycle_id int, mult int")
    else:
        base = labels.join(made.filter("node IS NOT NULL").select("comp", "node"), "comp").select("v", "node")
    empty = made.filter("node IS NOT NULL AND comp IS NULL").select("node")
    if value is None or value == delta:
        sizes = base.groupBy("node").count()
        degree = edges.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("ends"))
        shared = low.join(base, "v").join(sizes, "node").join(degree, "node", "left").filter((F.col("count") > 1) | (F.coalesce("ends", F.lit(0)) > 2))
        first = int(made.agg(F.coalesce(F.max("node"), F.lit(0))).first()[0]) + 1
        hung = numbered(shared.select("v", F.col("node").alias("old")), "v", "no").select("v", (F.col("no") + first).cast("int").alias("node"), "old")
        hung = stage(hung, "cactus-leaves").df
        base = base.join(hung.select("v", F.col("node").alias("own")), "v", "left").select("v", F.coalesce("own", "node").alias("node"))
        edges = edges.unionByName(hung.select(F.col("node").alias("a"), F.col("old").alias("b"), F.lit(None).cast("int").alias("cycle_id"), F.lit(2).alias("mult")))
    nodes = base.groupBy("node").agg(F.sort_array(F.collect_list("v")).alias("members"))
    hollow = empty.unionByName(edges.select(F.explode(F.array("a", "b")).alias("node"))).distinct().join(nodes, "node", "left_anti")
    return nodes.unionByName(hollow.select("node", F.array().cast("array<long>").alias("members"))), edges


def small_cut_sides(kernel_w: DataFrame, bound: float, seed: int = 1) -> DataFrame:
    """(cut int, value double, side array<long>): all cuts of the kernel of at
    most ``bound`` edges, kernel vertices of the shore without the least one."""

    def run(pdf):
        import numpy as np
        import pandas as pd

        w, names = S.dense(list(zip(pdf["cu"], pdf["cv"], pdf["mult"], strict=True)))
        sides = sorted(S.small_cuts(w, bound, seed), key=lambda s: s.tobytes())
        value = [float(w[s][:, ~s].sum()) for s in sides]
        return pd.DataFrame({"cut": range(len(sides)), "value": value, "side": [[int(x) for x in np.array(names)[s]] for s in sides]})

    return kernel_w.groupBy().applyInPandas(run, "cut int, value double, side array<long>")
