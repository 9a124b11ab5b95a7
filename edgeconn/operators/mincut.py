"""Edge connectivity: contract, solve what is left, compare with the degrees."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators import solve as S
from edgeconn.operators import sparse as K
from edgeconn.operators.components import components
from edgeconn.operators.contract import (
    adaptive_threshold,
    collapse,
    contract_once,
    edge_votes,
    inter_component_edges,
    k_out_labels,
    kernel_edges,
    merge_low_votes,
    widen,
)
from edgeconn.operators.graph import Graph, check_ids
from edgeconn.operators.probe import probe_contract
from edgeconn.plans.planning import plan_repetitions
from edgeconn.plans.staging import stage

#: Kernel rows that one task may solve; a larger kernel raises, it is not cut.
KERNEL_ROWS = 4_000_000
#: Kernel vertices of solvers that hold a square array.
DENSE_VERTICES = 4_000


@dataclass(frozen=True)
class CutResult:
    lambda_value: int
    kind: str  # trivial, nontrivial or disconnected
    side: DataFrame = field(compare=False, repr=False)
    side_size: int = 0
    kernel_vertices: int = 0
    kernel_edges: int = 0
    q: int = 0
    r: int = 0
    p_assumed: float = 0.0

    def row(self) -> dict:
        return {k: v for k, v in asdict_shallow(self).items() if k != "side"}


def asdict_shallow(x) -> dict:
    return {k: getattr(x, k) for k in x.__dataclass_fields__}


def solve_kernel(kernel_w: DataFrame, labels: DataFrame, solver: str = "auto", k: float | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """(*by, value double, side array<long>, vertices long): the least cut of
    each kernel (by..., cu, cv, mult), solved in one task each. ``side`` lists
    kernel vertices. ``auto`` and ``scan`` need memory by the rows; the other
    solvers hold a square array, so they refuse kernels over DENSE_VERTICES
    vertices. Kernels over KERNEL_ROWS rows are refused by all."""
    keys = list(by) or ["one"]
    rows = kernel_w if by else kernel_w.withColumn("one", F.lit(0))
    most = rows.groupBy(*keys).count().agg(F.max("count")).first()[0] or 0
    if most > KERNEL_ROWS:
        raise ValueError(f"a kernel of {most} rows is too large for one task; certify it first")

    def run(key, pdf):
        import numpy as np
        import pandas as pd

        kernel, names = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        if solver in ("auto", "scan"):
            value, side = K.solve_scan(kernel)
        elif len(names) > DENSE_VERTICES:
            raise ValueError(f"{len(names)} kernel vertices are too many for the solver {solver}; take scan")
        else:
            value, side = S.solve(S.square(kernel), solver, k)
        shore = [] if side is None else [int(x) for x in names[np.asarray(side, bool)]]
        return pd.DataFrame({**{c: [v] for c, v in zip(keys, key, strict=True)}, "value": [float(value)], "side": [shore], "vertices": [len(names)]})

    kinds = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in keys)
    return rows.groupBy(*keys).applyInPandas(run, f"{kinds}, value double, side array<long>, vertices long")


def _trivial(g: Graph, **counts) -> CutResult:
    p = g.profile
    return CutResult(p["min_degree"], "trivial", g.vertices.select("v", (F.col("v") == p["argmin"]).alias("in_s")), 1, **counts)


def _lifted(g: Graph, labels: DataFrame, value: float, shore: list[int], **counts) -> CutResult:
    """The result whose side are the vertices labelled by ``shore`` (kernel
    vertices of one solved kernel); the shore of fewer vertices, of equal ones
    that with the least vertex, is reported."""
    chosen = labels.select("comp").distinct().filter(F.col("comp").isin(shore)) if len(shore) < 1000 else labels.sparkSession.createDataFrame([(x,) for x in shore], "comp long")
    marked = labels.join(chosen.withColumn("hit", F.lit(True)), "comp", "left").select("v", F.coalesce("hit", F.lit(False)).alias("in_s"))
    row = marked.agg(F.sum(F.col("in_s").cast("long")).alias("s"), F.count(F.lit(1)).alias("n"), F.min(F.when(F.col("in_s"), F.col("v"))).alias("a"), F.min(F.when(~F.col("in_s"), F.col("v"))).alias("b")).first()
    if (row.n - row.s, row.b) < (row.s, row.a):
        marked = marked.select("v", (~F.col("in_s")).alias("in_s"))
    size = min(row.s, row.n - row.s)
    return CutResult(int(value), "trivial" if size == 1 else "nontrivial", marked, size, **counts)


def edge_connectivity(g: Graph, solver: str = "auto", profile: str = "mpc", mode: str = "vote", eps: float = 1.0, gamma: float = 1.0, p: float | None = 0.25, q: int | None = 16, r: int | str = "adaptive", edge_step: str | None = None, seed: int = 1, strategy: str = "auto", skip: str = "chunked", hashing: str = "xxhash64", draw: str = "minhash", guard_c: float | None = None) -> CutResult:
    """The least number of edges whose loss disconnects the graph, with a side.

    profile: ``mpc`` filters survivors by fingerprint, ``pram`` fetches labels
    for all edges, ``congest`` contracts by the 2-out partition alone, ``probe``
    asks probed forests. mode ``vote`` keeps edges by votes over q repetitions,
    ``best_of`` solves each repetition's kernel. edge_step ``uniform`` is fused
    with the 2-out sample; at minimum degrees under 8 a uniform share of 1/(2
    degree) hurts small cuts, so ``certificate`` is taken there. q None takes
    the planner's number for eps, gamma and p, which grows with the logarithm
    of the vertices. strategy, hashing, draw: of all components runs and draws.
    No task reads the edges of the graph: components see draws, samples and
    what one repetition leaves between its components.

    Whatever is returned is a real cut, so it is never under the connectivity;
    it is the connectivity with probability growing in q.
    """
    info = g.profile
    n, delta = info["n"], info["min_degree"]
    none = g.vertices.select("v", F.lit(False).alias("in_s"))
    if n < 2:
        return CutResult(0, "trivial", none)
    if delta == 0:
        return CutResult(0, "disconnected", g.vertices.select("v", (F.col("v") == info["argmin"]).alias("in_s")), 1)
    check_ids(g.edges)
    plan = plan_repetitions(n, eps, gamma, p, "probe" if profile == "probe" else "contract", q)
    q = plan.q
    known = {"q": q, "p_assumed": plan.p}
    if profile == "probe":
        threshold = plan.threshold if r == "theory" else r if isinstance(r, int) else max(1, q // 8)
        apart = _disconnected(g, k_out_labels(g, 2, 1, seed, strategy=strategy, hashing=hashing), strategy)
        if apart:
            return apart
        got = probe_contract(g, q, threshold, seed, skip, guard_c=guard_c, strategy=strategy, hashing=hashing)
        return _answer(g, stage(got.labels, "labels").df, stage(collapse(got.kernel), "kernel").df, solver, {**known, "r": threshold})
    apart = _disconnected(g, stage(k_out_labels(g, 2, 1, seed, strategy=strategy, hashing=hashing, draw=draw), "one-labels").df, strategy)
    if apart:  # told by one repetition, before all are drawn
        return apart
    step = edge_step or ("none" if profile == "congest" else "uniform" if delta >= 8 else "certificate")
    labels = stage(contract_once(g, q, seed, edge_step=step, strategy=strategy, hashing=hashing, draw=draw), "labels").df
    if mode == "best_of":
        kernels = stage(collapse(kernel_edges(g, labels), "rep"), "kernels").df
        best = solve_kernel(kernels, labels, solver, delta, ("rep",)).agg(F.min(F.struct("value", "rep", "side", "vertices")).alias("b")).first().b
        if best is None or best.value >= delta:
            return _trivial(g, **known)
        return _lifted(g, labels.filter(F.col("rep") == best.rep).select("v", "comp"), best.value, list(best.side), kernel_vertices=best.vertices, **known)
    wide = stage(widen(labels), "wide").df
    votes = stage(edge_votes(inter_component_edges(g.edges, wide, "naive" if profile == "pram" else "fingerprint")), "votes").df
    threshold = plan.threshold if r == "theory" else r if isinstance(r, int) else adaptive_threshold(votes, n)
    voted = merge_low_votes(g, wide, votes, threshold, strategy)
    return _answer(g, stage(voted.labels, "merged").df, stage(collapse(voted.kernel), "kernel").df, solver, {**known, "r": threshold})


def _disconnected(g: Graph, labels: DataFrame, strategy: str) -> CutResult | None:
    """The least component of the graph as a side, if there are several: found
    from one repetition's components and the edges that run between them."""
    between = kernel_edges(g, labels).select("rep", "cu", "cv").distinct()
    top = components(between, src="cu", dst="cv", strategy=strategy).select(F.col("v").alias("comp"), F.col("comp").alias("top"))
    whole = stage(labels.select("v", "comp").join(top, "comp", "left").select("v", F.coalesce("top", "comp").alias("comp")), "whole").df
    parts = whole.groupBy("comp").count().orderBy("count", "comp").limit(2).collect()
    if len(parts) < 2:
        return None
    return CutResult(0, "disconnected", whole.select("v", (F.col("comp") == parts[0].comp).alias("in_s")), parts[0]["count"])


def _answer(g: Graph, labels: DataFrame, kernel_w: DataFrame, solver: str, known: dict) -> CutResult:
    """The kernel's cut if it is under the least degree, else that."""
    size = kernel_w.agg(F.coalesce(F.sum("mult"), F.lit(0)).alias("m")).first().m
    found = solve_kernel(kernel_w, labels, solver, g.profile["min_degree"]).collect() if size else []
    counts = {"kernel_vertices": found[0].vertices if found else 1, "kernel_edges": size, **known}
    if not found or found[0].value >= g.profile["min_degree"]:
        return _trivial(g, **counts)
    return _lifted(g, labels, found[0].value, list(found[0].side), **counts)


def certified_connectivity(g: Graph, solver: str = "capped", seed: int = 1, reps: int = 8) -> CutResult:
    """Best of several 2-out contractions, each shrunk by a certificate of
    twice the least degree and solved with the degree as cap."""
    return edge_connectivity(g, solver, mode="best_of", q=reps, edge_step="certificate", seed=seed)


def weighted_connectivity(pairs: DataFrame, weight: str, solver: str = "max_adjacency") -> DataFrame:
    """(value, side, vertices) of a weighted graph (src, dst, weight) as it is:
    contraction by samples is for simple graphs alone."""
    w = pairs.groupBy(F.least("src", "dst").alias("cu"), F.greatest("src", "dst").alias("cv")).agg(F.sum(weight).alias("mult"))
    return solve_kernel(w, w, solver).drop("one")


def as_row(spark, result: CutResult) -> DataFrame:
    schema = "lambda_value long, kind string, side_size long, kernel_vertices long, kernel_edges long, q int, r int, p_assumed double"
    return spark.createDataFrame([tuple(result.row()[c.split()[0]] for c in schema.split(", "))], schema)
