"""Methods that the contraction is compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators import blocks as X
from edgeconn.operators import solve as S
from edgeconn.operators import sparse as K
from edgeconn.operators.certificate import certificate
from edgeconn.operators.components import components
from edgeconn.operators.contract import collapse, k_out_labels, kernel_edges, sample_labels
from edgeconn.operators.graph import Graph
from edgeconn.operators.mincut import DENSE_VERTICES, KERNEL_ROWS, solve_kernel
from edgeconn.operators.uniform import uniform_runs
from edgeconn.plans.staging import stage

#: How a figure relates to the method of its name.
FULL, STAND_IN, COST_MODEL = "full", "stand-in", "cost-model"


def whole_kernel(g: Graph) -> DataFrame:
    """The graph itself as a kernel."""
    return g.edges.select("eid", F.col("src").alias("cu"), F.col("dst").alias("cv"))


def least_cut(g: Graph) -> float:
    """The exact connectivity, by ``cut_kernel``."""
    if not g.profile["min_degree"]:
        return 0.0
    rows, _ = cut_kernel(g)
    return min(float(g.profile["min_degree"]), solve_kernel(rows, rows, "scan").first().value)


def cut_kernel(g: Graph, ratio: float = 1.0, vertices: int | None = None) -> tuple[DataFrame, float]:
    """(rows cu, cv, mult; bound): a kernel that a task can hold and in which
    all cuts under ``bound``, the minimum ones among them, have their size.

    A graph of at most KERNEL_ROWS edges (and ``vertices`` vertices) is its own
    kernel. Of a larger one a certificate of level k is taken and what scans
    prove connected by k is contracted, k being doubled from 8 times ``ratio``
    until the least cut times ``ratio`` is under k. Nothing is sampled; where even the certificate
    has over KERNEL_ROWS edges, that is an error.
    """
    p = g.profile
    if p["m"] <= KERNEL_ROWS and not (vertices and p["n"] > vertices):
        return collapse(whole_kernel(g)), math.inf
    most, k = int(ratio * p["min_degree"]) + 1, int(8 * ratio)
    while True:
        k = min(k, most)
        if g.blocks is not None:
            kept = tied_kernel(g, k)[1]
        else:
            kept = stage(certificate(whole_kernel(g).withColumn("rep", F.lit(0)), k, "merge"), "cut-certificate").df
            size = kept.count()
            if size > KERNEL_ROWS:
                raise ValueError(f"a certificate of level {k} has {size} edges, too many for one task")
            kept = collapse(kept)
        rows = stage(kept.groupBy().applyInPandas(_shrunk(k), "cu long, cv long, mult long"), "cut-kernel").df
        found = solve_kernel(rows, rows, "scan").collect()
        if k == most or found and found[0].value * ratio < k:
            return rows, float(k)
        k *= 2


def tied_kernel(g: Graph, k: int) -> tuple[DataFrame, DataFrame]:
    """(labels v, comp of the vertices that are not alone; rows cu, cv, mult) of
    a graph of blocks, all cuts under k as they are: tasks keep certificates of
    the edges that they read, and what their last forests tie is contracted."""
    rows = stage(X.sieved(g.blocks, k), "sieved").df
    ties = rows.filter("tie").select(F.lit(0).alias("rep"), F.col("a").alias("src"), F.col("b").alias("dst"))
    labels = stage(components(ties).select("v", "comp"), "tied").df
    la, lb = labels.toDF("a", "ca"), labels.toDF("b", "cb")
    ends = rows.filter("NOT tie").join(la, "a", "left").join(lb, "b", "left").select(F.coalesce("ca", "a").alias("ca"), F.coalesce("cb", "b").alias("cb"))
    left = stage(collapse(ends.filter("ca <> cb").select(F.least("ca", "cb").alias("cu"), F.greatest("ca", "cb").alias("cv"))), "tied-kernel").df
    size = left.count()
    if size > KERNEL_ROWS:
        raise ValueError(f"certificates of level {k} leave {size} rows, too many for one task")
    return labels, left


def level_kernel(g: Graph, k: int) -> DataFrame:
    """(cu, cv, mult) of a certificate of level k; of a graph of blocks over a
    task's edges, of what is left by ``tied_kernel``."""
    if g.blocks is not None and g.profile["m"] > KERNEL_ROWS:
        return tied_kernel(g, k)[1]
    return collapse(certificate(whole_kernel(g).withColumn("rep", F.lit(0)), k, "merge"))


def level_value(g: Graph, k: int) -> DataFrame:
    """(value): the least cut of ``level_kernel``; where that contracts, cuts
    from k on are told by the least degree."""
    rows = level_kernel(g, k)
    if g.blocks is None or g.profile["m"] <= KERNEL_ROWS:
        return solve_kernel(rows, rows, "scan").select("value")
    found = solve_kernel(rows, rows, "scan").collect()
    value = found[0].value if found and found[0].value < k else g.profile["min_degree"]
    return rows.sparkSession.createDataFrame([(float(value),)], "value double")


def _shrunk(k: int):
    def run(pdf):
        import pandas as pd

        kernel, _ = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        (_, u, v, w), _ = K.shrink(kernel, k)
        return pd.DataFrame({"cu": u, "cv": v, "mult": w.astype("int64")})

    return run


def contracted(g: Graph, ratio: float = 1.0) -> tuple[DataFrame, DataFrame] | None:
    """(labels v, comp; kernel cu, cv, mult) of the contraction in ``cut_kernel``,
    with the vertices of the graph: no cut of up to ``ratio`` times the least
    one is contracted, nothing is sampled. None where a certificate may have
    over KERNEL_ROWS edges."""
    p = g.profile
    most, k = int(ratio * p["min_degree"]) + 1, 8
    while True:
        k = min(k, most)
        if g.blocks is not None:
            tied, rows = tied_kernel(g, k)
            rest = stage(rows.groupBy().applyInPandas(_labelled(k), LABELLED), "contracted").df
            kernel = rest.filter("cu IS NOT NULL").select("cu", "cv", "mult")
            found = solve_kernel(kernel, kernel, "scan").collect()
            if k == most or found and found[0].value * ratio < k:
                top = rest.filter("v IS NOT NULL").select(F.col("v").alias("c"), F.col("comp").alias("top"))
                first = g.vertices.join(tied, "v", "left").select("v", F.coalesce("comp", "v").alias("c"))
                return first.join(top, "c", "left").select("v", F.coalesce("top", "c").alias("comp")), kernel
            k *= 2
            continue
        if k * (p["n"] - 1) > KERNEL_ROWS:
            return None
        kept = collapse(certificate(whole_kernel(g).withColumn("rep", F.lit(0)), k, "merge"))
        rows = stage(kept.groupBy().applyInPandas(_labelled(k), LABELLED), "contracted").df
        kernel = rows.filter("cu IS NOT NULL").select("cu", "cv", "mult")
        found = solve_kernel(kernel, kernel, "scan").collect()
        if k == most or found and found[0].value * ratio < k:
            return rows.filter("v IS NOT NULL").select("v", "comp"), kernel
        k *= 2


LABELLED = "v long, comp long, cu long, cv long, mult long"


def _labelled(k: int):
    def run(pdf):
        import numpy as np
        import pandas as pd

        kernel, names = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        (_, u, v, w), label = K.shrink(kernel, k)
        head = names[np.unique(label, return_index=True)[1]]  # the least vertex of each
        whole = {"v": names, "comp": head[label]}, {"cu": head[u], "cv": head[v], "mult": w.astype("int64")}
        return pd.concat([pd.DataFrame(x) for x in whole]).reindex(columns=["v", "comp", "cu", "cv", "mult"]).astype("Int64")

    return run


def real(g: Graph, values: DataFrame, bound: float) -> DataFrame:
    """``values`` with those from ``bound`` on, which a kernel need not have
    kept, replaced by the least degree, which is a cut's size as well."""
    if math.isinf(bound):
        return values
    return values.withColumn("value", F.when(F.col("value") < bound, F.col("value")).otherwise(F.lit(float(g.profile["min_degree"]))))


def replicas(g: Graph, repeats: int, method: str, seed: int = 1) -> DataFrame:
    """(rep, value): independent runs of a Monte-Carlo solver, a task each, on
    the graph or, if it is large, on its ``cut_kernel``."""
    rows, bound = cut_kernel(g)
    rows = rows.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(repeats - 1))))

    def run(key, pdf):
        import pandas as pd

        kernel, _ = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        value, _ = K.solve_recursive(kernel, seed + key[0]) if method == "recursive" else K.solve_uniform(kernel, seed + key[0])
        return pd.DataFrame({"rep": [key[0]], "value": [value]})

    return real(g, rows.groupBy("rep").applyInPandas(run, "rep int, value double"), bound)


def baseline_uniform(g: Graph, repeats: int = 64, seed: int = 1) -> DataFrame:
    """Single-edge contraction of the graph itself down to two vertices, best of
    the repeats; nothing else is contracted before."""
    runs = uniform_runs(g, repeats, seed) if g.profile["m"] > KERNEL_ROWS else replicas(g, repeats, "uniform", seed)
    return runs.agg(F.min("value").alias("value")).withColumn("fidelity", F.lit(FULL))


def baseline_recursive(g: Graph, repeats: int = 4, seed: int = 1) -> DataFrame:
    """Recursive contraction; replicas in parallel are the earlier massively
    parallel method."""
    return replicas(g, repeats, "recursive", seed).agg(F.min("value").alias("value")).withColumn("fidelity", F.lit(FULL))


def baseline_tree_packing(g: Graph) -> DataFrame:
    """Tree packing on the graph as it is or, if it is large, on its ``cut_kernel``."""
    rows, bound = cut_kernel(g, vertices=DENSE_VERTICES)
    return real(g, solve_kernel(rows, rows, "tree_packing").select("value"), bound).withColumn("fidelity", F.lit(FULL))


def tree_packing_parallel(g: Graph, trees: int = 16, seed: int = 1) -> DataFrame:
    """A task per tree: spanning trees of random edge orders instead of a
    greedy packing, each with its best cut over at most two tree edges."""
    rows, bound = cut_kernel(g, vertices=DENSE_VERTICES)
    rows = rows.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(trees - 1))))

    def run(key, pdf):
        import numpy as np
        import pandas as pd

        w = S.square(K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])[0])
        noise = np.random.default_rng(seed + key[0]).exponential(size=w.shape)
        parent, order = S._tree(w, noise + noise.T)
        value = 0.0 if parent is None else min(S.two_respecting(w, parent, order)[0], S.best_single(w)[0])
        return pd.DataFrame({"rep": [key[0]], "value": [value]})

    return real(g, rows.groupBy("rep").applyInPandas(run, "rep int, value double").agg(F.min("value").alias("value")), bound).withColumn("fidelity", F.lit(STAND_IN))


def baseline_filtering(g: Graph, level: int | None = None) -> DataFrame:
    """Filter to a certificate of level least degree + 1 by parts, then solve."""
    k = level or g.profile["min_degree"] + 1
    return level_value(g, k).withColumn("fidelity", F.lit(FULL))


def baseline_small_cut(g: Graph) -> DataFrame:
    """Guess the cut by doubling; a certificate of the guess + 1 settles it."""
    guess = 1
    while True:
        value = level_value(g, guess + 1).first().value
        if value <= guess or guess > g.profile["min_degree"]:
            return g.vertices.sparkSession.createDataFrame([(float(value), STAND_IN)], "value double, fidelity string")
        guess *= 2


def baseline_uniform_sample(g: Graph, reps: int = 16, seed: int = 1) -> DataFrame:
    """(rep, components, value): the uniform edge sample without the 2-out one,
    and the least cut of what it leaves (null where that is one vertex). Of a
    graph over KERNEL_ROWS edges a certificate is contracted by each sample, of
    doubled level until all the cuts are under it."""
    labels = stage(sample_labels(g, reps, seed), "sample-labels").df
    parts = labels.groupBy("rep").agg(F.countDistinct("comp").alias("components"))
    m, k = g.profile["m"], 8
    while True:
        part = g
        if m > KERNEL_ROWS:
            kept = stage(certificate(whole_kernel(g).withColumn("rep", F.lit(0)), k, "merge"), "sample-certificate").df
            part = Graph(g.vertices, kept.select("eid", F.col("cu").alias("src"), F.col("cv").alias("dst")))
        solved = stage(solve_kernel(collapse(kernel_edges(part, labels), "rep"), labels, "scan", by=("rep",)).select("rep", "value"), "sample-values").df
        if part is g or solved.filter(F.col("value") >= k).isEmpty() or part.edges.count() == m:
            return parts.join(solved, "rep", "left")
        k *= 2


def baseline_skeleton(g: Graph, eps: float = 0.5, seed: int = 1) -> DataFrame:
    """(1 + eps) estimate: solve a uniform skeleton dense enough to keep every
    cut's proportion, and scale its value up. The rate goes by a guess of the
    connectivity, from the least degree down: a cut far under the degree needs
    more edges than that tells."""
    p = g.profile
    c = float(max(1, p["min_degree"]))
    while True:
        rate = min(1.0, 3 * math.log(max(2, p["n"])) / (eps**2 * c))
        part = g if rate >= 1 else Graph(g.vertices, g.edges.filter(F.xxhash64(F.lit(seed), "eid").cast("double") / 2.0**64 + 0.5 < rate))
        value = least_cut(part)
        if rate >= 1 or value >= (1 - eps) * rate * c:  # a skeleton of too few edges for its own cut is drawn anew
            return g.vertices.sparkSession.createDataFrame([(value / rate, FULL)], "value double, fidelity string")
        c = max(1.0, min(c / 2, value / rate))


def baseline_estimate(g: Graph, eps: float = 0.5, kernel: tuple[DataFrame, float] | None = None) -> DataFrame:
    """(2 + eps) estimate by repeated certificates, in one task. ``kernel``:
    the ``cut_kernel`` of that ratio, where the caller has it."""
    rows, bound = kernel or cut_kernel(g, 2 + eps)

    def run(pdf):
        import pandas as pd

        return pd.DataFrame({"value": [K.estimate(K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])[0], eps)]})

    return real(g, rows.groupBy().applyInPandas(run, "value double"), bound).withColumn("fidelity", F.lit(FULL))


def baseline_diffusion(g: Graph, steps: int = 20) -> DataFrame:
    """Random-walk sweeps find sparse sides; what no sparse side splits is
    contracted, and the rest is solved. A stand-in for the published method,
    which certifies its sweeps; the value is that of a real cut."""
    rows, bound = cut_kernel(g)

    def run(pdf):
        import numpy as np
        import pandas as pd

        kernel, _ = K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])
        best, signature = K.sweep_cuts(kernel, steps)
        same = signature[kernel[1]] == signature[kernel[2]]
        small, _ = K.relabelled(kernel, K.joined(kernel[0], kernel[1][same], kernel[2][same]))
        value = min(best, K.solve_scan(small)[0])
        return pd.DataFrame({"value": [value], "vertices": [small[0]], "edges": [int(np.sum(small[3]))]})

    return real(g, rows.groupBy().applyInPandas(run, "value double, vertices long, edges long"), bound).withColumn("fidelity", F.lit(STAND_IN))


def baseline_flow(g: Graph) -> DataFrame:
    """Deterministic contraction without sampling: scans contract what is
    connected by the least degree, capped flows solve the rest. A stand-in for
    the published flow framework; exact."""
    rows, bound = cut_kernel(g)
    k = int(min(g.profile["min_degree"], bound))

    def run(pdf):
        import pandas as pd

        small, _ = K.shrink(K.from_rows(pdf["cu"], pdf["cv"], pdf["mult"])[0], k)
        if small[0] > DENSE_VERTICES:
            raise ValueError(f"{small[0]} vertices are left, too many for flows in one task")
        value = float(k) if small[0] < 2 else S.solve_capped(S.square(small), k)[0]
        return pd.DataFrame({"value": [value], "vertices": [small[0]]})

    return real(g, rows.groupBy().applyInPandas(run, "value double, vertices long"), bound).withColumn("fidelity", F.lit(STAND_IN))


def baseline_scan(g: Graph, kernel: tuple[DataFrame, float] | None = None) -> DataFrame:
    """The exact solver on the whole graph in one task, nothing sampled: what
    any contraction has to beat once the graph outgrows a task; from there on
    its ``cut_kernel`` is solved, or the one of any ratio that is given."""
    rows, bound = kernel or cut_kernel(g)
    return real(g, solve_kernel(rows, rows, "scan").select("value"), bound).withColumn("fidelity", F.lit(FULL))


def k_sweep(g: Graph, ks: tuple[int, ...] = (1, 2, 3, 4, 6, 8), reps: int = 8, seed: int = 1, side: DataFrame | None = None) -> DataFrame:
    """(k, components, edges, p, survived): per k the averages over repetitions
    of k-out contraction and, for the cut around ``side`` (v, in_s), the exact
    chance that it survives and how many repetitions kept it."""
    from edgeconn.operators.measures import survival_probability, survival_rate

    out = None
    for k in ks:
        labels = stage(k_out_labels(g, k, reps, seed), "sweep").df
        row = labels.agg((F.countDistinct("rep", "comp") / reps).alias("components"))
        row = row.crossJoin(kernel_edges(g, labels).agg((F.count(F.lit(1)) / reps).alias("edges")))  # a row each
        if side is not None:
            row = row.crossJoin(survival_probability(g, side, k)).crossJoin(survival_rate(labels, side).select("survived"))  # a row each
        row = row.select(F.lit(k).alias("k"), "*")
        out = row if out is None else out.unionByName(row)
    return out
