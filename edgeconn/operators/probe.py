"""Edge queries by randomly probed forests, and votes over many of them.

A structure is a 2-out sample, whose components are the forests' vertices, and
4 * min degree forests. An edge draws one forest and is kept where it joins two
of that forest's trees. Forests never look at each other, so each is grown on
its own group of edges, in edge order, with the answers of one long scan.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators import components as C
from edgeconn.operators.certificate import Forest
from edgeconn.operators.components import components
from edgeconn.operators.contract import k_out_labels, kernel_edges
from edgeconn.operators.graph import Graph
from edgeconn.operators.sample import forest_of
from edgeconn.plans.staging import stage


def _grow(pdf):
    pdf = pdf.sort_values("eid")
    forest = Forest()
    kept = [forest.union(a, b) for a, b in zip(pdf["cu"], pdf["cv"], strict=True)]
    return pdf[kept][["rep", "cell", "eid", "cu", "cv"]]


def guarded(labels: DataFrame, n: int, delta: int, guard_c: float | None) -> DataFrame:
    """Labels of the repetitions with at most guard_c * n / delta components;
    a structure over more of them answers contract to every edge."""
    if guard_c is None:
        return labels
    few = labels.groupBy("rep").agg(F.countDistinct("comp").alias("c")).filter(F.col("c") <= guard_c * n / max(1, delta))
    return labels.join(F.broadcast(few.select("rep")), "rep", "left_semi")  # a row per repetition


def forest_probe(g: Graph, reps: int = 1, seed: int = 1, ell: int | None = None, guard_c: float | None = None, labels: DataFrame | None = None, strategy: str = "auto", hashing: str = "md5") -> DataFrame:
    """(rep, cell, eid, cu, cv): the edges that a structure answers preserve to.

    Edges inside a component are contracted without a probe. Each forest keeps
    at most its vertices less one, whatever the number of edges.
    """
    p = g.profile
    ell = ell or max(1, 4 * p["min_degree"])
    labels = guarded(labels if labels is not None else k_out_labels(g, 2, reps, seed, strategy=strategy, hashing=hashing), p["n"], p["min_degree"], guard_c)
    drawn = kernel_edges(g, labels).withColumn("cell", forest_of(["eid"], ell, seed, hashing))
    return drawn.groupBy("rep", "cell").applyInPandas(_grow, "rep int, cell int, eid long, cu long, cv long")


def probe_votes(kept: DataFrame) -> DataFrame:
    """(eid, n_preserved): how many structures keep an edge."""
    return kept.groupBy("eid").agg(F.count(F.lit(1)).cast("int").alias("n_preserved"))


@dataclass(frozen=True)
class Probed:
    labels: DataFrame  # v, comp
    kernel: DataFrame  # eid, cu, cv
    queried: int
    kept: int


def probe_contract(g: Graph, reps: int, threshold: int, seed: int = 1, skip: str = "chunked", ell: int | None = None, guard_c: float | None = None, strategy: str = "auto", hashing: str = "md5") -> Probed:
    """Contract every edge with fewer than ``threshold`` preserves.

    skip ``none`` asks all structures about all edges. ``chunked`` feeds the
    edges in chunks of 1/64, 1/32, ... of them: edges whose ends are joined by
    then are not asked about, and forests go on from what they kept.
    ``adaptive`` goes edge by edge in one task, for graphs that fit it
    (``components.TASK_ROWS`` edges; more are refused).
    """
    labels = stage(k_out_labels(g, 2, reps, seed, strategy=strategy, hashing=hashing), "probe-labels").df
    if skip == "adaptive":
        if g.profile["m"] > C.TASK_ROWS:
            raise ValueError(f"{g.profile['m']} edges are too many to go through in one task; take chunks")
        return _adaptive(g, labels, reps, threshold, seed, ell or max(1, 4 * g.profile["min_degree"]))
    chunk_of = F.pmod(F.xxhash64(F.lit(seed), "eid"), F.lit(64))
    cuts = [(0, 64)] if skip == "none" else [(0, 1), (1, 2), (2, 4), (4, 8), (8, 16), (16, 32), (32, 64)]
    ell = ell or max(1, 4 * g.profile["min_degree"])
    base = guarded(labels, g.profile["n"], g.profile["min_degree"], guard_c)
    top = g.vertices.select("v", F.col("v").alias("comp"))
    held, votes, queried = None, None, 0
    for lo, hi in cuts:
        a, b = top.withColumnsRenamed({"v": "src", "comp": "ca"}), top.withColumnsRenamed({"v": "dst", "comp": "cb"})
        fresh = g.edges.filter((chunk_of >= lo) & (chunk_of < hi)).join(a, "src").join(b, "dst").filter("ca <> cb")
        asked = stage(fresh, "probe-chunk").df
        queried += asked.count()
        drawn = kernel_edges(Graph(g.vertices, asked.select("eid", "src", "dst")), base).withColumn("cell", forest_of(["eid"], ell, seed)).withColumn("old", F.lit(False))
        if held is not None:
            drawn = drawn.unionByName(held.withColumn("old", F.lit(True)))
        grown = drawn.groupBy("rep", "cell").applyInPandas(_regrow, "rep int, cell int, eid long, cu long, cv long, old boolean")
        grown = stage(grown, "probe-forest").df
        held = grown.drop("old")
        new = asked.select("eid", "ca", "cb").join(probe_votes(grown.filter("not old")), "eid", "left").select("eid", "ca", "cb", F.coalesce("n_preserved", F.lit(0)).alias("n_preserved"))
        new = stage(new, "probe-votes").df
        votes = new if votes is None else votes.unionByName(new)
        low = new.filter(F.col("n_preserved") < threshold).select(F.lit(0).alias("rep"), F.col("ca").alias("src"), F.col("cb").alias("dst"))
        joined = components(low, strategy=strategy).select(F.col("v").alias("comp"), F.col("comp").alias("up"))
        top = stage(top.join(joined, "comp", "left").select("v", F.coalesce("up", "comp").alias("comp")), "probe-top").df
    a, b = top.withColumnsRenamed({"v": "src", "comp": "ca"}), top.withColumnsRenamed({"v": "dst", "comp": "cb"})
    left = g.edges.join(a, "src").join(b, "dst").filter("ca <> cb")
    kernel = left.select("eid", F.least("ca", "cb").alias("cu"), F.greatest("ca", "cb").alias("cv"))
    return Probed(top, kernel, queried, votes.filter(F.col("n_preserved") >= threshold).count())


def _regrow(pdf):
    """Forest edges of earlier chunks first, then the new ones in edge order."""
    pdf = pdf.sort_values(["old", "eid"], ascending=[False, True])
    forest = Forest()
    kept = [forest.union(a, b) for a, b in zip(pdf["cu"], pdf["cv"], strict=True)]
    return pdf[kept][["rep", "cell", "eid", "cu", "cv", "old"]]


def _adaptive(g: Graph, labels: DataFrame, reps: int, threshold: int, seed: int, ell: int) -> Probed:
    drawn = kernel_edges(g, labels).withColumn("cell", forest_of(["eid"], ell, seed))
    per_edge = drawn.groupBy("eid").agg(F.collect_list(F.struct("rep", "cell", "cu", "cv")).alias("asks"))  # reps entries at most
    rows = g.edges.join(per_edge, "eid", "left").select(F.lit(0).alias("one"), "eid", "src", "dst", "asks")

    def run(pdf):
        import pandas as pd

        top, forests, out = Forest(), {}, []
        for e in pdf.sort_values("eid").itertuples():
            top.find(e.src), top.find(e.dst)
            if top.joined(e.src, e.dst):
                continue
            votes = 0
            for ask in e.asks if e.asks is not None else []:
                votes += forests.setdefault((ask["rep"], ask["cell"]), Forest()).union(ask["cu"], ask["cv"])
            if votes < threshold:
                top.union(e.src, e.dst)
            out.append((e.eid, None, None, votes))
        return pd.DataFrame(out + [(None, v, top.find(v), None) for v in list(top.up)], columns=["eid", "v", "comp", "votes"]).astype("Int64")

    got = stage(rows.groupBy("one").applyInPandas(run, "eid long, v long, comp long, votes long"), "probe-adaptive").df
    top = g.vertices.join(got.filter("v IS NOT NULL").select("v", "comp"), "v", "left").select("v", F.coalesce("comp", "v").alias("comp"))
    a, b = top.withColumnsRenamed({"v": "src", "comp": "ca"}), top.withColumnsRenamed({"v": "dst", "comp": "cb"})
    kernel = g.edges.join(a, "src").join(b, "dst").filter("ca <> cb").select("eid", F.least("ca", "cb").alias("cu"), F.greatest("ca", "cb").alias("cv"))
    asked = got.filter("eid IS NOT NULL")
    return Probed(top, kernel, asked.count(), asked.filter(F.col("votes") >= threshold).count())
