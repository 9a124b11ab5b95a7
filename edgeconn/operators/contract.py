"""Contractions, the fingerprint filter, edge votes and the kernel."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.operators.certificate import certificate
from edgeconn.operators.components import components, with_singletons
from edgeconn.operators.graph import Graph
from edgeconn.operators.sample import edge_sample, k_out_draws
from edgeconn.plans.staging import stage


def _ends(draws: DataFrame) -> DataFrame:
    return draws.select("rep", F.col("v").alias("src"), F.col("nbr").alias("dst"))


def k_out_labels(g: Graph, k: int = 2, reps: int = 1, seed: int = 1, strategy: str = "auto", **how) -> DataFrame:
    """(rep, v, comp): contraction of the components of a k-out sample."""
    return with_singletons(components(_ends(k_out_draws(g, k, reps, seed, **how)), strategy=strategy), g.vertices, reps)


def fused_labels(g: Graph, k: int = 2, reps: int = 1, seed: int = 1, p: float | None = None, strategy: str = "auto", hashing: str = "md5", draw: str = "minhash") -> DataFrame:
    """(rep, v, comp) of the k-out sample together with a uniform edge sample,
    in one components run. Sampled edges come from all edges of the graph."""
    pairs = _ends(k_out_draws(g, k, reps, seed, draw=draw, hashing=hashing)).unionByName(edge_sample(g, p, reps, seed, hashing).select("rep", "src", "dst"))
    return with_singletons(components(pairs, strategy=strategy), g.vertices, reps)


def sample_labels(g: Graph, reps: int = 1, seed: int = 1, p: float | None = None, strategy: str = "auto", hashing: str = "md5") -> DataFrame:
    """The uniform edge sample alone, without k-out (a baseline)."""
    return with_singletons(components(edge_sample(g, p, reps, seed, hashing).select("rep", "src", "dst"), strategy=strategy), g.vertices, reps)


def kernel_edges(g: Graph, labels: DataFrame) -> DataFrame:
    """(rep, eid, cu, cv): edges between different components, with cu < cv.
    Edges keep their ids, so parallel ones stay apart. ``labels`` holds each
    vertex in each of its repetitions; edges are read once for all of them."""
    wide = stage(widen(labels), "wide").df
    reps = [r.rep for r in labels.select("rep").distinct().orderBy("rep").collect()]  # a row per repetition
    found = inter_component_edges(g.edges, wide)
    ids = F.array(*(F.lit(r) for r in reps)) if reps else F.array().cast("array<int>")
    each = F.arrays_zip(ids.alias("rep"), F.col("cu").alias("ca"), F.col("cv").alias("cb"))
    rows = found.select("eid", F.explode(each).alias("x")).select("x.rep", "eid", "x.ca", "x.cb")
    return rows.filter("ca <> cb").select("rep", "eid", F.least("ca", "cb").alias("cu"), F.greatest("ca", "cb").alias("cv"))


def collapse(kernel: DataFrame, *by: str) -> DataFrame:
    """(*by, cu, cv, mult): parallel edges as one row; keeps every cut's size."""
    return kernel.groupBy(*by, "cu", "cv").agg(F.count(F.lit(1)).alias("mult"))


def certificate_contract(kernel: DataFrame, k: int, strategy: str = "merge", components_by: str = "auto") -> DataFrame:
    """(rep, v, comp) over kernel vertices: every edge outside a certificate of
    level k is contracted, which only loses cuts of more than k edges."""
    kernel = stage(kernel, "certify").df
    inside = certificate(kernel, k, strategy)
    outside = kernel.join(inside, ["rep", "eid", "cu", "cv"], "left_anti")
    return components(outside, src="cu", dst="cv", strategy=components_by)


def contract_once(g: Graph, reps: int = 1, seed: int = 1, vertex_step: str = "k_out", edge_step: str = "uniform", k: int = 2, level: int | None = None, strategy: str = "auto", hashing: str = "md5", draw: str = "minhash") -> DataFrame:
    """(rep, v, comp) of one full contraction per repetition.

    edge_step ``uniform``: the fused sample; ``certificate``: k-out, then the
    contraction outside a certificate of twice the minimum degree; ``none``.
    vertex_step ``none`` leaves the uniform sample alone.
    """
    if vertex_step == "none":
        return sample_labels(g, reps, seed, strategy=strategy, hashing=hashing)
    if edge_step == "uniform":
        return fused_labels(g, k, reps, seed, strategy=strategy, hashing=hashing, draw=draw)
    first = k_out_labels(g, k, reps, seed, strategy=strategy, hashing=hashing, draw=draw)
    if edge_step == "none":
        return first
    first = stage(first, "first-labels").df
    again = certificate_contract(kernel_edges(g, first), level or 2 * g.profile["min_degree"], components_by=strategy).select("rep", F.col("v").alias("comp"), F.col("comp").alias("top"))
    return first.join(again, ["rep", "comp"], "left").select("rep", "v", F.coalesce("top", "comp").alias("comp"))


def widen(labels: DataFrame) -> DataFrame:
    """(v, comps array<long> by rep, fp struct of two longs): all labels of a
    vertex, as many as repetitions, and a fingerprint of 128 bits, so that no
    collision hides an edge at any number of vertices that can be had."""
    wide = labels.groupBy("v").agg(F.sort_array(F.collect_list(F.struct("rep", "comp"))).alias("x"))
    return wide.select("v", F.col("x.comp").alias("comps"), F.struct(F.xxhash64(F.col("x.comp")).alias("a"), F.xxhash64(F.lit(1), F.col("x.comp")).alias("b")).alias("fp"))


def inter_component_edges(edges: DataFrame, wide: DataFrame, mode: str = "fingerprint") -> DataFrame:
    """(eid, src, dst, cu, cv): edges whose ends differ in some repetition,
    with both label arrays.

    ``fingerprint`` compares 16-byte fingerprints on all edges and fetches the
    arrays for survivors alone; ``naive`` fetches them for every edge.
    """
    a = wide.select(F.col("v").alias("src"), F.col("comps").alias("cu"))
    b = wide.select(F.col("v").alias("dst"), F.col("comps").alias("cv"))
    if mode == "fingerprint":
        fa = wide.select(F.col("v").alias("src"), F.col("fp").alias("fa"))
        fb = wide.select(F.col("v").alias("dst"), F.col("fp").alias("fb"))
        edges = edges.join(fa, "src").join(fb, "dst").filter("fa <> fb").select("eid", "src", "dst")
    return edges.join(a, "src").join(b, "dst").filter(F.col("cu") != F.col("cv")).select("eid", "src", "dst", "cu", "cv")


def edge_votes(survivors: DataFrame) -> DataFrame:
    """(eid, src, dst, n_preserved): repetitions in which an edge survived."""
    n = F.aggregate(F.zip_with("cu", "cv", lambda x, y: (x != y).cast("int")), F.lit(0), lambda s, x: s + x)
    return survivors.select("eid", "src", "dst", n.alias("n_preserved"))


def vote_histogram(votes: DataFrame) -> DataFrame:
    return votes.groupBy("n_preserved").agg(F.count(F.lit(1)).alias("n_edges"))


def adaptive_threshold(votes: DataFrame, n: int, c: float = 4.0) -> int:
    """The least r of 1.. at which at most c * n edges have r votes or more.
    A lower r never loses a cut that a higher one keeps."""
    rows = sorted((r.n_preserved, r.n_edges) for r in vote_histogram(votes).collect())  # a row per count of votes
    left = sum(k for _, k in rows)
    for v, k in rows:
        if left <= c * n:
            return max(1, v)
        left -= k
    return max(1, rows[-1][0] + 1) if rows else 1


@dataclass(frozen=True)
class Votes:
    labels: DataFrame  # v, comp of the voted graph
    kernel: DataFrame  # eid, cu, cv
    threshold: int


def merge_low_votes(g: Graph, wide: DataFrame, votes: DataFrame, r: int, strategy: str = "auto") -> Votes:
    """Contract the edges with fewer than r votes.

    Vertices with equal labels in all repetitions are merged by a grouping
    first: no cut that survived anywhere separates them. Only survivors with
    few votes then need a components run.
    """
    group = wide.select("v", "comps").join(wide.groupBy("comps").agg(F.min("v").alias("s")), "comps").select("v", "s")
    a, b = group.select(F.col("v").alias("src"), F.col("s").alias("sa")), group.select(F.col("v").alias("dst"), F.col("s").alias("sb"))
    raised = votes.join(a, "src").join(b, "dst").select("eid", "n_preserved", "sa", "sb")
    low = raised.filter(F.col("n_preserved") < r).select(F.lit(0).alias("rep"), F.col("sa").alias("src"), F.col("sb").alias("dst"))
    top = components(low, strategy=strategy).select(F.col("v").alias("s"), F.col("comp").alias("top"))
    labels = group.join(top, "s", "left").select("v", F.coalesce("top", "s").alias("comp"))
    ends = raised.join(top.withColumnsRenamed({"s": "sa", "top": "ta"}), "sa", "left").join(top.withColumnsRenamed({"s": "sb", "top": "tb"}), "sb", "left")
    ca, cb = F.coalesce("ta", "sa"), F.coalesce("tb", "sb")
    kernel = ends.filter(ca != cb).select("eid", F.least(ca, cb).alias("cu"), F.greatest(ca, cb).alias("cv"))
    return Votes(labels, kernel, r)
