"""Draws and samples by md5 on arrays, and what large graphs make of them."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeconn.functions.md5 import Numbers
from edgeconn.operators import baselines as B
from edgeconn.operators import mincut as M
from edgeconn.operators import sample
from edgeconn.operators.contract import kernel_edges, sample_labels
from edgeconn.operators.graph import Graph, canonical_edges
from edgeconn.plans.staging import stage


def plain(text: str) -> str:
    return hashlib.md5(text.encode()).hexdigest()


@pytest.mark.parametrize("prefix", ["", "1", "abc", "1:0:e", "1:15:e", "x" * 40])
def test_first_digits_are_those_of_md5(prefix):
    tens = 10 ** np.arange(19, dtype=np.int64)
    x = np.r_[tens, tens - 1, -tens, 2**63 - 1, np.arange(70_000)]
    y = x[::-1].copy()
    at = np.r_[:200, len(x) - 200 : len(x)]
    want = [int(plain(f"{prefix}:{x[i]}:{y[i]}")[:8], 16) for i in at]
    assert Numbers(x, y).first(prefix)[at].tolist() == want


@pytest.fixture(scope="module")
def dense(spark):
    """Two cliques of 60 vertices, also below zero and from 2^31 on, with two links."""
    c = spark.range(60).select(F.col("id").alias("a")).crossJoin(spark.range(60).select(F.col("id").alias("b"))).filter("a < b")
    far = c.select(F.when(F.col("a") < 5, -1 - F.col("a")).otherwise(F.col("a") + (1 << 31)).alias("a"), (F.col("b") + (1 << 31)).alias("b")).filter("b >= 2147483653")
    links = spark.createDataFrame([(3, (1 << 31) + 9), (4, (1 << 31) + 10)], "a long, b long")
    return Graph.of(stage(canonical_edges(c.unionByName(far).unionByName(links)).repartition(5), "t").df)


def test_draws_on_arrays_equal_plain_ones_whatever_a_task_holds(spark, dense, monkeypatch):
    plan = sample.k_out_draws(dense, 2, 2)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Generate" not in plan  # edges are not multiplied by tries
    ends = {}
    for e in dense.edges.collect():
        ends.setdefault(e.src, []).append(e.dst)
        ends.setdefault(e.dst, []).append(e.src)
    want = {(r, j, v, min(n, key=lambda x: plain(f"1:{r}:{j}:{v}:{x}"))) for v, n in ends.items() for r in range(2) for j in range(2)}
    for chunk, held in ((1 << 18, 1 << 21), (100, 50), (7, 1)):
        monkeypatch.setattr(sample, "CHUNK", chunk)
        monkeypatch.setattr(sample, "HELD", held)
        assert {(d.rep, d.j, d.v, d.nbr) for d in sample.k_out_draws(dense, 2, 2).collect()} == want


def test_samples_on_arrays_equal_plain_ones(dense):
    want = {(r, e.eid, e.src, e.dst) for e in dense.edges.collect() for r in range(3) if plain(f"1:{r}:e:{e.src}:{e.dst}")[:8] < "20000000"}
    assert set(map(tuple, sample.edge_sample(dense, 0.125, 3).collect())) == want
    assert sample.edge_sample(dense, 1.0, 2).count() == 2 * dense.edges.count()


def test_kernels_of_all_repetitions_read_the_edges_once(dense):
    labels = stage(sample_labels(dense, 3, 1, 0.05), "t").df
    comp = {(x.rep, x.v): x.comp for x in labels.collect()}
    want = sorted((r, e.eid, *sorted((comp[r, e.src], comp[r, e.dst]))) for e in dense.edges.collect() for r in range(3) if comp[r, e.src] != comp[r, e.dst])
    assert sorted(map(tuple, kernel_edges(dense, labels).collect())) == want
    assert {x.rep for x in kernel_edges(dense, labels.filter("rep = 2")).collect()} == {2}


def test_uniform_sample_solves_graphs_over_a_task(dense, monkeypatch):
    want = sorted(map(tuple, B.baseline_uniform_sample(dense, 4).collect()))
    for m in (B, M):
        monkeypatch.setattr(m, "KERNEL_ROWS", 2000)
    assert dense.profile["m"] > 2000 and [x[2] for x in want] == [2.0] * 4
    assert sorted(map(tuple, B.baseline_uniform_sample(dense, 4).collect())) == want
