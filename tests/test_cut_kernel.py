"""Baselines on graphs that are more than a task may hold."""

import itertools

import pytest

from edgeconn.operators import baselines as B
from edgeconn.operators import certificate as C
from edgeconn.operators.graph import Graph, canonical_edges
from edgeconn.sources import workloads as W


def rows_of(spark):
    """Four cliques of 40 on a ring with three bridges a gap: least cut 6."""
    pairs = [(40 * c + i, 40 * c + j) for c in range(4) for i, j in itertools.combinations(range(40), 2)]
    pairs += [(40 * c + r, 40 * ((c + 1) % 4) + r + 3) for c in range(4) for r in range(3)]
    return Graph.of(canonical_edges(spark.createDataFrame(pairs, "a long, b long")))


@pytest.mark.parametrize("f", [B.baseline_scan, lambda g: B.baseline_uniform(g, 16), B.baseline_tree_packing, B.baseline_diffusion, B.baseline_flow, B.baseline_skeleton])
def test_beyond_a_task(spark, monkeypatch, f):
    monkeypatch.setattr(B, "KERNEL_ROWS", 2500)
    monkeypatch.setattr(B, "DENSE_VERTICES", 100)
    monkeypatch.setattr(C, "PART_ROWS", 500)
    assert f(rows_of(spark)).first().value == 6


def test_cells_make_the_same_pairs(spark, small, monkeypatch):
    want = sorted(map(tuple, W.graph(spark, small, "nation_ring", t=3).edges.collect()))
    monkeypatch.setattr(W, "CELL", 3)
    assert sorted(map(tuple, W.graph(spark, small, "nation_ring", t=3).edges.collect())) == want


@pytest.mark.parametrize("key", ["cactus_ring_nodes", "cactus_ring_cuts", "cactus_chain_edges", "cut_edges_chain", "ring_small_cuts"])
def test_cactus_beyond_a_task_draws_nothing(spark, monkeypatch, key):
    """The contraction of a graph over a task is exact and reads its edges
    without draws, of which there are many to each edge."""
    import duckdb

    import edgeconn.queries as Q
    from tests.test_queries import TABLES, plain

    d = "/root/testdata/sf0.01"
    monkeypatch.setattr(B, "KERNEL_ROWS", 40_000)
    monkeypatch.setattr(C, "PART_ROWS", 5000)
    monkeypatch.setattr(Q, "contract_once", None)
    db = duckdb.connect()
    for t in TABLES:
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    got = Q.queries()[key](spark, d)
    want = db.sql(Q.oracle_sql()[key])
    assert sorted(tuple(plain(r[c]) for c in want.columns) for r in got.collect()) == sorted(tuple(plain(v) for v in r) for r in want.fetchall())


def test_contracted_keeps_the_cut(spark, monkeypatch):
    g = rows_of(spark)
    labels, kernel = B.contracted(g)
    assert sorted((r.v, r.comp) for r in labels.collect()) == [(v, v // 40 * 40) for v in range(160)]
    assert sorted(map(tuple, kernel.collect())) == [(0, 40, 3), (0, 120, 3), (40, 80, 3), (80, 120, 3)]
    monkeypatch.setattr(B, "KERNEL_ROWS", 500)
    assert B.contracted(g) is None


def test_estimate_reads_the_edges_once(spark, monkeypatch):
    import edgeconn.queries as Q

    levels = []
    monkeypatch.setattr(B, "KERNEL_ROWS", 40_000)
    monkeypatch.setattr(B, "certificate", lambda kernel, k, how: levels.append(k) or C.certificate(kernel, k, how))
    assert Q.queries()["baseline_estimate"](spark, "/root/testdata/sf0.01").first().within
    assert levels == [20]
