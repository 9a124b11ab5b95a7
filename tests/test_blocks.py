"""Dense graphs as blocks, whose edges are made where they are read."""

import itertools

import numpy as np
import pytest

import edgeconn.queries as Q
from edgeconn.operators import baselines as B
from edgeconn.operators import blocks as X
from edgeconn.operators import sparse as K
from edgeconn.sources import workloads as W


def in_blocks(spark, monkeypatch):
    """Nations of 60 customers in cells, and edges over a task, which no step
    may write or certify as rows."""
    monkeypatch.setattr(W, "CELL", 17)
    monkeypatch.setattr(B, "KERNEL_ROWS", 40_000)
    monkeypatch.setattr(B, "certificate", None)
    monkeypatch.setattr(X, "edges_of", lambda blocks: blocks.sparkSession.createDataFrame([], "src long, dst long"))


def same_as_sql(spark, key):
    import duckdb

    from tests.test_queries import TABLES, plain

    d = "/root/testdata/sf0.01"
    db = duckdb.connect()
    for t in TABLES:
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    got = Q.queries()[key](spark, d)
    want = db.sql(Q.oracle_sql()[key])
    assert sorted(tuple(plain(r[c]) for c in want.columns) for r in got.collect()) == sorted(tuple(plain(v) for v in r) for r in want.fetchall())


@pytest.mark.parametrize("name, params", [("nation_cliques", {}), ("nation_ring", {"t": 3}), ("nation_chain", {"t": 1}), ("nation_ring_uneven", {"t": 2})])
def test_blocks_are_the_same_graph(spark, small, monkeypatch, name, params):
    want = W.graph(spark, small, name, **params)
    monkeypatch.setattr(W, "CELL", 4)
    monkeypatch.setattr(X, "CHUNK", 5)
    got = W.block_graph(spark, small, name, **params)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(got.edges) == rows(want.edges)
    assert rows(got.degrees) == rows(want.degrees)
    assert rows(got.vertices) == rows(want.vertices)
    assert got.profile == want.profile


@pytest.mark.parametrize("shift", [0, 1 << 40, -(1 << 40)])
def test_ties_keep_all_cuts_under_the_level(shift):
    rng = np.random.default_rng(3)
    for _ in range(60):
        n, k = int(rng.integers(3, 9)), int(rng.integers(1, 5))
        pairs = np.array([p for p in itertools.combinations(range(n), 2) if rng.random() < 0.7]).reshape(-1, 2) + shift
        sieve, kept = X.Sieve(k), []
        for part in np.array_split(pairs, 4):
            if len(part):
                kept += part[sieve.kept(part[:, 0], part[:, 1])].tolist()
        v, head = sieve.ties()
        top = dict(zip((v - shift).tolist(), (head - shift).tolist(), strict=True))
        for side in range(1, 1 << n - 1):
            cut = sum((side >> a - shift & 1) != (side >> b - shift & 1) for a, b in pairs.tolist())
            left = sum((side >> a - shift & 1) != (side >> b - shift & 1) for a, b in kept)
            assert left == cut if cut < k else left >= k
            if cut < k:
                assert all((side >> a & 1) == (side >> b & 1) for a, b in top.items())


def test_table_drops_what_forests_drop():
    rng = np.random.default_rng(5)
    with_table, plain = X.Sieve(3), K.tied
    a, b = rng.integers(0, 40, 3000), rng.integers(0, 40, 3000)
    a, b = np.minimum(a, b)[a != b], np.maximum(a, b)[a != b]
    sizes = [len(with_table.kept(x, y)) for x, y in zip(np.array_split(a, 30), np.array_split(b, 30), strict=True)]
    assert sum(sizes) == 3 * 39 and len(with_table.ties()[0]) == 39 == len(set(plain(40, a, b, 3))) + 38


KEYS = ["baseline_scan", "baseline_uniform", "baseline_flow", "baseline_tree_packing", "baseline_estimate", "baseline_recursive", "baseline_filtering", "cactus_ring_nodes", "baseline_small_cut", "cactus_chain_edges", "baseline_parallel_tree_packing", "baseline_diffusion"]


@pytest.mark.parametrize("key", KEYS)
def test_queries_on_blocks(spark, monkeypatch, key):
    in_blocks(spark, monkeypatch)
    same_as_sql(spark, key)
