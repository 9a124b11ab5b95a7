"""Uniform contraction of graphs over a task: of the graph, not of what an
exact contraction leaves of it."""

import itertools

import pytest

from edgeconn.operators import baselines as B
from edgeconn.operators import uniform as U
from edgeconn.operators.graph import Graph, canonical_edges


def rows_of(spark, pairs):
    return Graph.of(canonical_edges(spark.createDataFrame(pairs, "a long, b long")))


@pytest.mark.parametrize("drawn", [1, 6, 1000])
def test_runs_contract_the_graph_itself(spark, monkeypatch, drawn):
    """A clique of ten with a tail of one edge: a run finds the tail's cut with
    chance 1 or less, and others cut more; a kernel of the exact cut has two
    vertices and leaves one value."""
    monkeypatch.setattr(B, "KERNEL_ROWS", 10)
    monkeypatch.setattr(B, "cut_kernel", None)
    monkeypatch.setattr(U, "DRAWN", drawn)
    pairs = list(itertools.combinations(range(6), 2)) + [(5, 6)]
    g = rows_of(spark, pairs)
    values = [r.value for r in U.uniform_runs(g, 300).collect()]
    assert len(values) == 300 and min(values) == 1
    assert 0.05 < sum(v > 1 for v in values) / 300 < 0.95  # the last edge goes first in some runs
    assert B.baseline_uniform(g, 64).first().value == 1


@pytest.mark.parametrize("drawn", [1, 1000])
def test_parts_are_told(spark, monkeypatch, drawn):
    monkeypatch.setattr(U, "DRAWN", drawn)
    pairs = [(8 * c + i, 8 * c + j) for c in range(3) for i, j in itertools.combinations(range(6), 2)]
    assert {r.value for r in U.uniform_runs(rows_of(spark, pairs), 4).collect()} == {0.0}
