"""Graphs in several parts are told before the repetitions are drawn."""

import pytest

from edgeconn.operators import mincut as M
from edgeconn.operators.graph import Graph, canonical_edges


@pytest.mark.parametrize("how", [{}, {"edge_step": "certificate"}, {"mode": "best_of"}])
def test_parts_are_told_by_one_repetition(spark, monkeypatch, how):
    def never(*args, **kwargs):
        raise AssertionError("all repetitions were drawn")

    monkeypatch.setattr(M, "contract_once", never)
    pairs = [(10 * p + i, 10 * p + j) for p in range(3) for i in range(4 + p) for j in range(i)]
    got = M.edge_connectivity(Graph.of(canonical_edges(spark.createDataFrame(pairs, "a long, b long"))), **how)
    assert (got.lambda_value, got.kind, got.side_size) == (0, "disconnected", 4)
    assert sorted(r.v for r in got.side.filter("in_s").collect()) == [0, 1, 2, 3]
