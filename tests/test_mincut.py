import random

import pytest

from edgeconn.operators import measures as M
from edgeconn.operators.contract import edge_votes, fused_labels, inter_component_edges, k_out_labels, kernel_edges, widen
from edgeconn.operators.graph import Graph, canonical_edges, cut_edges, encode_vertices
from edgeconn.operators.mincut import edge_connectivity
from edgeconn.operators.probe import forest_probe
from edgeconn.operators.sample import k_out_draws
from edgeconn.plans.planning import congest_plan, plan_repetitions
from edgeconn.plans.staging import stage
from edgeconn.sources.workloads import graph


def of(spark, pairs, vertices=None):
    g = canonical_edges(spark.createDataFrame(pairs, "a long, b long"))
    v = spark.createDataFrame([(x,) for x in vertices], "v long") if vertices is not None else None
    return Graph.of(g, v)


def two_cliques(n, t):
    pairs = [(i, j) for b in (0, n) for i in range(b, b + n) for j in range(i + 1, b + n)]
    return pairs + [(i, n + i) for i in range(t)]


@pytest.mark.parametrize("t,kind", [(2, "nontrivial"), (9, "trivial")])
def test_two_cliques(spark, t, kind):
    g = of(spark, two_cliques(10, t))
    got = edge_connectivity(g)
    assert (got.lambda_value, got.kind) == (min(t, 9), kind)
    assert cut_edges(g, got.side).count() == got.lambda_value


@pytest.mark.parametrize(
    "pairs,vertices,value,kind",
    [
        ([], [], 0, "trivial"),
        ([], [3], 0, "trivial"),
        ([], [3, 4], 0, "disconnected"),
        ([(1, 2), (2, 1), (1, 1)], None, 1, "trivial"),
        ([(1, 2), (2, 3)], [1, 2, 3, 9], 0, "disconnected"),
        ([(1, 2), (3, 4)], None, 0, "disconnected"),
        ([(-5, 2), (2, 7), (7, -5)], None, 2, "trivial"),
        ([(i, i + 1) for i in range(6)], None, 1, "trivial"),
    ],
)
def test_small_graphs(spark, pairs, vertices, value, kind):
    got = edge_connectivity(of(spark, pairs, vertices))
    assert (got.lambda_value, got.kind) == (value, kind)


def test_planted_chain_and_invariants(spark, small):
    g = graph(spark, small, "nation_chain", t=1)
    g = Graph.of(stage(g.edges, "t").df)
    got = edge_connectivity(g, q=24)
    assert got.lambda_value == 1 and got.kind == "nontrivial"
    assert cut_edges(g, got.side).count() == 1
    assert edge_connectivity(g, q=2, seed=9).lambda_value >= 1  # a real cut, whatever the luck


def test_kernel_keeps_cut_sizes(spark, small):
    g = Graph.of(stage(graph(spark, small, "nation_ring", t=3).edges, "t").df)
    labels = stage(k_out_labels(g, 2, 1), "l").df
    comp = {r.v: r.comp for r in labels.collect()}
    want = sum(comp[e.src] != comp[e.dst] for e in g.edges.collect())
    assert kernel_edges(g, labels).count() == want


def test_draws_are_uniform_and_repeatable(spark):
    g = of(spark, [(0, i) for i in range(1, 5)])
    first = k_out_draws(g, 2, 400).filter("v = 0")
    n = first.groupBy("nbr").count().collect()
    assert sum(r["count"] for r in n) == 800 and all(120 < r["count"] < 280 for r in n)
    assert first.exceptAll(k_out_draws(g, 2, 400).filter("v = 0").repartition(5)).isEmpty()
    for how in ({"draw": "rank"}, {"hashing": "xxhash64"}, {"draw": "rank", "hashing": "xxhash64"}):
        rows = k_out_draws(g, 2, 400, **how)
        assert rows.count() == 400 * 2 * 5
        n = rows.filter("v = 0").groupBy("nbr").count().collect()
        assert all(120 < r["count"] < 280 for r in n)


def test_survivors_agree_and_survival_is_as_computed(spark, small):
    g = Graph.of(stage(graph(spark, small, "nation_chain", t=1).edges, "t").df)
    wide = stage(widen(fused_labels(g, 2, 8)), "w").df
    a = inter_component_edges(g.edges, wide)
    assert sorted(r.eid for r in a.collect()) == sorted(r.eid for r in inter_component_edges(g.edges, wide, "naive").collect())
    assert edge_votes(a).filter("n_preserved < 1 OR n_preserved > 8").isEmpty()
    two = of(spark, two_cliques(12, 2))
    side = two.vertices.selectExpr("v", "v < 12 AS in_s")
    p = M.survival_probability(two, side).first().p
    row = M.survival_rate(k_out_labels(two, 2, 300), side).first()
    assert abs(row.survived / row.reps - p) < 4 * (p * (1 - p) / 300) ** 0.5


def test_probed_forests_do_not_depend_on_partitions(spark, small):
    g = Graph.of(stage(graph(spark, small, "nation_ring", t=3).edges, "t").df)
    again = Graph.of(g.edges.repartition(7, "dst"))
    key = lambda x: sorted((r.rep, r.cell, r.eid) for r in x.collect())
    assert key(forest_probe(g, 3)) == key(forest_probe(again, 3))


def test_text_ids(spark):
    raw = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a"), ("a", None)], "a string, b string")
    pairs, names = encode_vertices(raw)
    assert sorted((r.v, r.name) for r in names.collect()) == [(0, "a"), (1, "b"), (2, "c")]
    assert edge_connectivity(Graph.of(canonical_edges(pairs))).lambda_value == 2


def test_plans():
    p = plan_repetitions(2100, p=0.25)
    assert p.q == 245 and p.threshold == 30
    assert plan_repetitions(2100).q > 100_000 and not plan_repetitions(2100).assumed
    assert congest_plan(10_000, 10, 100)[0] == "large_cut" and congest_plan(10_000, 10, 1)[0] == "small_cut"


def test_insertions_follow_batch_answers(spark):
    from edgeconn.streaming.incremental import IncrementalConnectivity

    rng = random.Random(4)
    pairs = two_cliques(7, 1)
    extra = [(rng.randrange(7), 7 + rng.randrange(7)) for _ in range(10)]
    state, seen = IncrementalConnectivity(spark, vertices=spark.range(14).withColumnRenamed("id", "v")), []
    for i, batch in enumerate([pairs, extra[:3], extra[3:]]):
        seen += batch
        row = state.process(i, spark.createDataFrame(batch, "a long, b long"))
        assert row[3] == edge_connectivity(of(spark, seen), q=24).lambda_value
        assert state.process(i, spark.createDataFrame(batch, "a long, b long")) == row
