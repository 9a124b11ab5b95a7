"""Paths that large graphs take, forced on small ones; solvers on edge arrays."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeconn.operators import baselines as B
from edgeconn.operators import components as C
from edgeconn.operators import mincut as M
from edgeconn.operators import solve as S
from edgeconn.operators import sparse as K
from edgeconn.operators.cactus import min_cut_cactus
from edgeconn.operators.certificate import certificate
from edgeconn.operators.contract import inter_component_edges, widen
from edgeconn.operators.diameter import low_diameter_cover
from edgeconn.operators.graph import Graph, canonical_edges, check_ids
from edgeconn.operators.sample import k_out_draws
from edgeconn.plans.staging import new_path, stage
from edgeconn.sources.workloads import graph, user_user
from edgeconn.streaming.incremental import IncrementalConnectivity
from tests.test_mincut import of, two_cliques


@pytest.mark.parametrize("seed", range(60))
def test_scan_solver_equals_brute_force(seed):
    rng = np.random.default_rng(seed)
    n, m = rng.integers(2, 10), rng.integers(2, 25)
    u = rng.integers(0, n, m)
    k, _ = K.from_rows(u, (u + rng.integers(1, n, m)) % n, rng.integers(1, 5, m))
    w = S.square(k)
    value, side = K.solve_scan(k)
    true = S.solve_brute(w)[0]
    assert value == true == w[side][:, ~side].sum()
    assert true <= K.estimate(k) <= 2.5 * true
    small, label = K.shrink(k, true + 1)
    assert K.solve_scan(small)[0] == true and len(set(label.tolist())) == small[0]
    for other, side in (K.solve_uniform(k, seed), K.solve_recursive(k, seed)):
        assert other >= true and w[side][:, ~side].sum() == other
    assert K.sweep_cuts(k)[0] >= true


def test_no_components_run_sees_all_edges(spark, small, monkeypatch):
    g = Graph.of(stage(graph(spark, small, "nation_chain", t=1).edges, "t").df)
    seen = []
    real = C.components
    monkeypatch.setattr(M, "components", lambda edges, **how: seen.append(edges.count()) or real(edges, **how))
    assert M.edge_connectivity(g, q=24).lambda_value == 1
    assert seen and max(seen) < g.profile["m"] / 2


def test_star_components_all_the_way(spark, monkeypatch):
    monkeypatch.setattr(C, "TASK_ROWS", 10)
    g = of(spark, two_cliques(10, 2))
    assert M.edge_connectivity(g, q=6).lambda_value == 2
    apart = M.edge_connectivity(of(spark, [(1, 2), (2, 3), (3, 1), (4, 5), (5, 6), (6, 4), (6, 7), (7, 4)]), q=4)
    assert (apart.lambda_value, apart.kind, apart.side_size) == (0, "disconnected", 3)


def test_sampled_components_at_their_own_rate(spark):
    rows = [(0, i, i + 1) for i in range(40)] + [(0, 100, 101), (1, 5, 7)]
    edges = spark.createDataFrame(rows, "rep int, src long, dst long")
    key = lambda x: sorted(tuple(r) for r in x.collect())
    assert key(C.components(edges, strategy="sampled")) == key(C.components(edges, strategy="local"))


def test_lags_reach_over_days(spark):
    folder = new_path(spark, "events")
    rows = [(i, f"2024-01-0{i + 1} 12:00:00", i * 10) for i in range(6)]
    spark.createDataFrame(rows, "event_id long, ts string, user_id long").withColumn("ts", F.col("ts").cast("timestamp_ntz")).write.parquet(f"{folder}/events.parquet")
    got = sorted((r.a, r.b) for r in user_user(spark, folder, 3).collect())
    assert got == sorted((10 * i, 10 * j) for i in range(6) for j in range(6) if 0 < j - i <= 3)


def test_cover_takes_one_special_center_per_component_left(spark):
    g = of(spark, [(10 * c + i, 10 * c + j) for c in range(12) for i in range(4) for j in range(i)])
    draws = stage(k_out_draws(g, 2, 1, 1), "draws").df
    pieces = C.components(draws.select("rep", F.col("v").alias("src"), F.col("nbr").alias("dst"))).select("comp").distinct().count()
    for mode in ("simple", "staged"):
        tree, centers = low_diameter_cover(draws, 10**9, 10**9, 1.0, mode=mode)  # no random center
        assert tree.count() == 48 == tree.select("v").distinct().count()
        assert centers.filter("special").count() == pieces == 12


def test_colliding_edge_ids_are_told(spark):
    good = canonical_edges(spark.createDataFrame([(-1, 2), (1 << 40, 3)], "a long, b long"))
    check_ids(good)
    with pytest.raises(ValueError, match="collide"):
        check_ids(good.withColumn("eid", F.lit(5).cast("long")))


@pytest.mark.parametrize("part_rows", [5, 40, 10**6])
def test_certificates_of_any_number_of_parts_keep_small_cuts(spark, part_rows):
    rng = np.random.default_rng(part_rows)
    n, k = 8, 3
    rows = [(r, 100 * r + i, *map(int, rng.choice(n, 2, replace=False))) for r in range(2) for i in range(70)]
    kernel = spark.createDataFrame(rows, "rep int, eid long, cu long, cv long")
    kept = [tuple(r) for r in certificate(kernel, k, fan_in=2, part_rows=part_rows).collect()]
    assert set(kept) <= set(rows) and len(kept) == len(set(kept))
    for rep in range(2):
        of_rep = lambda some: [(a, b) for r, _, a, b in some if r == rep]  # noqa: B023, E731
        assert len(of_rep(kept)) <= k * (n - 1)
        for bits in range(1, 1 << (n - 1)):
            crosses = lambda some: sum((bits >> a ^ bits >> b) & 1 for a, b in some)  # noqa: B023, E731
            assert crosses(of_rep(kept)) >= min(k, crosses(of_rep(rows)))
    assert certificate(kernel.filter("false"), k).count() == 0


def test_fingerprints_differ_where_labels_do(spark):
    labels = spark.createDataFrame([(r, v, v % (r + 2)) for r in range(3) for v in range(30)], "rep int, v long, comp long")
    wide = widen(labels)
    assert wide.select("fp").distinct().count() == wide.select("comps").distinct().count()
    edges = canonical_edges(spark.createDataFrame([(i, i + 12) for i in range(15)] + [(1, 2)], "a long, b long"))
    assert [(r.src, r.dst) for r in inter_component_edges(edges, wide).collect()] == [(1, 2)]


def test_large_kernels_are_refused_by_square_solvers(spark, monkeypatch):
    monkeypatch.setattr(M, "DENSE_VERTICES", 5)
    rows = spark.createDataFrame([(i, i + 1, 1) for i in range(9)], "cu long, cv long, mult long")
    assert M.solve_kernel(rows, rows).first().value == 1
    with pytest.raises(Exception, match="too many"):
        M.solve_kernel(rows, rows, "tree_packing").collect()
    monkeypatch.setattr(B, "KERNEL_ROWS", 3)
    with pytest.raises(ValueError, match="too many"):
        B.baseline_uniform(of(spark, two_cliques(4, 1)))


def test_cactus_of_a_cycle_and_of_one_vertex(spark):
    g = of(spark, [(i, (i + 1) % 7) for i in range(7)])
    kernel = g.edges.select(F.col("src").alias("cu"), F.col("dst").alias("cv"), F.lit(1).cast("long").alias("mult"))
    nodes, edges = min_cut_cactus(g, g.vertices.select("v", F.col("v").alias("comp")), kernel)
    assert edges.filter("mult = 1").count() == 7 and edges.count() == 7
    clique = of(spark, [(i, j) for i in range(6) for j in range(i)])
    one = clique.vertices.select("v", F.lit(0).cast("long").alias("comp"))
    nodes, edges = min_cut_cactus(clique, one, kernel.filter("false"))
    assert edges.count() == 6 and nodes.filter("size(members) = 1").count() == 6


def test_insertions_go_on_after_a_restart(spark):
    path = new_path(spark, "incremental")
    v = spark.range(14).withColumnRenamed("id", "v")
    batch = lambda pairs: spark.createDataFrame(pairs, "a long, b long")
    one = IncrementalConnectivity(spark, path=path, vertices=v)
    first = one.process(0, batch(two_cliques(7, 1)))
    assert first[3] == 1
    two = IncrementalConnectivity(spark, path=path, vertices=v)
    assert two.process(0, batch([(0, 9)])) == first  # delivered again: nothing changes
    assert two.process(1, batch([(0, 8), (1, 9)]))[3] == 3
    # an insertion chosen from the last reported cut
    assert IncrementalConnectivity(spark, path=path, vertices=v).process(2, batch([(2, 10)]))[3] == 4


def test_many_draws_move_each_edge_end_once(spark, monkeypatch):
    from edgeconn.operators import sample
    from edgeconn.operators.graph import Graph, canonical_edges
    from edgeconn.plans.staging import stage

    g = Graph.of(stage(canonical_edges(spark.range(400).selectExpr("id AS a", "(id * 7 + 3) % 400 AS b")), "t").df)
    df = sample.k_out_draws(g, 2, 8)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(v#") == 1 and "Exchange hashpartitioning(rep#" not in plan
    monkeypatch.setattr(sample, "SPARSE", 0)
    assert sorted(map(tuple, df.collect())) == sorted(map(tuple, sample.k_out_draws(g, 2, 8).collect()))
