"""Queries over the given tables: one for each method, variant and workload."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgeconn import oracles as O
from edgeconn.operators import baselines as B
from edgeconn.operators import measures as M
from edgeconn.operators.cactus import min_cut_cactus, small_cut_sides
from edgeconn.operators.certificate import certificate
from edgeconn.operators.components import components
from edgeconn.operators.contract import (
    adaptive_threshold,
    collapse,
    contract_once,
    edge_votes,
    fused_labels,
    inter_component_edges,
    k_out_labels,
    kernel_edges,
    merge_low_votes,
    sample_labels,
    vote_histogram,
    widen,
)
from edgeconn.operators.diameter import ball_growth, ball_members, component_diameters, disjoint_balls, low_diameter_cover
from edgeconn.operators.graph import Graph, cut_edges, half_edges, min_degree_cut, with_ids
from edgeconn.operators.mincut import as_row, edge_connectivity, solve_kernel
from edgeconn.operators.probe import forest_probe, probe_contract, probe_votes
from edgeconn.operators.sample import edge_sample, k_out_draws
from edgeconn.plans import planning as P
from edgeconn.plans.staging import stage
from edgeconn.sources.tables import table
from edgeconn.sources.workloads import block_graph, bridges, graph

FOUND: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        FOUND[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def held(spark: SparkSession, d: str, name: str, **params) -> Graph:
    """A workload graph whose edges are written once for several uses, without
    their ids, which are most of the bytes and follow from the ends; of large
    nations, whose pairs fill a disk, blocks of them."""
    by_blocks = block_graph(spark, d, name, **params)
    if by_blocks:
        return by_blocks
    return Graph.of(with_ids(stage(graph(spark, d, name, **params).edges.select("src", "dst"), name).df))


# Graphs.

GRAPHS = {
    "graph_part_supplier": ("part_supplier", {}, O.PAIRS["part_supplier"]),
    "graph_customer_supplier": ("customer_supplier", {}, O.PAIRS["customer_supplier"]),
    "graph_part_part": ("part_part", {}, O.PAIRS["part_part"]),
    "graph_supplier_supplier": ("supplier_supplier", {}, O.PAIRS["supplier_supplier"]),
    "graph_nation_ring": ("nation_ring", {"t": 3}, O.ring(3)),
    "graph_nation_chain": ("nation_chain", {"t": 1}, O.ring(1, closed=False)),
    "graph_two_block": ("two_block", {"t": 5}, O.two_block(5)),
    "graph_user_user": ("user_user", {}, O.PAIRS["user_user"]),
    "graph_brand_supplier": ("brand_supplier", {}, O.PAIRS["brand_supplier"]),
    "graph_nation_nation": ("nation_nation", {}, O.PAIRS["nation_nation"]),
}
for _key, (_name, _params, _raw) in GRAPHS.items():
    query(_key, O.canonical(_raw))(lambda s, d, n=_name, p=_params: graph(s, d, n, **p).edges.select("src", "dst"))
TEXT_IDS = {
    "user_hour": "SELECT DISTINCT 'u' || user_id AS a, 'h' || strftime(ts, '%Y%m%d%H') AS b FROM events",
    "page_links": """SELECT DISTINCT 'p' || page_id AS a, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS b FROM pages""",
    "conversation_paths": "SELECT conv_id || ':' || turn AS a, conv_id || ':' || after AS b FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations) WHERE after IS NOT NULL",
}
for _name in ("user_hour", "page_links", "conversation_paths", "embedding_neighbours", "document_shingles"):
    _sql = f"WITH {O.dictionary(TEXT_IDS[_name])} {O.canonical(O.named('SELECT a, b FROM raw'))}" if _name in TEXT_IDS else None
    query(f"graph_{_name}", _sql)(lambda s, d, n=_name: graph(s, d, n).edges.select("src", "dst"))
LAGS = "SELECT unnest([" + ", ".join(f"lag(user_id, {i}) OVER w" for i in range(1, 6)) + "]) AS a, user_id AS b FROM events WINDOW w AS (ORDER BY ts, event_id)"


@query("graph_user_user_lag5", O.canonical(f"SELECT a, b FROM ({LAGS}) WHERE a IS NOT NULL"))
def user_user_lag5(s, d):
    return graph(s, d, "user_user", lags=5).edges.select("src", "dst")


@query("degree_histogram", f"WITH {O.edges(O.PAIRS['part_supplier'])} SELECT deg, count(*) AS n FROM deg GROUP BY deg")
def degree_histogram(s, d):
    return graph(s, d, "part_supplier").degrees.groupBy("deg").agg(F.count(F.lit(1)).alias("n"))


@query("min_degree_cut", f"WITH {O.edges(O.PAIRS['customer_supplier'])} SELECT v, deg FROM deg ORDER BY deg, v LIMIT 1")
def min_degree(s, d):
    return min_degree_cut(graph(s, d, "customer_supplier"))


@query(
    "degree_by_region_rollup",
    f"""WITH {O.edges(O.PAIRS['customer_supplier'])} SELECT r_name, n_name, CAST(sum(deg) AS BIGINT) AS ends, CAST(grouping(r_name, n_name) AS BIGINT) AS gid
    FROM deg JOIN customer ON v = 2 * c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""",
)
def degree_by_region(s, d):
    deg = graph(s, d, "customer_supplier").degrees
    rows = deg.join(table(s, d, "customer"), F.col("v") == 2 * F.col("c_custkey"))
    return _with_region(s, d, rows, "c_nationkey").rollup("r_name", "n_name").agg(F.sum("deg").alias("ends"), F.grouping_id("r_name", "n_name").alias("gid"))


def _with_region(s, d, rows: DataFrame, key: str) -> DataFrame:
    nations = table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return rows.join(F.broadcast(nations), F.col(key) == F.col("n_nationkey"))  # 25 nations


# Samples and contractions.

def _draws_sql(raw: str, k: int, reps: int) -> str:
    return f"WITH {O.edges(raw)}, {O.draws(k, reps)} SELECT CAST(rep AS INT) AS rep, CAST(j AS INT) AS j, v, nbr FROM draws"


@query("one_out_draws", _draws_sql(O.PAIRS["part_supplier"], 1, 1))
def one_out(s, d):
    return k_out_draws(graph(s, d, "part_supplier"), 1, 1, O.SEED).select("rep", "j", "v", "nbr")


@query("two_out_draws", _draws_sql(O.PAIRS["part_supplier"], 2, 2))
def two_out(s, d):
    return k_out_draws(graph(s, d, "part_supplier"), 2, 2, O.SEED).select("rep", "j", "v", "nbr")


@query(
    "k_out_draws_distinct",
    f"""WITH {O.edges(O.PAIRS['part_supplier'])}, h AS (SELECT v, nbr, row_number() OVER (PARTITION BY v ORDER BY md5(concat_ws(':', {O.SEED}, 0, 'd', v, nbr)), nbr) - 1 AS j FROM half)
    SELECT 0 AS rep, CAST(j AS INT) AS j, v, nbr FROM h WHERE j < 3""",
)
def three_distinct(s, d):
    return k_out_draws(graph(s, d, "part_supplier"), 3, 1, O.SEED, replace=False).select("rep", "j", "v", "nbr")


@query(
    "k_out_draws_rank",
    f"""WITH {O.edges(O.PAIRS['part_supplier'])}, placed AS (SELECT v, nbr, row_number() OVER (PARTITION BY v ORDER BY least(v, nbr), greatest(v, nbr)) - 1 AS place FROM half)
    SELECT CAST(r.i AS INT) AS rep, CAST(j.i AS INT) AS j, v, nbr FROM range(2) AS r(i), range(2) AS j(i), deg JOIN placed USING (v)
    WHERE place = ('0x' || substr(md5(concat_ws(':', {O.SEED}, r.i, j.i, v)), 1, 8))::BIGINT % deg""",
)
def rank_draws(s, d):
    return k_out_draws(graph(s, d, "part_supplier"), 2, 2, O.SEED, draw="rank").select("rep", "j", "v", "nbr")


def _labels_sql(raw: str, reps: int, select: str, pairs: str = O.TWO_OUT, p: str = "0", k: int = 2) -> str:
    more = f", {O.sampled(p, reps)}" if "sampled" in pairs else ""
    return f"WITH RECURSIVE {O.edges(raw)}, {O.draws(k, reps)}{more}, {O.reach(pairs)} {select}"


HALF_DEGREE = "(SELECT 1.0 / (2 * min(deg)) FROM deg)"


@query("two_out_components", _labels_sql(O.ring(3), 4, "SELECT CAST(rep AS INT) AS rep, v, comp FROM labels"))
def two_out_components(s, d):
    return k_out_labels(held(s, d, "nation_ring", t=3), 2, 4, O.SEED)


@query("one_out_components", _labels_sql(O.ring(3), 2, "SELECT CAST(rep AS INT) AS rep, v, comp FROM labels", k=1))
def one_out_components(s, d):
    return k_out_labels(held(s, d, "nation_ring", t=3), 1, 2, O.SEED)


@query("two_out_components_star", _labels_sql(O.ring(3), 2, "SELECT CAST(rep AS INT) AS rep, v, comp FROM labels"))
def two_out_star(s, d):
    return k_out_labels(held(s, d, "nation_ring", t=3), 2, 2, O.SEED, strategy="star")


@query("two_out_components_sampled", _labels_sql(O.ring(3), 2, "SELECT CAST(rep AS INT) AS rep, v, comp FROM labels"))
def two_out_sampled(s, d):
    return k_out_labels(held(s, d, "nation_ring", t=3), 2, 2, O.SEED, strategy="sampled")


@query("two_out_component_sizes", _labels_sql(O.PAIRS["nation_cliques"], 2, "SELECT CAST(rep AS INT) AS rep, comp, count(*) AS size FROM labels GROUP BY rep, comp"))
def two_out_sizes(s, d):
    return k_out_labels(held(s, d, "nation_cliques"), 2, 2, O.SEED).groupBy("rep", "comp").agg(F.count(F.lit(1)).alias("size"))


@query(
    "two_out_kernel_edges",
    _labels_sql(O.ring(3), 2, "SELECT CAST(x.rep AS INT) AS rep, least(x.comp, y.comp) AS cu, greatest(x.comp, y.comp) AS cv, count(*) AS mult FROM e JOIN labels x ON x.v = src JOIN labels y ON y.v = dst AND y.rep = x.rep WHERE x.comp <> y.comp GROUP BY ALL"),
)
def two_out_kernel(s, d):
    g = held(s, d, "nation_ring", t=3)
    return collapse(kernel_edges(g, k_out_labels(g, 2, 2, O.SEED)), "rep")


@query("uniform_edge_sample", f"WITH {O.edges(O.ring(3))}, {O.sampled(HALF_DEGREE, 4)} SELECT CAST(rep AS INT) AS rep, src, dst FROM sampled")
def uniform_sample(s, d):
    return edge_sample(held(s, d, "nation_ring", t=3), None, 4, O.SEED).select("rep", "src", "dst")


@query("fused_components", _labels_sql(O.ring(3), 4, "SELECT CAST(rep AS INT) AS rep, v, comp FROM labels", O.FUSED, HALF_DEGREE))
def fused(s, d):
    return fused_labels(held(s, d, "nation_ring", t=3), 2, 4, O.SEED)


@query("certificate_contraction")
def certified(s, d):
    return contract_once(held(s, d, "nation_ring", t=3), 4, O.SEED, edge_step="certificate").groupBy("rep").agg(F.countDistinct("comp").alias("components"))


Q = 16


def _voted_sql(select: str) -> str:
    return f"WITH RECURSIVE {O.edges(O.ring(3))}, {O.draws(2, Q)}, {O.sampled(HALF_DEGREE, Q)}, {O.reach(O.FUSED)}, {O.wide(Q)} {select}"


def _voted(s, d, mode: str = "fingerprint"):
    g = held(s, d, "nation_ring", t=3)
    wide = stage(widen(fused_labels(g, 2, Q, O.SEED)), "wide").df
    return g, wide, inter_component_edges(g.edges, wide, mode)


@query("survivors_fingerprint", _voted_sql("SELECT src, dst FROM survivors"))
def survivors(s, d):
    return _voted(s, d)[2].select("src", "dst")


@query("survivors_naive", _voted_sql("SELECT src, dst FROM survivors"))
def survivors_naive(s, d):
    return _voted(s, d, "naive")[2].select("src", "dst")


@query("edge_votes", _voted_sql("SELECT src, dst, n_preserved FROM votes"))
def votes(s, d):
    return edge_votes(_voted(s, d)[2]).select("src", "dst", "n_preserved")


@query("vote_histogram", _voted_sql("SELECT n_preserved, count(*) AS n_edges FROM votes GROUP BY n_preserved"))
def histogram(s, d):
    return vote_histogram(edge_votes(_voted(s, d)[2]))


@query("kept_edges", _voted_sql("SELECT src, dst FROM votes WHERE n_preserved >= 3"))
def kept(s, d):
    return edge_votes(_voted(s, d)[2]).filter("n_preserved >= 3").select("src", "dst")


@query("vote_kernel", _voted_sql("SELECT least(x.comp, y.comp) AS cu, greatest(x.comp, y.comp) AS cv, count(*) AS mult FROM votes JOIN top x ON x.v = src JOIN top y ON y.v = dst WHERE x.comp <> y.comp GROUP BY ALL").replace(" SELECT least(x.comp", f", {O.voted(Q)} SELECT least(x.comp"))
def vote_kernel(s, d):
    g, wide, found = _voted(s, d)
    v = stage(edge_votes(found), "votes").df
    return collapse(merge_low_votes(g, wide, v, adaptive_threshold(v, g.profile["n"])).kernel)


def _first_nation(s, d, g: Graph) -> DataFrame:
    c = table(s, d, "customer").select(F.col("c_custkey").alias("v"), (F.col("c_nationkey") == 0).alias("in_s"))
    return g.vertices.join(c, "v").select("v", "in_s")


SURVIVAL = """SELECT CASE WHEN max(CAST(c = d AS INT)) = 1 THEN 0.0 ELSE round(exp(2 * sum(CASE WHEN c < d THEN ln(1.0 - c::DOUBLE / d) END)), 6) END AS p
FROM (SELECT v, sum(CAST(x.c_nationkey = 0 AS INT) <> CAST(y.c_nationkey = 0 AS INT)) AS c, count(*) AS d FROM half JOIN customer x ON x.c_custkey = v JOIN customer y ON y.c_custkey = nbr GROUP BY v)"""


@query("survival_product", f"WITH {O.edges(O.ring(3))} {SURVIVAL}".replace("sum(CAST(x.c_nationkey = 0 AS INT) <> CAST(y.c_nationkey = 0 AS INT))", "count(*) FILTER ((x.c_nationkey = 0) <> (y.c_nationkey = 0))"))
def survival(s, d):
    g = held(s, d, "nation_ring", t=3)
    return M.survival_probability(g, _first_nation(s, d, g), 2).select(F.round("p", 6).alias("p"))


@query(
    "survival_observed",
    _labels_sql(O.ring(3), 64, "SELECT count(*) AS reps, CAST(sum(kept) AS BIGINT) AS survived FROM (SELECT rep, min(CAST(one AS INT)) AS kept FROM (SELECT rep, comp, min(c_nationkey = 0) = max(c_nationkey = 0) AS one FROM labels JOIN customer ON c_custkey = v GROUP BY rep, comp) GROUP BY rep)"),
)
def survival_observed(s, d):
    g = held(s, d, "nation_ring", t=3)
    return M.survival_rate(k_out_labels(g, 2, 64, O.SEED), _first_nation(s, d, g))


BETWEEN = "SELECT x.rep AS rep, count(*) AS edges FROM e JOIN labels x ON x.v = src JOIN labels y ON y.v = dst AND y.rep = x.rep WHERE x.comp <> y.comp GROUP BY x.rep"


@query(
    "size_report",
    _labels_sql(O.ring(3), 8, f"""SELECT CAST(c.rep AS INT) AS rep, components, round(components * (SELECT min(deg) FROM deg) / (SELECT count(*) FROM deg)::DOUBLE, 6) AS scaled_components,
    coalesce(edges, 0) AS edges, round(coalesce(edges, 0) / (SELECT count(*) FROM deg)::DOUBLE, 6) AS scaled_edges
    FROM (SELECT rep, count(DISTINCT comp) AS components FROM labels GROUP BY rep) c LEFT JOIN ({BETWEEN}) b ON b.rep = c.rep"""),
)
def sizes(s, d):
    g = held(s, d, "nation_ring", t=3)
    out = M.size_report(g, k_out_labels(g, 2, 8, O.SEED))
    return out.withColumns({c: F.round(c, 6) for c in ("scaled_components", "scaled_edges")})


@query("survivor_report", _labels_sql(O.ring(3), 4, f"SELECT CAST(rep AS INT) AS rep, edges AS survivors, round(edges / ((SELECT count(*) FROM deg) * ln((SELECT count(*) FROM deg))), 6) AS scaled FROM ({BETWEEN})", O.FUSED, HALF_DEGREE))
def survivors_measured(s, d):
    g = held(s, d, "nation_ring", t=3)
    return M.survivor_report(g, fused_labels(g, 2, 4, O.SEED)).withColumn("scaled", F.round("scaled", 6))


@query(
    "ledger",
    f"""{_voted_sql('')[:-1]}, size AS (SELECT count(*)::DOUBLE AS n, (SELECT count(*) FROM e)::DOUBLE AS m, min(deg)::DOUBLE AS d FROM deg),
    rows AS (SELECT 'draw' AS phase, 'rows' AS metric, (SELECT count(*) FROM draws)::DOUBLE AS value, 2 * n * {Q} AS bound FROM size
    UNION ALL SELECT 'sample', 'rows', (SELECT count(*) FROM sampled), m * {Q} / (2 * d) FROM size
    UNION ALL SELECT 'components', 'largest_task_rows', (SELECT max(c) FROM (SELECT rep, count(*) AS c FROM (SELECT rep FROM draws UNION ALL SELECT rep FROM sampled) GROUP BY rep)), 2 * n + m / (2 * d) FROM size
    UNION ALL SELECT 'filter', 'fingerprint_bytes', 32 * m, 16 * {Q} * m FROM size
    UNION ALL SELECT 'filter', 'survivors', (SELECT count(*) FROM survivors), n * ln(n) FROM size
    UNION ALL SELECT 'vote', 'label_values', 2 * {Q} * (SELECT count(*) FROM survivors), 2 * {Q} * m FROM size)
    SELECT phase, metric, value, round(bound, 6) AS bound, round(value / bound, 6) AS ratio FROM rows""",
)
def measured_ledger(s, d):
    """What a voted contraction of the ring moves; the kept edges, which hang
    on the threshold, are left to ``vote_histogram``."""
    out = M.ledger(held(s, d, "nation_ring", t=3), Q, O.SEED).filter("metric <> 'kept_edges'")
    return out.withColumns({c: F.round(c, 6) for c in ("bound", "ratio")})


@query("small_component_share", _labels_sql(O.PAIRS["supplier_supplier"], 4, "SELECT CAST(sum(n) AS BIGINT) AS vertices, CAST(sum(CASE WHEN n <= (SELECT min(deg) FROM deg) / (8 * exp(3)) THEN n ELSE 0 END) AS BIGINT) AS small FROM (SELECT rep, comp, count(*) AS n FROM labels GROUP BY rep, comp)"))
def small_components(s, d):
    g = held(s, d, "supplier_supplier")
    return M.small_component_share(k_out_labels(g, 2, 4, O.SEED), P.component_tail_bound(1, g.profile["min_degree"])["max_size"])


@query("certificate_forest_count", f"WITH RECURSIVE {O.edges(O.PAIRS['customer_supplier'])}, {O.whole()} SELECT true AS within, count(DISTINCT comp) AS components FROM whole")
def certificate_count(s, d):
    """Whether a level-4 certificate has at most 4 (n - 1) edges, and how many
    components it leaves, which are those of the graph."""
    g = held(s, d, "customer_supplier")
    kept = stage(certificate(B.whole_kernel(g).withColumn("rep", F.lit(0)), 4, "merge"), "certificate").df
    parts = components(kept, src="cu", dst="cv").agg(F.countDistinct("comp").alias("components"))
    return kept.agg((F.count(F.lit(1)) <= 4 * (g.profile["n"] - 1)).alias("within")).crossJoin(parts)  # a row each


@query("forest_probe_summary")
def probe_summary(s, d):
    return forest_probe(held(s, d, "nation_ring", t=3), 8, O.SEED).groupBy("rep").agg(F.count(F.lit(1)).alias("kept"), F.countDistinct("cell").alias("forests"))


@query("forest_probe_votes")
def probe_summary_votes(s, d):
    return probe_votes(forest_probe(held(s, d, "nation_ring", t=3), 16, O.SEED)).groupBy("n_preserved").agg(F.count(F.lit(1)).alias("n_edges"))


@query("probe_report")
def probe_measured(s, d):
    """Kept cut edges of the first nation in 16 structures of the ring."""
    g = held(s, d, "nation_ring", t=3)
    labels = stage(k_out_labels(g, 2, 16, O.SEED), "labels").df
    return M.probe_report(g, labels, forest_probe(g, 16, O.SEED, labels=labels), _first_nation(s, d, g))


# Minimum cuts.

def _lambda(name: str, params: dict, value: str, trivial: str, key: str | None = None, **how):
    @query(key or f"mincut_{name}", f"SELECT CAST({value} AS BIGINT) AS lambda_value, {trivial} AS kind" if value else None)
    def run(s, d):
        got = edge_connectivity(held(s, d, name, **params), **how)
        return as_row(s, got).select("lambda_value", "kind")

    return run


def _delta(raw: str) -> str:
    return f"(WITH {O.edges(raw)} SELECT min(deg) FROM deg)"


def _gaps(t: int, closed: bool, n: int) -> str:
    """Sum of the n smallest gaps."""
    return f"(SELECT sum(c) FROM (SELECT count(*) AS c FROM ({O.bridges(t, closed)}) GROUP BY gap ORDER BY c LIMIT {n}))"


def _least(raw: str, gaps: str) -> tuple[str, str]:
    delta = _delta(raw)
    return f"least({delta}, {gaps})", f"CASE WHEN {gaps} < {delta} THEN 'nontrivial' ELSE 'trivial' END"


_lambda("nation_ring", {"t": 3}, *_least(O.ring(3), _gaps(3, True, 2)), key="mincut_ring")
_lambda("nation_chain", {"t": 1}, *_least(O.ring(1, False), _gaps(1, False, 1)), key="mincut_chain")
_lambda("two_block", {"t": 5}, *_least(O.two_block(5), f"(SELECT count(*) FROM ({O.canonical(O.two_block(5))}) WHERE src % 2 <> dst % 2)"), key="mincut_two_block")
_lambda("brand_supplier", {}, "least(25, (SELECT count(*) FROM supplier))", "'trivial'", key="mincut_brand_supplier")
_lambda("part_supplier", {}, _delta(O.PAIRS["part_supplier"]), "'trivial'", key="mincut_part_supplier")
_lambda("nation_cliques", {}, "(SELECT CASE WHEN count(DISTINCT c_nationkey) > 1 THEN 0 END FROM customer)", "'disconnected'", key="mincut_disconnected")
_lambda("user_user", {}, _delta(O.PAIRS["user_user"]), "'trivial'", key="mincut_user_user")
for _key, _how in {
    "pram": {"profile": "pram"},
    "congest": {"profile": "congest"},
    "probe": {"profile": "probe"},
    "best_of": {"mode": "best_of"},
    "certificate": {"mode": "best_of", "edge_step": "certificate", "solver": "capped", "q": 8},
    "tree_packing": {"solver": "tree_packing"},
}.items():
    _lambda("nation_ring", {"t": 3}, *_least(O.ring(3), _gaps(3, True, 2)), key=f"mincut_ring_{_key}", **_how)


@query("mincut_circulant", f"SELECT CAST(least(2 * 2, {_gaps(1, True, 2)}) AS BIGINT) AS lambda_value")
def circulant(s, d):
    got = edge_connectivity(held(s, d, "nation_circulant", w=2, t=1), q=48, edge_step="certificate")
    return as_row(s, got).select("lambda_value")


BRUTE = f"""WITH {O.edges("SELECT n_nationkey AS a, s_nationkey AS b FROM nation, supplier WHERE n_regionkey <= 1 AND s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey <= 1)")},
place AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS i FROM deg),
sides AS (SELECT i AS side FROM range(1, (SELECT CAST(power(2, count(*) - 1) AS BIGINT) FROM deg)) AS r(i))
SELECT CAST(min(c) AS BIGINT) AS lambda_value FROM (SELECT side, count(*) FILTER (((side >> x.i) & 1) <> ((side >> y.i) & 1)) AS c FROM sides, e JOIN place x ON x.v = src JOIN place y ON y.v = dst GROUP BY side)"""


@query("mincut_brute_nations", BRUTE)
def brute(s, d):
    some = table(s, d, "nation").filter("n_regionkey <= 1").select("n_nationkey")
    other = table(s, d, "supplier").join(F.broadcast(some), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_nationkey").alias("b")).distinct()
    pairs = some.select(F.col("n_nationkey").alias("a")).crossJoin(F.broadcast(other))  # nations of two regions
    from edgeconn.operators.graph import canonical_edges

    rows = collapse(B.whole_kernel(Graph.of(canonical_edges(pairs))))
    return solve_kernel(rows, rows, "brute").select(F.col("value").cast("long").alias("lambda_value"))


@query("cut_edges_chain", f"""SELECT least(a, b) AS src, greatest(a, b) AS dst FROM ({O.bridges(1, False)}) WHERE gap = (
SELECT arg_min(gap, (size, low)) FROM (
  SELECT g.i AS gap, least(count(*) FILTER (c_nationkey <= g.i), count(*) FILTER (c_nationkey > g.i)) AS size,
  CASE WHEN count(*) FILTER (c_nationkey <= g.i) <= count(*) FILTER (c_nationkey > g.i) THEN min(CASE WHEN c_nationkey <= g.i THEN c_custkey END) ELSE min(CASE WHEN c_nationkey > g.i THEN c_custkey END) END AS low
  FROM customer, range(24) AS g(i) GROUP BY g.i))""")
def chain_cut(s, d):
    """The bridge whose loss leaves the smallest side: of all minimum cuts of
    the chain, read from the cactus of its kernel."""
    g, labels, kernel = _kernel_of(s, d, "nation_chain", t=1)
    sides = small_cut_sides(kernel, 1).select("cut", F.explode("side").alias("comp"))
    far = sides.join(labels, "comp").groupBy("cut").agg(F.count(F.lit(1)).alias("n"), F.min("v").alias("low"))
    n = g.profile["n"]
    first = g.vertices.agg(F.min("v")).first()[0]
    rank = far.select("cut", F.least(F.col("n"), n - F.col("n")).alias("size"), F.when(2 * F.col("n") < n, F.col("low")).otherwise(F.lit(first)).alias("low"))
    best = rank.orderBy("size", "low").limit(1)
    side = sides.join(F.broadcast(best.select("cut")), "cut").join(labels, "comp").select("v", F.lit(True).alias("in_s"))  # one cut
    return cut_edges(g, side).select("src", "dst")


def _kernel_of(s, d, name: str, q: int = 16, ratio: float = 1.0, **params):
    """A workload's graph, labels and kernel, with all cuts of up to ``ratio``
    times the least: of a dense graph over a task's edges by an exact
    contraction, which reads them once, of others by votes."""
    g = held(s, d, name, **params)
    exact = B.contracted(g, ratio) if g.profile["m"] > B.KERNEL_ROWS else None
    if exact:
        return g, *exact
    step = "uniform" if g.profile["min_degree"] >= 8 else "certificate"
    wide = stage(widen(contract_once(g, q, O.SEED, edge_step=step)), "wide").df
    v = stage(edge_votes(inter_component_edges(g.edges, wide)), "votes").df
    voted = merge_low_votes(g, wide, v, adaptive_threshold(v, g.profile["n"]))
    return g, stage(voted.labels, "labels").df, stage(collapse(voted.kernel), "kernel").df


@query(
    "ring_small_cuts",
    f"""WITH gaps AS (SELECT gap, count(*) AS c FROM ({O.bridges(3, True, True)}) GROUP BY gap), low AS (SELECT sum(c) AS l FROM (SELECT c FROM gaps ORDER BY c LIMIT 2))
    SELECT CAST(x.c + y.c AS BIGINT) AS size, count(*) AS n FROM gaps x JOIN gaps y ON x.gap < y.gap WHERE x.c + y.c <= 1.25 * (SELECT l FROM low) AND x.c + y.c < {_delta(O.ring(3, True, True))} GROUP BY 1""",
)
def ring_small_cuts(s, d):
    """Non-trivial cuts of the uneven ring up to 1.25 times the least."""
    g, _, kernel = _kernel_of(s, d, "nation_ring_uneven", ratio=1.25, t=3)
    least = solve_kernel(kernel, kernel).first().value
    cuts = small_cut_sides(kernel, 1.25 * least).select(F.col("value").cast("long").alias("size"))
    return cuts.filter(F.col("size") < g.profile["min_degree"]).groupBy("size").agg(F.count(F.lit(1)).alias("n"))


@query("cactus_ring_nodes", "SELECT CAST(min(c_custkey) AS BIGINT) AS least, count(*) AS size FROM customer GROUP BY c_nationkey")
def cactus_ring(s, d):
    nodes, _ = min_cut_cactus(*_kernel_of(s, d, "nation_ring", t=3))
    return nodes.select(F.array_min("members").alias("least"), F.size("members").cast("long").alias("size"))


@query("cactus_ring_cuts", "SELECT CAST(n * (n - 1) / 2 AS BIGINT) AS cuts, n AS cycle_edges FROM (SELECT count(DISTINCT c_nationkey) AS n FROM customer)")
def cactus_ring_cuts(s, d):
    _, edges = min_cut_cactus(*_kernel_of(s, d, "nation_ring", t=3))
    return edges.filter("cycle_id IS NOT NULL").groupBy("cycle_id").count().agg(F.sum((F.col("count") * (F.col("count") - 1) / 2).cast("long")).alias("cuts"), F.sum("count").alias("cycle_edges"))


@query("cactus_chain_edges", f"SELECT DISTINCT CAST(gap AS BIGINT) AS gap, 2 AS mult FROM ({O.bridges(1, False)})")
def cactus_chain(s, d):
    g, labels, kernel = _kernel_of(s, d, "nation_chain", t=1)
    nodes, edges = min_cut_cactus(g, labels, kernel)
    nation = table(s, d, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("nation"))
    at = nodes.select("node", F.array_min("members").alias("c_custkey")).join(nation, "c_custkey").select("node", "nation")
    a, b = at.withColumnsRenamed({"node": "a", "nation": "na"}), at.withColumnsRenamed({"node": "b", "nation": "nb"})
    return edges.join(a, "a").join(b, "b").select(F.least("na", "nb").alias("gap"), "mult")


@query("cactus_star", f"WITH {O.edges(O.PAIRS['part_supplier'])} SELECT v, 2 AS mult FROM deg WHERE deg = (SELECT min(deg) FROM deg)")
def cactus_star(s, d):
    g, labels, kernel = _kernel_of(s, d, "part_supplier")
    nodes, edges = min_cut_cactus(g, labels, kernel)
    leaves = nodes.filter(F.size("members") == 1).select("node", F.array_min("members").alias("v"))
    return edges.join(leaves, edges.a == leaves.node).select("v", "mult")


# Diameters, balls, covers.

@query("component_diameter_sum")
def diameters(s, d):
    g = held(s, d, "nation_cliques")
    draws = stage(k_out_draws(g, 2, 2, O.SEED), "draws").df
    labels = stage(k_out_labels(g, 2, 2, O.SEED), "labels").df
    return M.diameter_sum(component_diameters(draws, labels), g.profile["n"], g.profile["min_degree"])


@query(
    "ball_sizes",
    f"""WITH {O.edges(O.PAIRS['supplier_supplier'])}, {O.draws(2, 1)}, o AS (SELECT DISTINCT v, nbr FROM draws),
    b0 AS (SELECT v, v AS u FROM deg), b1 AS (SELECT * FROM b0 UNION SELECT b0.v, nbr FROM b0 JOIN o ON o.v = u), b2 AS (SELECT * FROM b1 UNION SELECT b1.v, nbr FROM b1 JOIN o ON o.v = u)
    SELECT v, 0 AS i, count(*) AS ball FROM b0 GROUP BY v UNION ALL SELECT v, 1, count(*) FROM b1 GROUP BY v UNION ALL SELECT v, 2, count(*) FROM b2 GROUP BY v""",
)
def balls(s, d):
    draws = stage(k_out_draws(held(s, d, "supplier_supplier"), 2, 1, O.SEED), "draws").df
    return ball_growth(draws, 2).select("v", "i", "ball")


@query("disjoint_balls")
def packed(s, d):
    draws = stage(k_out_draws(held(s, d, "supplier_supplier"), 2, 1, O.SEED), "draws").df
    return disjoint_balls(ball_members(draws, 1))


COVER = "SELECT 0 AS rep, count(*) AS vertices, true AS shallow, true AS rooted, true AS drawn FROM customer"


def _cover(s, d, mode: str):
    """Per repetition: vertices covered, whether no tree is deeper than the
    radius, every root is a center, and every tree edge was drawn."""
    g = held(s, d, "nation_cliques")
    draws = stage(k_out_draws(g, 2, 1, O.SEED), "draws").df
    tree, centers = low_diameter_cover(draws, g.profile["n"], g.profile["min_degree"], 0.5, mode=mode)
    sides = draws.select("rep", F.col("v"), F.col("nbr").alias("parent")).unionByName(draws.select("rep", F.col("nbr").alias("v"), F.col("v").alias("parent"))).distinct().withColumn("edge", F.lit(True))
    roots = centers.select("rep", F.col("v").alias("root")).distinct().withColumn("center", F.lit(True))
    seen = tree.join(sides, ["rep", "v", "parent"], "left").join(roots, ["rep", "root"], "left")
    radius = max(1, math.ceil(0.5 * math.log(g.profile["n"])))
    return seen.groupBy("rep").agg(F.countDistinct("v").alias("vertices"), (F.max("depth") <= radius).alias("shallow"), F.min(F.coalesce("center", F.lit(False))).alias("rooted"), F.min(F.col("parent").isNull() | F.coalesce("edge", F.lit(False))).alias("drawn"))


@query("low_diameter_cover", COVER)
def cover(s, d):
    return _cover(s, d, "simple")


@query("low_diameter_cover_staged", COVER)
def cover_staged(s, d):
    return _cover(s, d, "staged")


@query("ball_failure_report")
def ball_failed(s, d):
    """(rep, failed, vertices, bound): balls that stop growing before the
    proven radius; the bound says something from degrees over 200 on."""
    g = held(s, d, "supplier_supplier")
    bound = P.ball_failure_bound(g.profile["min_degree"])
    draws = stage(k_out_draws(g, 2, 2, O.SEED), "draws").df
    return M.ball_failures(ball_growth(draws, max(1, math.ceil(bound["radius"]))), g.profile["min_degree"]).withColumn("bound", F.lit(float(bound["probability"])))


# Plans and costs.

PROFILE = """WITH e AS (SELECT DISTINCT s_nationkey AS name, l_partkey, l_suppkey FROM lineitem JOIN supplier ON l_suppkey = s_suppkey),
dp AS (SELECT name, count(*) AS deg FROM e GROUP BY name, l_partkey), ds AS (SELECT name, count(*) AS deg FROM e GROUP BY name, l_suppkey),
t AS (SELECT name, count(*) + suppliers AS n, sum(deg) AS m, least(min(deg), low) AS delta, 2 * suppliers AS diameter, least(min(deg), low) AS lam
FROM dp JOIN (SELECT name, count(*) AS suppliers, min(deg) AS low FROM ds GROUP BY name) USING (name) GROUP BY name, suppliers, low)"""
REAL = "(SELECT name, n::DOUBLE AS n, m::DOUBLE AS m, delta::DOUBLE AS delta, diameter::DOUBLE AS diameter, lam::DOUBLE AS lam FROM t)"


def profiles(s, d) -> list[tuple]:
    """(nation, n, m, delta, diameter, lam) of the graph of parts and suppliers
    of each nation of suppliers: its least degree, which bounds the cut, and
    twice its suppliers, which bound the length of a path."""
    lines = table(s, d, "lineitem").select("l_partkey", "l_suppkey")
    home = table(s, d, "supplier").select(F.col("s_nationkey").alias("name"), "s_suppkey")
    e = stage(lines.join(home, F.col("l_suppkey") == F.col("s_suppkey")).select("name", "l_partkey", "l_suppkey").distinct(), "nation-lines").df
    parts, sups = (e.groupBy("name", c).agg(F.count(F.lit(1)).alias("deg")).groupBy("name").agg(F.count(F.lit(1)).alias(f"n_{c}"), F.sum("deg").alias(f"m_{c}"), F.min("deg").alias(f"d_{c}")) for c in ("l_partkey", "l_suppkey"))
    low = F.least("d_l_partkey", "d_l_suppkey")
    out = parts.join(sups, "name").select("name", F.col("n_l_partkey") + F.col("n_l_suppkey"), "m_l_partkey", low, 2 * F.col("n_l_suppkey"), low)
    return [tuple(r) for r in out.collect()]  # a row per nation


@query("repetition_plan", f"{PROFILE} SELECT n, q, CAST(floor(0.25 * q / 2) AS INT) AS r FROM (SELECT n, CAST(ceil(8 * ln(n) / 0.25) AS INT) AS q FROM t)")
def plans(s, d):
    rows = [(n, (p := P.plan_repetitions(n, p=0.25)).q, p.threshold) for _, n, *_ in profiles(s, d)]
    return s.createDataFrame(rows, "n long, q int, r int")


@query(
    "congest_cost_table",
    f"""{PROFILE} SELECT name, round(n / delta, 3) AS two_out, round(power(n, 0.8) * power(diameter, 0.2) + power(n, 0.9), 3) AS combined, round((diameter + sqrt(n)) * power(lam, 4), 3) AS small_cut,
    CASE WHEN lam >= (CASE WHEN diameter <= sqrt(n) THEN power(n, 0.1) ELSE power(n / diameter, 0.2) END) THEN 'large_cut' ELSE 'small_cut' END AS path FROM {REAL}""",
)
def congest_table(s, d):
    rows = [(k, *(round(P.congest_cost(x, n, dia, lam, delta), 3) for x in ("two_out_partition", "combined", "small_cut")), P.congest_plan(n, dia, lam)[0]) for k, n, m, delta, dia, lam in profiles(s, d)]
    return s.createDataFrame(rows, "name long, two_out double, combined double, small_cut double, path string")


@query("congest_cost_models")
def congest_all(s, d):
    rows = [(k, x, float(P.congest_cost(x, n, dia, lam, delta)), B.COST_MODEL) for k, n, m, delta, dia, lam in profiles(s, d) for x in P.CONGEST]
    return s.createDataFrame(rows, "name long, model string, rounds double, fidelity string")


@query("mpc_cost_table", f"{PROFILE} SELECT name, round(m + n * power(log2(n), 3), 3) AS global_memory, CAST(n AS DOUBLE) AS local_memory FROM {REAL}")
def mpc_table(s, d):
    rows = []
    for k, n, m, delta, _, _ in profiles(s, d):
        _, _, local, total = P.mpc_costs(n, m, delta, 16, n)[0]
        rows.append((k, round(total, 3), local))
    return s.createDataFrame(rows, "name long, global_memory double, local_memory double")


@query("work_depth_table", f"{PROFILE} SELECT name, round(m * log2(n) + n * power(log2(n), 4), 3) AS work, round(power(log2(n), 3), 6) AS depth FROM {REAL}")
def work_table(s, d):
    rows = [(k, round((x := P.work_depth(n, m)[0])[1], 3), round(x[2], 6)) for k, n, m, *_ in profiles(s, d)]
    return s.createDataFrame(rows, "name long, work double, depth double")


@query("bound_table")
def bounds(s, d):
    rows = [(name, delta, t["max_size"], t["probability"], t["vacuous"], b["radius"], b["probability"]) for name, n, _, delta, *_ in profiles(s, d) for t, b in [(P.component_tail_bound(n, delta), P.ball_failure_bound(delta))]]
    return s.createDataFrame([(a, x, *map(float, y[:2]), bool(y[2]), *map(float, y[3:])) for a, x, *y in rows], "name long, delta long, tail_size double, tail_p double, tail_vacuous boolean, ball_radius double, ball_p double")


# Baselines.

RING_VALUE = f"SELECT CAST({_least(O.ring(3), _gaps(3, True, 2))[0]} AS DOUBLE) AS value"


@query("baseline_tree_packing", RING_VALUE)
def base_tree(s, d):
    return B.baseline_tree_packing(held(s, d, "nation_ring", t=3)).select("value")


@query("baseline_filtering", RING_VALUE)
def base_filter(s, d):
    return B.baseline_filtering(held(s, d, "nation_ring", t=3), 8).select("value")


for _name, _f in {
    "baseline_scan": B.baseline_scan,
    "baseline_uniform": lambda g: B.baseline_uniform(g, 16),
    "baseline_recursive": lambda g: B.baseline_recursive(g, 1),
    "baseline_parallel_tree_packing": lambda g: B.tree_packing_parallel(g, 8),
    "baseline_small_cut": B.baseline_small_cut,
    "baseline_skeleton": B.baseline_skeleton,
    "baseline_diffusion": B.baseline_diffusion,
    "baseline_flow": B.baseline_flow,
}.items():
    query(_name, RING_VALUE)(lambda s, d, f=_f: f(held(s, d, "nation_ring", t=3)).select("value"))


@query("baseline_estimate", "SELECT true AS within")
def base_estimate(s, d):
    """Whether the (2 + eps) estimate lies between the exact value and that."""
    g = held(s, d, "nation_ring", t=3)
    kernel = B.cut_kernel(g, 2.5)
    exact = B.baseline_scan(g, kernel).select(F.col("value").alias("exact"))
    return B.baseline_estimate(g, 0.5, kernel).crossJoin(exact).select(((F.col("value") >= F.col("exact")) & (F.col("value") <= 2.5 * F.col("exact"))).alias("within"))  # a row each


ALONE = "SELECT rep, src AS a, dst AS b FROM sampled"


@query("baseline_uniform_sample", _labels_sql(O.ring(3), 8, "SELECT CAST(rep AS INT) AS rep, count(DISTINCT comp) AS components FROM labels GROUP BY rep", ALONE, HALF_DEGREE))
def base_sample(s, d):
    return B.baseline_uniform_sample(held(s, d, "nation_ring", t=3), 8).select("rep", "components")


@query("accuracy_by_repetition", f"SELECT CAST({Q} AS BIGINT) AS runs, value AS least FROM ({RING_VALUE})")
def accuracy(s, d):
    g = held(s, d, "nation_ring", t=3)
    labels = stage(fused_labels(g, 2, Q, O.SEED), "labels").df
    return M.repetition_accuracy(g, labels, B.baseline_scan(g).first().value).select("runs", "least")


@query("k_out_sweep", f"""WITH {O.edges(O.ring(3))}, s AS {SURVIVAL.replace("sum(CAST(x.c_nationkey = 0 AS INT) <> CAST(y.c_nationkey = 0 AS INT))", "count(*) FILTER ((x.c_nationkey = 0) <> (y.c_nationkey = 0))").replace("exp(2 * sum", "exp(k * sum").replace("THEN 0.0 ELSE", "THEN 0.0 ELSE").replace("SELECT CASE", "(SELECT k, CASE", 1)}, (VALUES (1), (2), (4)) AS ks(k) GROUP BY k) SELECT CAST(k AS INT) AS k, p FROM s""")
def sweep(s, d):
    """How fast the first nation's cut loses its chance as k grows."""
    g = held(s, d, "nation_ring", t=3)
    return B.k_sweep(g, (1, 2, 4), 4, side=_first_nation(s, d, g)).select("k", F.round("p", 6).alias("p"))


@query("k_out_sweep_observed")
def sweep_observed(s, d):
    g = held(s, d, "nation_ring", t=3)
    return B.k_sweep(g, (1, 2, 4), 16, side=_first_nation(s, d, g))


@query("probe_query_counts", f"SELECT skip, value FROM ({RING_VALUE}), (VALUES ('none'), ('chunked'), ('adaptive')) AS t(skip)")
def probe_counts(s, d):
    """The value that each way of skipping comes to on the ring."""
    g = held(s, d, "nation_ring", t=3)
    return probe_runs(g).select("skip", "value")


@query("probe_work")
def probe_work(s, d):
    """Edges asked about and kept by each way of skipping."""
    return probe_runs(held(s, d, "nation_ring", t=3)).select("skip", "queried", "kept")


def probe_runs(g: Graph, reps: int = 8, threshold: int = 1) -> DataFrame:
    """(skip, queried, kept, value) of the three ways on one graph."""
    rows = []
    for skip in ("none", "chunked", "adaptive"):
        got = probe_contract(g, reps, threshold, O.SEED, skip)
        kernel = stage(collapse(got.kernel), "probe-kernel").df
        found = solve_kernel(kernel, kernel).collect()
        rows.append((skip, got.queried, got.kept, min([float(g.profile["min_degree"]), *(r.value for r in found)])))
    return g.vertices.sparkSession.createDataFrame(rows, "skip string, queried long, kept long, value double")


def queries() -> dict:
    from edgeconn import relational

    return {**FOUND, **relational.FOUND}


def oracle_sql() -> dict[str, str]:
    from edgeconn import relational

    return {**SQL, **relational.SQL}


