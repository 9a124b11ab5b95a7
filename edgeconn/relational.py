"""Relational and streaming queries around the graph methods."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgeconn import oracles as O
from edgeconn.operators.contract import edge_votes, fused_labels, inter_component_edges, widen
from edgeconn.operators.graph import Graph, canonical_edges
from edgeconn.operators.sample import edge_sample, k_out_draws
from edgeconn.plans.staging import new_path, stage
from edgeconn.sources.tables import table
from edgeconn.sources.workloads import graph, user_user
from edgeconn.streaming.windows import sessions, windowed_edges

FOUND: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        FOUND[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def ring(s, d) -> Graph:
    return Graph.of(stage(graph(s, d, "nation_ring", t=3).edges, "ring").df)


CS = O.PAIRS["customer_supplier"]
PS = O.PAIRS["part_supplier"]


@query("scan_edge_projection", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def scan(s, d):
    return table(s, d, "lineitem").select("l_partkey", "l_suppkey").distinct()


@query("filter_edges_by_ship_window", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1996-04-01' AND l_quantity > 25 AND l_partkey IS NOT NULL")
def ship_window(s, d):
    day = F.col("l_shipdate")
    return table(s, d, "lineitem").filter((day >= F.lit("1996-01-01").cast("timestamp_ntz")) & (day < F.lit("1996-04-01").cast("timestamp_ntz")) & (F.col("l_quantity") > 25) & F.col("l_partkey").isNotNull()).select("l_partkey", "l_suppkey").distinct()


def customer_degrees(s, d) -> DataFrame:
    """(c_custkey, c_nationkey, c_mktsegment, deg) of customers with an edge."""
    deg = graph(s, d, "customer_supplier").degrees
    return deg.join(table(s, d, "customer"), F.col("v") == 2 * F.col("c_custkey")).select("c_custkey", "c_nationkey", "c_mktsegment", "deg")


CUSTOMERS = f"WITH {O.edges(CS)}, cd AS (SELECT c_custkey, c_nationkey, c_mktsegment, deg FROM deg JOIN customer ON v = 2 * c_custkey)"


def regions(s, d, rows: DataFrame) -> DataFrame:
    nations = table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return rows.join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations


WITH_REGION = "cd JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query("join_broadcast_nation_degree", f"{CUSTOMERS} SELECT c_custkey, deg, n_name, r_name FROM {WITH_REGION}")
def broadcast_join(s, d):
    return regions(s, d, customer_degrees(s, d)).select("c_custkey", "deg", "n_name", "r_name")


@query("join_sort_merge_customer_supplier", "SELECT o_custkey, l_suppkey, count(*) AS mult FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def merge_join(s, d):
    lines = table(s, d, "lineitem").select("l_orderkey", "l_suppkey")
    return table(s, d, "orders").hint("merge").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey", "l_suppkey").agg(F.count(F.lit(1)).alias("mult"))


@query("join_semi_active_customers", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def semi(s, d):
    return table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("join_anti_isolated_customers", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def anti(s, d):
    return table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


RING_LABELS = f"WITH RECURSIVE {O.edges(O.ring(3))}, {O.draws(2, 2)}, {O.sampled('(SELECT 1.0 / (2 * min(deg)) FROM deg)', 2)}, {O.reach(O.FUSED)}"


def ring_labels(s, d) -> DataFrame:
    return stage(fused_labels(ring(s, d), 2, 2, O.SEED), "labels").df


@query("join_full_outer_labelings", f"{RING_LABELS} SELECT v, x.comp AS c0, y.comp AS c1 FROM (SELECT * FROM labels WHERE rep = 0) x FULL JOIN (SELECT * FROM labels WHERE rep = 1) y USING (v) WHERE x.comp IS DISTINCT FROM y.comp")
def full_outer(s, d):
    x = ring_labels(s, d)
    a, b = (x.filter(F.col("rep") == i).select("v", F.col("comp").alias(f"c{i}")) for i in (0, 1))
    return a.join(b, "v", "full").filter(~F.col("c0").eqNullSafe(F.col("c1")))


@query("join_theta_same_nation_pairs", "SELECT x.c_nationkey AS nation, count(*) AS pairs FROM customer x JOIN customer y ON x.c_nationkey = y.c_nationkey AND x.c_custkey < y.c_custkey GROUP BY 1")
def theta(s, d):
    a = table(s, d, "customer").select(F.col("c_nationkey").alias("nation"), F.col("c_custkey").alias("k"))
    return a.join(a.withColumnRenamed("k", "k2"), "nation").filter("k < k2").groupBy("nation").agg(F.count(F.lit(1)).alias("pairs"))


@query("join_interval_user_pairs", "SELECT least(x.user_id, y.user_id) AS a, greatest(x.user_id, y.user_id) AS b, count(*) AS n FROM events x JOIN events y ON x.event_id < y.event_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) < 600000000 WHERE x.user_id <> y.user_id GROUP BY ALL")
def interval_join(s, d):
    """Events less than ten minutes apart. Users are dealt into groups, and each
    two groups meet in a task, which counts the pairs of its users while it
    finds them: events are moved once a group, pairs of events never."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = table(s, d, "events").select("event_id", "user_id", us.alias("us")).dropna()
    users = e.agg(F.countDistinct("user_id")).first()[0]
    groups = max(1, -(-users // GROUP))
    own, other = F.pmod(F.xxhash64("user_id"), F.lit(groups)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))
    dealt = e.withColumn("own", own).withColumn("other", other)
    met = dealt.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "event_id", "user_id", "us")
    tasks = min(groups * (groups + 1) // 2, 2000)
    return met.repartition(tasks, "i", "j").groupBy("i", "j").applyInPandas(_close_users, "a long, b long, n long")


#: Users of a group of ``interval_join``, and pairs of events made at once.
GROUP, PAIRS_AT_ONCE = 2000, 1 << 22


def _close_users(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
    """(a, b, n): pairs of events less than ten minutes apart, of one user of
    group i and one of group j."""
    import numpy as np

    i, j = key
    pdf = pdf.sort_values("us", kind="stable")
    sides = [pdf[pdf["own"] == g] for g in (i, j)]
    (us, event, user), (us2, event2, user2) = ([x[c].to_numpy() for c in ("us", "event_id", "user_id")] for x in sides)
    (names, at), (names2, at2) = (np.unique(x, return_inverse=True) for x in (user, user2))
    low, high = np.searchsorted(us2, us - 600_000_000, "right"), np.searchsorted(us2, us + 600_000_000, "left")
    if i == j:  # each two events once
        low = np.maximum(low, np.arange(len(us)) + 1)
    sizes = np.maximum(high - low, 0)
    ends = np.cumsum(sizes)
    n = np.zeros(len(names) * len(names2), np.int64)
    start = 0
    while start < len(us):
        done = ends[start] - sizes[start]
        stop = max(start + 1, int(np.searchsorted(ends, done + PAIRS_AT_ONCE, "right")))
        part = sizes[start:stop]
        x = np.repeat(np.arange(start, stop), part)
        y = np.arange(len(x)) + np.repeat(low[start:stop] - (ends[start:stop] - part - done), part)
        real = (event[x] != event2[y]) & (user[x] != user2[y])
        n += np.bincount(at[x[real]] * len(names2) + at2[y[real]], minlength=len(n))
        start = stop
    found = np.flatnonzero(n)
    a, b = names[found // max(1, len(names2))], names2[found % max(1, len(names2))]
    out = pd.DataFrame({"a": np.minimum(a, b), "b": np.maximum(a, b), "n": n[found]})
    return out.groupby(["a", "b"], as_index=False).sum() if i == j else out


@query("join_asof_last_purchase", "SELECT c.event_id, p.ts AS bought FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT user_id, ts FROM events WHERE event_type = 'purchase') p ON c.user_id = p.user_id AND c.ts >= p.ts")
def asof(s, d):
    """The latest purchase at or before each click: one pass over both in time
    order, purchases first at equal times."""
    e = table(s, d, "events").filter(F.col("event_type").isin("click", "purchase"))
    buy = F.col("event_type") == "purchase"
    w = Window.partitionBy("user_id").orderBy("ts", F.when(buy, 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("bought", F.last(F.when(buy, F.col("ts")), ignorenulls=True).over(w)).filter(~buy).select("event_id", "bought")


@query("join_cross_repetitions", f"WITH {O.edges(O.PAIRS['nation_nation'])} SELECT v, rep FROM deg, range(4) AS r(rep)")
def cross(s, d):
    return graph(s, d, "nation_nation").vertices.crossJoin(F.broadcast(s.range(4).withColumnRenamed("id", "rep")))  # four repetitions


@query("join_lateral_top_neighbors", "SELECT c_nationkey, l_suppkey, mult FROM (SELECT c_nationkey, l_suppkey, mult, row_number() OVER (PARTITION BY c_nationkey ORDER BY mult DESC, l_suppkey) AS r FROM (SELECT c_nationkey, l_suppkey, count(*) AS mult FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY ALL)) WHERE r <= 3")
def lateral(s, d):
    lines = table(s, d, "lineitem").select("l_orderkey", "l_suppkey")
    counts = table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey")).join(lines, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("c_nationkey", "l_suppkey").agg(F.count(F.lit(1)).alias("mult"))
    stage(counts, "lateral").df.createOrReplaceTempView("edgeconn_pair_counts")
    table(s, d, "nation").createOrReplaceTempView("edgeconn_nations")
    return s.sql(
        "SELECT n_nationkey AS c_nationkey, t.l_suppkey, t.mult FROM edgeconn_nations, "
        "LATERAL (SELECT slice(array_sort(collect_list(struct(-c.mult AS less, c.l_suppkey, c.mult))), 1, 3) AS best FROM edgeconn_pair_counts c WHERE c.c_nationkey = n_nationkey), "
        "LATERAL explode(best) AS t0(x), LATERAL (SELECT x.l_suppkey, x.mult) AS t"
    )


@query("agg_distinct_neighbors", "SELECT l_partkey, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY l_partkey")
def distinct_neighbours(s, d):
    return table(s, d, "lineitem").groupBy("l_partkey").agg(F.countDistinct("l_suppkey").alias("n"))


@query("agg_approx_neighbors")
def approx_neighbours(s, d):
    return table(s, d, "lineitem").groupBy("l_partkey").agg(F.approx_count_distinct("l_suppkey", 0.02).alias("n"))


@query("agg_rollup_region_nation", f"{CUSTOMERS} SELECT r_name, n_name, CAST(sum(deg) AS BIGINT) AS ends, CAST(grouping(r_name, n_name) AS BIGINT) AS gid FROM {WITH_REGION} GROUP BY ROLLUP (r_name, n_name)")
def rollup(s, d):
    return regions(s, d, customer_degrees(s, d)).rollup("r_name", "n_name").agg(F.sum("deg").alias("ends"), F.grouping_id("r_name", "n_name").alias("gid"))


@query("agg_cube_region_segment", f"{CUSTOMERS} SELECT r_name, c_mktsegment, CAST(sum(deg) AS BIGINT) AS ends, CAST(grouping(r_name, c_mktsegment) AS BIGINT) AS gid FROM {WITH_REGION} GROUP BY CUBE (r_name, c_mktsegment)")
def cube(s, d):
    return regions(s, d, customer_degrees(s, d)).cube("r_name", "c_mktsegment").agg(F.sum("deg").alias("ends"), F.grouping_id("r_name", "c_mktsegment").alias("gid"))


@query("agg_grouping_sets_degree", f"{CUSTOMERS} SELECT n_name, c_mktsegment, count(*) AS n FROM {WITH_REGION} GROUP BY GROUPING SETS ((n_name), (c_mktsegment), ())")
def grouping_sets(s, d):
    rows = regions(s, d, customer_degrees(s, d))
    return rows.groupingSets([["n_name"], ["c_mktsegment"], []], "n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("agg_pivot_event_type", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events WHERE event_type IN ('view', 'click', 'purchase') GROUP BY user_id")
def pivot(s, d):
    kinds = ["view", "click", "purchase"]
    return table(s, d, "events").filter(F.col("event_type").isin(kinds)).groupBy("user_id").pivot("event_type", kinds).count().fillna(0)


@query("agg_side_fingerprint_sum", f"{RING_LABELS} SELECT CAST(rep AS INT) AS rep, comp, CAST(sum(('0x' || substr(md5(CAST(v AS VARCHAR)), 1, 8))::BIGINT) AS BIGINT) AS fp FROM labels GROUP BY rep, comp")
def side_sum(s, d):
    h = F.conv(F.substring(F.md5(F.col("v").cast("string")), 1, 8), 16, 10).cast("long")
    return ring_labels(s, d).groupBy("rep", "comp").agg(F.sum(h).alias("fp"))


@query("agg_side_fingerprint")
def side_xor(s, d):
    return ring_labels(s, d).groupBy("rep", "comp").agg(F.bit_xor(F.xxhash64("v")).alias("fp"))


def ps_degrees(s, d) -> DataFrame:
    """Degree of parts; ranked within degree modulo ranges, not in one task."""
    return graph(s, d, "part_supplier").degrees


DEG = f"WITH {O.edges(PS)}"


@query("window_rank_weakest", f"{DEG} SELECT v, deg, rank() OVER (PARTITION BY v % 2 ORDER BY deg) AS r, dense_rank() OVER (PARTITION BY v % 2 ORDER BY deg) AS dr FROM deg")
def rank_weakest(s, d):
    w = Window.partitionBy("side").orderBy("deg")
    return ps_degrees(s, d).withColumn("side", F.col("v") % 2).select("v", "deg", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))


@query("window_ntile_degree", f"{DEG} SELECT v, ntile(4) OVER (PARTITION BY v % 2 ORDER BY deg, v) AS tile FROM deg")
def tiles(s, d):
    return ps_degrees(s, d).withColumn("side", F.col("v") % 2).select("v", F.ntile(4).over(Window.partitionBy("side").orderBy("deg", "v")).alias("tile"))


@query("window_percent_rank_degree", f"{DEG} SELECT v, round(percent_rank() OVER (PARTITION BY v % 2 ORDER BY deg), 6) AS pr FROM deg")
def percent(s, d):
    return ps_degrees(s, d).withColumn("side", F.col("v") % 2).select("v", F.round(F.percent_rank().over(Window.partitionBy("side").orderBy("deg")), 6).alias("pr"))


FIRST_SEEN = "first AS (SELECT CAST(min(ts) AS DATE) AS day, count(*) AS n FROM (SELECT least(a, b) AS a, greatest(a, b) AS b, ts FROM (SELECT lag(user_id) OVER (ORDER BY ts, event_id) AS a, user_id AS b, ts FROM events) WHERE a <> b) GROUP BY a, b), days AS (SELECT day, count(*) AS fresh FROM first GROUP BY day)"


def fresh_by_day(s, d) -> DataFrame:
    pairs = user_user(s, d).filter("a <> b").select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y"), "ts")
    return pairs.groupBy("x", "y").agg(F.to_date(F.min("ts")).alias("day")).groupBy("day").agg(F.count(F.lit(1)).alias("fresh"))


@query("window_running_edges_by_day", f"WITH {FIRST_SEEN} SELECT day, fresh, CAST(sum(fresh) OVER (ORDER BY day ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total FROM days")
def running(s, d):
    return fresh_by_day(s, d).withColumn("total", F.sum("fresh").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)))  # a row per day


@query("window_rolling_7d_edges", f"WITH {FIRST_SEEN} SELECT day, CAST(sum(fresh) OVER (ORDER BY day RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM days")
def rolling(s, d):
    w = Window.orderBy(F.unix_date("day")).rangeBetween(-6, 0)
    return fresh_by_day(s, d).select("day", F.sum("fresh").over(w).alias("week"))  # a row per day


@query("window_lag_user_pairs", "SELECT event_id, a, b FROM (SELECT event_id, lag(user_id) OVER (ORDER BY ts, event_id) AS a, user_id AS b FROM events) WHERE a IS NOT NULL")
def lag_pairs(s, d):
    return user_user(s, d).select("event_id", "a", "b")


@query("weak_links_by_month", "SELECT month, l_partkey, n FROM (SELECT *, row_number() OVER (PARTITION BY month ORDER BY n, l_partkey) AS r FROM (SELECT strftime(l_shipdate, '%Y-%m') AS month, l_partkey, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY ALL)) WHERE r = 1")
def weak_links(s, d):
    counts = table(s, d, "lineitem").groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month"), "l_partkey").agg(F.countDistinct("l_suppkey").alias("n"))
    return counts.groupBy("month").agg(F.min(F.struct("n", "l_partkey")).alias("m")).select("month", "m.l_partkey", "m.n")


@query("topk_weakest_per_nation", f"{CUSTOMERS} SELECT c_nationkey, c_custkey, deg FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY deg, c_custkey) AS r FROM cd) WHERE r <= 3")
def topk(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("deg", "c_custkey")
    return customer_degrees(s, d).withColumn("r", F.row_number().over(w)).filter("r <= 3").select("c_nationkey", "c_custkey", "deg")


TAKEN = f"WITH {O.edges(O.ring(3))}, {O.draws(2, 1)}, {O.sampled('(SELECT 1.0 / (2 * min(deg)) FROM deg)', 1)}, o AS (SELECT j, least(v, nbr) AS src, greatest(v, nbr) AS dst FROM draws)"


def taken(s, d, j: int | None = None) -> DataFrame:
    x = k_out_draws(ring(s, d), 2, 1, O.SEED)
    x = x if j is None else x.filter(F.col("j") == j)
    return x.select(F.least("v", "nbr").alias("src"), F.greatest("v", "nbr").alias("dst"))


@query("setop_union_samples", f"{TAKEN} SELECT src, dst FROM o UNION SELECT src, dst FROM sampled")
def union(s, d):
    return taken(s, d).unionByName(edge_sample(ring(s, d), None, 1, O.SEED).select("src", "dst")).distinct()


@query("setop_intersect_draws", f"{TAKEN} SELECT src, dst FROM o WHERE j = 0 INTERSECT SELECT src, dst FROM o WHERE j = 1")
def intersect(s, d):
    return taken(s, d, 0).intersect(taken(s, d, 1))


@query("setop_except_samples", f"{TAKEN} SELECT src, dst FROM e EXCEPT SELECT src, dst FROM o")
def except_(s, d):
    return ring(s, d).edges.select("src", "dst").subtract(taken(s, d))


KEPT = f"{RING_LABELS}, {O.wide(2)}"


@query("setop_except_low_votes", f"{KEPT} SELECT src, dst FROM e EXCEPT SELECT src, dst FROM votes WHERE n_preserved >= 2")
def except_low(s, d):
    """Edges that are not kept by both of two repetitions."""
    g = ring(s, d)
    votes = edge_votes(inter_component_edges(g.edges, widen(fused_labels(g, 2, 2, O.SEED))))
    return g.edges.select("src", "dst").subtract(votes.filter("n_preserved >= 2").select("src", "dst"))


@query("incremental_min_degree", f"""WITH p AS (SELECT a, b, dayofyear(ts) AS day FROM (SELECT lag(user_id) OVER (ORDER BY ts, event_id) AS a, user_id AS b, ts FROM events) WHERE a <> b),
e AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM p WHERE day < (SELECT min(day) + 10 FROM p)), half AS (SELECT src AS v FROM e UNION ALL SELECT dst FROM e)
SELECT CAST(min(n) AS BIGINT) AS min_degree FROM (SELECT u.user_id, count(v) AS n FROM (SELECT DISTINCT user_id FROM events) u LEFT JOIN half ON v = u.user_id GROUP BY 1)""")
def first_batch_degree(s, d):
    """Least degree after the first ten days of the user graph."""
    pairs = user_user(s, d).filter("a <> b").select("a", "b", F.dayofyear("ts").alias("day"))
    first = pairs.agg(F.min("day").alias("first"))
    early = pairs.crossJoin(F.broadcast(first)).filter(F.col("day") < F.col("first") + 10)  # first: one row
    users = table(s, d, "events").select(F.col("user_id").alias("v")).distinct()
    return Graph(users, canonical_edges(early)).degrees.agg(F.min("deg").alias("min_degree"))


@query("scalar_json_props", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def json_props(s, d):
    return table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("scalar_url_host", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages")
def host(s, d):
    return table(s, d, "pages").select("page_id", F.expr("try_parse_url(url, 'HOST')").alias("host"))


@query("scalar_date_buckets", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n FROM orders GROUP BY 1")
def months(s, d):
    return table(s, d, "orders").groupBy(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("timestamp_ntz").alias("month")).agg(F.count(F.lit(1)).alias("n"))


@query("scalar_array_votes", f"{RING_LABELS} SELECT v, count(DISTINCT comp) AS parts FROM labels GROUP BY v")
def array_votes(s, d):
    return widen(ring_labels(s, d)).select("v", F.size(F.array_distinct("comps")).cast("long").alias("parts"))


@query("scalar_map_ledger", "SELECT 'n' AS metric, (SELECT count(*) FROM customer)::BIGINT AS value UNION ALL SELECT 'orders', (SELECT count(*) FROM orders)::BIGINT")
def ledger(s, d):
    n = table(s, d, "customer").agg(F.count(F.lit(1)).alias("n")).crossJoin(table(s, d, "orders").agg(F.count(F.lit(1)).alias("orders")))  # a row each
    return n.select(F.explode(F.create_map(F.lit("n"), "n", F.lit("orders"), "orders")).alias("metric", "value"))


@query("scalar_text_shingles", r"SELECT doc_id, len(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS words FROM documents")
def text_words(s, d):
    return table(s, d, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit(r"([^\x20\x09-\x0D]+)"), 1)).cast("long").alias("words"))


ISLANDS = """SELECT user_id, min(ts) AS start, count(*) AS n_events FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM (
SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, no"""


@query("session_windows_users", ISLANDS)
def user_sessions(s, d):
    return sessions(table(s, d, "events")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("supplier_sessions", """SELECT l_suppkey, min(day) AS start, CAST(sum(n) AS BIGINT) AS lines FROM (SELECT *, sum(fresh) OVER (PARTITION BY l_suppkey ORDER BY day ROWS UNBOUNDED PRECEDING) AS no FROM (
SELECT l_suppkey, day, n, CASE WHEN day - lag(day) OVER (PARTITION BY l_suppkey ORDER BY day) <= 7 THEN 0 ELSE 1 END AS fresh FROM (SELECT l_suppkey, CAST(l_shipdate AS DATE) AS day, count(*) AS n FROM lineitem GROUP BY ALL))) GROUP BY l_suppkey, no""")
def supplier_runs(s, d):
    """Gaps and islands: runs of ship days at most a week apart."""
    days = table(s, d, "lineitem").groupBy("l_suppkey", F.to_date("l_shipdate").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("l_suppkey").orderBy("day")
    fresh = F.when(F.datediff("day", F.lag("day").over(w)) <= 7, 0).otherwise(1)
    marked = days.withColumn("fresh", fresh).withColumn("no", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy("l_suppkey", "no").agg(F.min("day").alias("start"), F.sum("n").alias("lines")).drop("no")


@query("tumbling_hour_edges", "SELECT date_trunc('hour', ts)::TIMESTAMP AS start, count(*) AS n_events, CAST(sum(user_id) AS BIGINT) AS user_sum FROM events GROUP BY 1")
def tumbling(s, d):
    return windowed_edges(table(s, d, "events"), "1 hour").withColumn("start", F.col("start").cast("timestamp_ntz"))


SLIDING = "SELECT (date_trunc('hour', ts) - INTERVAL 1 HOUR * i)::TIMESTAMP AS start, count(*) AS n_events, CAST(sum(user_id) AS BIGINT) AS user_sum FROM events, range(2) AS r(i) GROUP BY 1"


@query("sliding_hour_edges", SLIDING)
def sliding(s, d):
    return windowed_edges(table(s, d, "events"), "2 hours", "1 hour").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding_edges", SLIDING)
def sliding_stream(s, d):
    """The same windows by a stream over the events file, run to its end."""
    kind = table(s, d, "events").schema
    stream = s.readStream.schema(kind).parquet(_as_dir(s, d, "events"))
    path = new_path(s, "stream-out")
    out = windowed_edges(stream, "2 hours", "1 hour", "40 days")

    def keep(batch: DataFrame, no: int) -> None:
        batch.write.mode("overwrite").parquet(path)  # complete mode: all windows each time

    out.writeStream.outputMode("complete").option("checkpointLocation", new_path(s, "stream-state")).foreachBatch(keep).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(path).withColumn("start", F.col("start").cast("timestamp_ntz"))


def _as_dir(s, d: str, name: str) -> str:
    """A folder to stream from: the table's own, or the parts of a copy."""
    path = f"{d}/{name}.parquet"
    fs = s._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(s._jsc.hadoopConfiguration())
    return path if fs.getFileStatus(s._jvm.org.apache.hadoop.fs.Path(path)).isDirectory() else stage(table(s, d, name), f"stream-{name}").path


@query("incremental_connectivity")
def incremental(s, d):
    """(batch, inserted, min_degree, value, rebuilt, touched) by week of the
    user graph; the vertices are all users of the table."""
    from edgeconn.streaming.incremental import IncrementalConnectivity

    pairs = stage(user_user(s, d).select("a", "b", F.date_format("ts", "D").cast("int").alias("day")), "pairs").df
    users = table(s, d, "events").select(F.col("user_id").alias("v")).distinct()
    state = IncrementalConnectivity(s, vertices=stage(users, "users").df)
    first = pairs.agg(F.min("day")).first()[0]
    rows = [state.process(i, pairs.filter(F.floor((F.col("day") - first) / 10) == i)) for i in range(3)]
    return s.createDataFrame(rows, "batch int, inserted long, min_degree long, value long, rebuilt boolean, touched long")


@query("udaf_component_count", f"{RING_LABELS} SELECT CAST(rep AS INT) AS rep, count(DISTINCT comp) AS parts FROM labels GROUP BY rep")
def udaf(s, d):
    @F.pandas_udf("long")
    def parts(comp: pd.Series) -> int:
        return comp.nunique()

    return ring_labels(s, d).groupBy("rep").agg(parts("comp").alias("parts"))


@query("pandas_udf_side_bits", "SELECT o_orderkey AS side, bit_count(o_orderkey) AS ones FROM orders")
def side_bits(s, d):
    @F.pandas_udf("int")
    def ones(x: pd.Series) -> pd.Series:
        return x.map(lambda v: int(v).bit_count())

    key = F.col("o_orderkey").cast("long")
    return table(s, d, "orders").select(key.alias("side"), F.when(key.isNotNull(), ones(F.coalesce(key, F.lit(0)))).alias("ones"))


@query("udtf_components", f"{RING_LABELS} SELECT CAST(rep AS INT) AS rep, v, comp FROM labels")
def udtf_components(s, d):
    from edgeconn.sqlapi import register

    g = ring(s, d)
    pairs = k_out_draws(g, 2, 2, O.SEED).select("rep", F.col("v").alias("src"), F.col("nbr").alias("dst"))
    pairs.unionByName(edge_sample(g, None, 2, O.SEED).select("rep", "src", "dst")).createOrReplaceTempView("edgeconn_pairs")
    register(s)
    return s.sql("SELECT * FROM edge_components(TABLE(edgeconn_pairs) PARTITION BY rep)")


@query("udtf_min_cut", "SELECT CAST(least(25, (SELECT count(*) FROM supplier)) AS BIGINT) AS value")
def udtf_cut(s, d):
    from edgeconn.sqlapi import register

    graph(s, d, "brand_supplier").edges.select(F.lit(0).alias("rep"), "src", "dst").createOrReplaceTempView("edgeconn_edges")
    register(s)
    return s.sql("SELECT value FROM edge_min_cut(TABLE(edgeconn_edges) PARTITION BY rep)")


@query("sink_bucketed_roundtrip", f"WITH {O.edges(PS)} SELECT count(*) AS n, CAST(sum(src) AS BIGINT) AS s, CAST(sum(dst) AS BIGINT) AS t FROM e")
def bucketed(s, d):
    """Edges written by bucket of src and read back, so that joins on src need
    no shuffle."""
    path = new_path(s, "buckets")
    edges = graph(s, d, "part_supplier").edges.withColumn("bucket", F.pmod(F.xxhash64("src"), F.lit(8)))
    edges.repartition(8, "bucket").sortWithinPartitions("src").write.partitionBy("bucket").parquet(path)
    return s.read.parquet(path).agg(F.count(F.lit(1)).alias("n"), F.sum("src").alias("s"), F.sum("dst").alias("t"))
