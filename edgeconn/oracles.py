"""SQL twins of the graph queries, for an engine that reads the same tables."""

from __future__ import annotations

SEED = 1


def canonical(raw: str) -> str:
    return f"SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM ({raw}) WHERE a <> b"


PAIRS = {
    "part_supplier": "SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem",
    "customer_supplier": "SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "part_part": "SELECT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_partkey < y.l_partkey",
    "supplier_supplier": "SELECT x.l_suppkey AS a, y.l_suppkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_suppkey < y.l_suppkey",
    "nation_cliques": "SELECT x.c_custkey AS a, y.c_custkey AS b FROM customer x JOIN customer y ON x.c_nationkey = y.c_nationkey AND x.c_custkey < y.c_custkey",
    "user_user": "SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events",
    "brand_supplier": "SELECT 2 * k AS a, 2 * l_suppkey + 1 AS b FROM lineitem JOIN (SELECT p_partkey, dense_rank() OVER (ORDER BY p_brand) - 1 AS k FROM part) ON p_partkey = l_partkey",
    "nation_nation": "SELECT c_nationkey AS a, s_nationkey AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey",
}
RANKED = "SELECT c_custkey AS v, c_nationkey AS nation, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS r FROM customer"


def bridges(t: int, closed: bool = True, uneven: bool = False) -> str:
    limit = f"{t} + x.nation % 2" if uneven else str(t)
    return f"SELECT x.v AS a, y.v AS b, x.nation AS gap FROM ({RANKED}) x JOIN ({RANKED}) y ON y.nation = (x.nation + 1) % 25 AND x.r = y.r WHERE x.r < {limit}" + ("" if closed else " AND x.nation < 24")


def ring(t: int, closed: bool = True, uneven: bool = False) -> str:
    return f"{PAIRS['nation_cliques']} UNION ALL SELECT a, b FROM ({bridges(t, closed, uneven)})"


def two_block(t: int) -> str:
    return f"SELECT a, b FROM ({PAIRS['part_part']}) WHERE a % 2 = b % 2 UNION ALL SELECT 2 * i, 2 * i + 1 FROM range({t}) AS x(i)"


def edges(raw: str) -> str:
    return f"e AS ({canonical(raw)}), half AS (SELECT src AS v, dst AS nbr FROM e UNION ALL SELECT dst, src FROM e), deg AS (SELECT v, count(*) AS deg FROM half GROUP BY v)"


def draws(k: int, reps: int, seed: int = SEED) -> str:
    return f"""tries AS (SELECT r.i AS rep, j.i AS j FROM range({reps}) AS r(i), range({k}) AS j(i)),
    draws AS (SELECT rep, j, v, arg_min(nbr, md5(concat_ws(':', {seed}, rep, j, v, nbr))) AS nbr FROM half, tries GROUP BY rep, j, v)"""


def sampled(p: str, reps: int, seed: int = SEED) -> str:
    """p: SQL for the probability."""
    return f"""sampled AS (SELECT rep, src, dst FROM e, (SELECT i AS rep FROM range({reps}) AS r(i))
    WHERE substr(md5(concat_ws(':', {seed}, rep, 'e', src, dst)), 1, 8) < printf('%08x', CAST(floor({p} * 4294967296) AS BIGINT)))"""


def reach(pairs: str) -> str:
    """Components of (rep, a, b) by least label, sources being all of ``deg``."""
    return f"""sym AS (SELECT rep, a, b FROM ({pairs}) UNION SELECT rep, b, a FROM ({pairs})),
    cc(rep, v, comp) USING KEY (rep, v) AS (
      SELECT rep, v, v FROM deg, (SELECT DISTINCT rep FROM sym)
      UNION
      SELECT s.rep, s.b, min(c.comp) FROM cc c JOIN sym s ON s.rep = c.rep AND s.a = c.v JOIN recurring.cc o ON o.rep = s.rep AND o.v = s.b
      WHERE c.comp < o.comp GROUP BY s.rep, s.b),
    labels AS (SELECT rep, v, comp FROM cc)"""


def named(raw: str, a: str = "a", b: str = "b") -> str:
    """Pairs of text ids as numbers in name order."""
    return f"""SELECT x.v AS a, y.v AS b FROM ({raw}) p JOIN names x ON x.name = p.{a} JOIN names y ON y.name = p.{b}"""


def dictionary(raw: str) -> str:
    return f"raw AS ({raw}), names AS (SELECT name, row_number() OVER (ORDER BY name) - 1 AS v FROM (SELECT a AS name FROM raw UNION SELECT b FROM raw) WHERE name IS NOT NULL)"


def whole(name: str = "whole") -> str:
    """Components of all edges."""
    return f"""both_ways AS (SELECT src AS a, dst AS b FROM e UNION SELECT dst, src FROM e),
    {name}(v, comp) USING KEY (v) AS (
      SELECT v, v FROM deg UNION SELECT s.b, min(c.comp) FROM {name} c JOIN both_ways s ON s.a = c.v JOIN recurring.{name} o ON o.v = s.b WHERE c.comp < o.comp GROUP BY s.b)"""


def voted(reps: int, c: int = 4) -> str:
    """The kernel of the vote: threshold, merged classes, parallel edges."""
    return f"""hist AS (SELECT n_preserved AS k, count(*) AS n FROM votes GROUP BY 1),
    cut AS (SELECT coalesce(min(r), (SELECT max(k) + 1 FROM hist)) AS r FROM (SELECT k AS r, sum(n) OVER (ORDER BY k DESC) AS left_over FROM hist) WHERE left_over <= {c} * (SELECT count(*) FROM deg)),
    same AS (SELECT v AS a, min(v) OVER (PARTITION BY comps) AS b FROM wide UNION SELECT src, dst FROM votes WHERE n_preserved < (SELECT greatest(1, r) FROM cut)),
    sym2 AS (SELECT a, b FROM same WHERE a <> b UNION SELECT b, a FROM same WHERE a <> b),
    top(v, comp) USING KEY (v) AS (
      SELECT v, v FROM deg UNION SELECT s.b, min(t.comp) FROM top t JOIN sym2 s ON s.a = t.v JOIN recurring.top o ON o.v = s.b WHERE t.comp < o.comp GROUP BY s.b)"""


TWO_OUT = "SELECT rep, v AS a, nbr AS b FROM draws"
FUSED = TWO_OUT + " UNION ALL SELECT rep, src AS a, dst AS b FROM sampled"


def wide(reps: int) -> str:
    """Label lists, survivors and votes."""
    return """wide AS (SELECT v, list(comp ORDER BY rep) AS comps FROM labels GROUP BY v),
    survivors AS (SELECT src, dst, x.comps AS cu, y.comps AS cv FROM e JOIN wide x ON x.v = src JOIN wide y ON y.v = dst WHERE x.comps <> y.comps),
    votes AS (SELECT src, dst, CAST(list_sum(list_transform(list_zip(cu, cv), lambda t: CAST(t[1] <> t[2] AS INT))) AS INT) AS n_preserved FROM survivors)"""
