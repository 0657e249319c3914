"""SQL that answers for an inverse without the engine: elimination on one list of lists, and the workload matrices' cells."""

from __future__ import annotations

# Cells (i, j, x) of the workload matrices; every relation is a parenthesised SELECT.

GRAM = """(SELECT i, j, sum(p * q) + CASE WHEN i = j THEN 1.0 ELSE 0.0 END AS x
 FROM (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS p, unnest(range(64)) AS i FROM embeddings)
 JOIN (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS q, unnest(range(64)) AS j FROM embeddings) USING (vec_id) GROUP BY i, j)"""


def price(n: int, shift: float = 0.0) -> str:
    return f"""(SELECT i, j, (sum(c) % 100000) / 100000.0::DOUBLE + CASE WHEN i = j THEN {float(shift)} ELSE 0.0 END AS x
 FROM (SELECT coalesce(l_orderkey % {n}, 0) AS i, coalesce(l_partkey % {n}, 0) AS j, coalesce(CAST(round(l_extendedprice * 100) AS BIGINT), 0) AS c FROM lineitem
  UNION ALL SELECT a.i, b.j, 0 FROM range({n}) a(i), range({n}) b(j)) GROUP BY i, j)"""


FLOW_SHARES = """(WITH f AS (SELECT c_nationkey AS i, s_nationkey AS j, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS c
   FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2),
 g AS (SELECT a.n_nationkey AS i, b.n_nationkey AS j, coalesce(f.c, 0) AS c FROM nation a CROSS JOIN nation b LEFT JOIN f ON f.i = a.n_nationkey AND f.j = b.n_nationkey)
 SELECT i, j, CASE WHEN sum(c) OVER (PARTITION BY i) > 0 THEN CAST(c AS DOUBLE) / CAST(sum(c) OVER (PARTITION BY i) AS DOUBLE) ELSE 0.0 END AS x FROM g)"""

TRANSITIONS = """(WITH s AS (SELECT event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events),
 c AS (SELECT a, b, count(*) AS c FROM s WHERE a IS NOT NULL AND b IS NOT NULL GROUP BY a, b),
 t AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS k FROM (SELECT DISTINCT event_type FROM events WHERE event_type IS NOT NULL)),
 g AS (SELECT t.k AS i, u.k AS j, coalesce(c.c, 0) AS c FROM t CROSS JOIN t u LEFT JOIN c ON c.a = t.event_type AND c.b = u.event_type)
 SELECT i, j, CASE WHEN sum(c) OVER (PARTITION BY i) > 0 THEN CAST(c AS DOUBLE) / CAST(sum(c) OVER (PARTITION BY i) AS DOUBLE) ELSE 0.0 END AS x FROM g)"""


def damped(shares: str) -> str:
    return f"(SELECT i, j, CASE WHEN i = j THEN 1.0 ELSE 0.0 END - 0.9 * x AS x FROM {shares})"


SUPPLIERS = """(WITH p AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem),
 s AS (SELECT s_suppkey, row_number() OVER (ORDER BY s_suppkey) - 1 AS i FROM supplier),
 q AS (SELECT l_orderkey, i FROM p JOIN s ON s_suppkey = l_suppkey),
 w AS (SELECT a.i AS i, b.i AS j, CAST(count(*) AS DOUBLE) AS w FROM q a JOIN q b ON a.l_orderkey = b.l_orderkey AND a.i <> b.i GROUP BY 1, 2)
 SELECT a.i AS i, b.i AS j, CASE WHEN a.i = b.i THEN 1.0 + coalesce((SELECT sum(w) FROM w WHERE w.i = a.i), 0.0) ELSE -coalesce(w.w, 0.0) END AS x
 FROM s a CROSS JOIN s b LEFT JOIN w ON w.i = a.i AND w.j = b.i)"""

BRANDS = """(WITH c AS (SELECT p_brand, p_type, count(*) AS c FROM part GROUP BY 1, 2),
 b AS (SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS i FROM (SELECT DISTINCT p_brand FROM part)),
 o AS (SELECT i, p_type, c FROM c JOIN b USING (p_brand)),
 s AS (SELECT x.i AS i, y.i AS j, CAST(sum(x.c * y.c) AS DOUBLE) AS x FROM o x JOIN o y USING (p_type) GROUP BY 1, 2)
 SELECT a.i AS i, d.i AS j, coalesce(s.x, 0.0) + CASE WHEN a.i = d.i THEN 25.0 ELSE 0.0 END AS x FROM b a CROSS JOIN b d LEFT JOIN s ON s.i = a.i AND s.j = d.i)"""

NORMAL = """(WITH z AS (SELECT [1.0::DOUBLE, l_quantity, 100 * l_discount, 100 * l_tax] AS z FROM lineitem)
 SELECT i, j, sum(z[i + 1] * z[j + 1]) AS x FROM z, range(4) a(i), range(4) b(j) GROUP BY i, j)"""

HILBERT6 = "(SELECT i, j, 1.0::DOUBLE / (i + j + 1) AS x FROM range(6) a(i), range(6) b(j))"


def inverse(cells: str, n: int) -> str:
    """Relation (i, j, x): the inverse of cells by Gauss-Jordan elimination without a pivot search."""
    return f"""(WITH RECURSIVE r AS (SELECT i, list(CAST(x AS DOUBLE) ORDER BY j) AS r FROM {cells} AS c GROUP BY i),
 t AS (SELECT list(list_concat(r, list_transform(range({n}), lambda k: CASE WHEN k = i THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END)) ORDER BY i) AS t FROM r),
 e AS (SELECT 0 AS k, t FROM t UNION ALL
   SELECT k + 1, list_transform(t, lambda row, m: CASE WHEN m = k + 1 THEN p ELSE list_transform(row, lambda v, c: v - row[k + 1] * p[c]) END)
   FROM (SELECT k, t, list_transform(t[k + 1], lambda v: v / t[k + 1][k + 1]) AS p FROM e WHERE k < {n}))
 SELECT i, j, t[i + 1][{n} + j + 1] AS x FROM e, range({n}) a(i), range({n}) b(j) WHERE k = {n})"""


def cells(relation: str, digits: int) -> str:
    return f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(CAST(x AS DOUBLE), {digits}) + 0.0 AS x FROM {relation} AS c"


def lu_factors(cells_: str, n: int) -> str:
    """Relation (i, j, l, u): unpivoted factors by elimination; multipliers stay in the place of what they remove."""
    return f"""(WITH RECURSIVE r AS (SELECT i, list(CAST(x AS DOUBLE) ORDER BY j) AS r FROM {cells_} AS c GROUP BY i),
 t AS (SELECT list(r ORDER BY i) AS t FROM r),
 e AS (SELECT 0 AS k, t FROM t UNION ALL
   SELECT k + 1, list_transform(t, lambda row, m: CASE WHEN m <= k + 1 THEN row ELSE list_transform(row, lambda v, c: CASE WHEN c <= k THEN v WHEN c = k + 1 THEN row[k + 1] / p[k + 1] ELSE v - row[k + 1] / p[k + 1] * p[c] END) END)
   FROM (SELECT k, t, t[k + 1] AS p FROM e WHERE k < {n}))
 SELECT i, j, CASE WHEN i = j THEN 1.0 WHEN i > j THEN t[i + 1][j + 1] ELSE 0.0 END AS l, CASE WHEN i <= j THEN t[i + 1][j + 1] ELSE 0.0 END AS u
 FROM e, range({n}) a(i), range({n}) b(j) WHERE k = {n})"""


def product(a: str, b: str) -> str:
    return f"(SELECT a.i, b.j, sum(a.x * b.x) AS x FROM {a} AS a JOIN {b} AS b ON a.j = b.i GROUP BY a.i, b.j)"
