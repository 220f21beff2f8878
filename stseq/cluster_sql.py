"""The sequential clustering and the border merge as recursive DuckDB SQL, for the oracle queries.

A step of the recursion inserts one event into each group at once, so the number of steps is that of the largest group.
Rows of the state: g (group), id, x, y, t (in units of the diameter bound), o (order of insertion), c (cluster), k (step).
"""

from __future__ import annotations

ROUND = 9


def _d2(a: str, b: str) -> str:
    return f"(pow({a}x - {b}x, 2) + pow({a}y - {b}y, 2) + pow({a}t - {b}t, 2))"


def _split(rows: str, hit: str, tag: str) -> str:
    """CTE mv<tag> (g, c, id): members of the clusters in ``hit`` (g, c) that leave for the new cluster of their split."""
    return f"""
 own{tag} AS (SELECT r.g, r.c, r.id, r.x, r.y, r.t, r.o, row_number() OVER (PARTITION BY r.g, r.c ORDER BY r.o) AS place, count(*) OVER (PARTITION BY r.g, r.c) AS m
  FROM {rows} r JOIN {hit} h ON h.g = r.g AND h.c = r.c),
 far{tag} AS (SELECT a.g, a.c, max({{'d': round({_d2('a.', 'b.')}, {ROUND}), 'i': -a.o, 'j': -b.o}}) AS f
  FROM own{tag} a JOIN own{tag} b ON a.g = b.g AND a.c = b.c AND a.o < b.o GROUP BY a.g, a.c),
 seed{tag} AS (SELECT q.g, q.c, q.f.d AS d, -q.f.i AS i, -q.f.j AS j, a.x AS ax, a.y AS ay, a.t AS az, b.x AS bx, b.y AS bw, b.t AS bz
  FROM far{tag} q JOIN own{tag} a ON a.g = q.g AND a.c = q.c AND a.o = -q.f.i JOIN own{tag} b ON b.g = q.g AND b.c = q.c AND b.o = -q.f.j),
 mv{tag} AS (SELECT o.g, o.c, o.id FROM own{tag} o JOIN seed{tag} s ON s.g = o.g AND s.c = o.c
  WHERE CASE WHEN s.d <= 0 THEN o.place > (o.m + 1) // 2 ELSE o.o <> s.i AND (o.o = s.j
   OR round((pow(o.x - ax, 2) + pow(o.y - ay, 2) + pow(o.t - az, 2)) - (pow(o.x - bx, 2) + pow(o.y - bw, 2) + pow(o.t - bz, 2)), {ROUND}) > 0) END)"""


_WIDE = "sqrt(greatest(0, 2 * (coalesce(var_samp(x), 0) + coalesce(var_samp(y), 0) + coalesce(var_samp(t), 0)))) > 1 + 1e-9"


def clustering(source: str, limit: int | None = None, name: str = "cl") -> str:
    """CTEs up to ``name`` (id, g, c): clusters of ``source`` (g, id, x, y, t in units of the bound, o) by farthest-pair splits.

    ``limit``: clusters above so many members are split, and each piece once more if it is too wide.
    """
    first = f"count(*) > {limit} OR ({_WIDE})" if limit else _WIDE
    second = ""
    last = "a1"
    if limit:
        second = f""",
 pieces AS (SELECT a1.g, a1.c FROM a1 JOIN hit1 h ON h.g = a1.g AND h.full AND (a1.c = h.c OR a1.c = h.m + 1) GROUP BY a1.g, a1.c HAVING {_WIDE}),
 hit2 AS (SELECT p.g, p.c, h.m + 1 + row_number() OVER (PARTITION BY p.g ORDER BY p.c) AS made FROM pieces p JOIN hit1 h ON h.g = p.g),
 {_split('a1', 'hit2', '2')},
 a2 AS (SELECT r.g, r.id, r.x, r.y, r.t, r.o, CASE WHEN v.id IS NULL THEN r.c ELSE h.made END AS c FROM a1 r LEFT JOIN mv2 v ON v.g = r.g AND v.id = r.id LEFT JOIN hit2 h ON h.g = v.g AND h.c = v.c)"""
        last = "a2"
    return f"""st AS (SELECT g, id, x, y, t, o, 0::BIGINT AS c, 1::BIGINT AS k FROM {source} WHERE o = 1
 UNION ALL (
 WITH nw AS (SELECT p.* FROM {source} p JOIN (SELECT DISTINCT g, k FROM st) s ON p.g = s.g AND p.o = s.k + 1),
 cen AS (SELECT g, c, avg(x) AS x, avg(y) AS y, avg(t) AS t FROM st GROUP BY g, c),
 top AS (SELECT g, max(c) AS m FROM st GROUP BY g),
 nr AS (SELECT w.g, w.id, min({{'d': round({_d2('w.', 'n.')}, {ROUND}), 'c': n.c}}).c AS c FROM nw w JOIN cen n ON n.g = w.g GROUP BY w.g, w.id),
 al AS (SELECT st.g, st.id, st.x, st.y, st.t, st.o, st.c FROM st JOIN nw ON nw.g = st.g UNION ALL SELECT w.g, w.id, w.x, w.y, w.t, w.o, nr.c FROM nw w JOIN nr ON nr.g = w.g),
 hit1 AS (SELECT al.g, al.c, any_value(top.m) AS m, {f'count(*) > {limit}' if limit else 'false'} AS "full" FROM al JOIN nr ON nr.g = al.g AND nr.c = al.c JOIN top ON top.g = al.g GROUP BY al.g, al.c HAVING {first}),
 {_split('al', 'hit1', '1')},
 a1 AS (SELECT r.g, r.id, r.x, r.y, r.t, r.o, CASE WHEN v.id IS NULL THEN r.c ELSE h.m + 1 END AS c FROM al r LEFT JOIN mv1 v ON v.g = r.g AND v.id = r.id LEFT JOIN hit1 h ON h.g = v.g){second}
 SELECT g, id, x, y, t, o, c, (SELECT max(k) + 1 FROM st) FROM {last}
 )),
 {name} AS (SELECT st.id, st.g, st.c FROM st JOIN (SELECT g, max(o) AS m FROM {source} GROUP BY g) e ON e.g = st.g AND st.k = e.m)"""


def absorbing(source: str, name: str = "cl") -> str:
    """CTEs up to ``name`` (id, g, c): each event joins the nearest cluster while its diameter stays within the bound, else is a new one."""
    return f"""st AS (SELECT g, id, x, y, t, o, 0::BIGINT AS c, 1::BIGINT AS k FROM {source} WHERE o = 1
 UNION ALL (
 WITH nw AS (SELECT p.* FROM {source} p JOIN (SELECT DISTINCT g, k FROM st) s ON p.g = s.g AND p.o = s.k + 1),
 cen AS (SELECT g, c, count(*) AS n, avg(x) AS x, avg(y) AS y, avg(t) AS t, coalesce(var_samp(x) + var_samp(y) + var_samp(t), 0) * (count(*) - 1) AS ss FROM st GROUP BY g, c),
 top AS (SELECT g, max(c) AS m FROM st GROUP BY g),
 nr AS (SELECT w.g, w.id, min({{'d': round({_d2('w.', 'n.')}, {ROUND}), 'c': n.c, 'n': n.n, 'ss': n.ss}}) AS b FROM nw w JOIN cen n ON n.g = w.g GROUP BY w.g, w.id),
 put AS (SELECT nr.g, nr.id, CASE WHEN sqrt(2 * (b.ss + b.d * b.n / (b.n + 1)) / b.n) <= 1 + 1e-9 THEN b.c ELSE top.m + 1 END AS c FROM nr JOIN top ON top.g = nr.g)
 SELECT st.g, st.id, st.x, st.y, st.t, st.o, st.c, st.k + 1 FROM st JOIN nw ON nw.g = st.g UNION ALL SELECT w.g, w.id, w.x, w.y, w.t, w.o, put.c, w.o FROM nw w JOIN put ON put.g = w.g
 )),
 {name} AS (SELECT st.id, st.g, st.c FROM st JOIN (SELECT g, max(o) AS m FROM {source} GROUP BY g) e ON e.g = st.g AND st.k = e.m)"""


def merging(clusters: str, name: str = "merged", limit: int | None = None) -> str:
    """CTEs up to ``name``: rounds of mutual-nearest merges of ``clusters`` (g, type, tile, n, ss, x, y, t; units of the bound).

    ``name`` has (g, root): the cluster that each cluster ended in.
    """
    few = f"AND a.n + b.n <= {limit}" if limit else ""
    return f"""mg AS (SELECT g, g AS root, type, tile, false AS joined, n, ss, x, y, t, 0::BIGINT AS k FROM {clusters}
 UNION ALL (
 WITH u AS (SELECT DISTINCT root, type, tile, joined, n, ss, x, y, t FROM mg),
 cand AS (SELECT a.root AS a, b.root AS b, {_d2('a.', 'b.')} AS gap FROM u a JOIN u b ON a.type = b.type AND a.root <> b.root AND (a.tile <> b.tile OR a.joined OR b.joined) {few}
  AND abs(a.t - b.t) <= 1 AND {_d2('a.', 'b.')} <= 1
  AND sqrt(2 * (a.ss + b.ss + {_d2('a.', 'b.')} * a.n * b.n / (a.n + b.n)) / (a.n + b.n - 1)) <= 1),
 best AS (SELECT a, min({{'gap': gap, 'b': b}}).b AS b FROM cand GROUP BY a),
 pair AS (SELECT p.a AS keep, p.b AS gone FROM best p JOIN best q ON q.a = p.b AND q.b = p.a WHERE p.a < p.b),
 mv AS (SELECT u.*, coalesce(pair.keep, u.root) AS into_ FROM u LEFT JOIN pair ON pair.gone = u.root),
 su AS (SELECT into_, any_value(type) AS type, min(tile) AS tile, count(*) > 1 OR bool_or(joined) AS joined, sum(n)::BIGINT AS n, sum(x * n) / sum(n) AS x, sum(y * n) / sum(n) AS y, sum(t * n) / sum(n) AS t,
  CASE WHEN count(*) > 1 THEN sum(ss) + greatest(0, sum((x * x + y * y + t * t) * n) - (pow(sum(x * n), 2) + pow(sum(y * n), 2) + pow(sum(t * n), 2)) / sum(n)) ELSE sum(ss) END AS ss FROM mv GROUP BY into_)
 SELECT m.g, s.into_, s.type, s.tile, s.joined, s.n, s.ss, s.x, s.y, s.t, m.k + 1 FROM mg m LEFT JOIN pair ON pair.gone = m.root JOIN su s ON s.into_ = coalesce(pair.keep, m.root)
 WHERE EXISTS (SELECT 1 FROM pair)
 )),
 {name} AS (SELECT g, root FROM mg WHERE k = (SELECT max(k) FROM mg))"""
