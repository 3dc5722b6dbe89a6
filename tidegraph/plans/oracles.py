"""SQL for DuckDB that gives the rows of the registered graph queries."""

from __future__ import annotations

import math

GEO = """SELECT DISTINCT CAST(n_nationkey AS BIGINT) * 8 + 4 AS u, CAST(n_regionkey AS BIGINT) * 8 + 5 AS v FROM nation
UNION ALL SELECT DISTINCT CAST(c_custkey AS BIGINT) * 8 + 3, CAST(c_nationkey AS BIGINT) * 8 + 4 FROM customer
UNION ALL SELECT DISTINCT CAST(s_suppkey AS BIGINT) * 8 + 2, CAST(s_nationkey AS BIGINT) * 8 + 4 FROM supplier"""
PART_SUPPLIER = "SELECT DISTINCT CAST(l_partkey AS BIGINT) * 8 + 1 AS u, CAST(l_suppkey AS BIGINT) * 8 + 2 AS v FROM lineitem"
CUSTOMER_SUPPLIER = "SELECT DISTINCT CAST(o_custkey AS BIGINT) * 8 + 3 AS u, CAST(l_suppkey AS BIGINT) * 8 + 2 AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
USER_PATHS = "SELECT CAST(event_id AS BIGINT) * 8 + 6 AS u, CAST(nxt AS BIGINT) * 8 + 6 AS v FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL"
CONVERSATIONS = "SELECT CAST(a.conv_id * 1000 + a.turn AS BIGINT) AS u, CAST(a.conv_id * 1000 + a.turn + 1 AS BIGINT) AS v FROM (SELECT DISTINCT conv_id, turn FROM conversations) a JOIN (SELECT DISTINCT conv_id, turn FROM conversations) b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"
COPIES = "SELECT CAST(min(doc_id) OVER (PARTITION BY text) AS BIGINT) AS u, CAST(doc_id AS BIGINT) AS v FROM documents WHERE text IS NOT NULL QUALIFY u <> v"
LINES = "SELECT DISTINCT CAST(doc_id AS BIGINT) * 8 AS u, CAST(('0x' || substr(md5(line), 1, 13)) AS BIGINT) * 8 + 7 AS v FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20"
USER_USER = "SELECT DISTINCT least(x, y) AS u, greatest(x, y) AS v FROM (SELECT CAST(user_id AS BIGINT) AS x, lead(CAST(user_id AS BIGINT)) OVER (ORDER BY ts, event_id) AS y FROM events) WHERE x <> y"
CATERPILLAR = USER_PATHS + " UNION ALL SELECT CAST(event_id AS BIGINT) * 8 + 6, (CAST(event_id AS BIGINT) * 5 + k) * 8 + 7 FROM events, range(1, 5) t(k) WHERE k <= event_id % 5"
KNN1 = """SELECT DISTINCT CAST(least(i, j) AS BIGINT) AS u, CAST(greatest(i, j) AS BIGINT) AS v FROM (
SELECT a.vec_id AS i, b.vec_id AS j, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 6) DESC, b.vec_id) AS r
FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r = 1"""
SIMILAR = """SELECT CAST(a.vec_id AS BIGINT) AS u, CAST(b.vec_id AS BIGINT) AS v FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id
WHERE round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 6) >= 0.35"""
CLIQUES = "SELECT DISTINCT CAST(a.user_id AS BIGINT) AS u, CAST(b.user_id AS BIGINT) AS v FROM (SELECT DISTINCT user_id FROM events) a JOIN (SELECT DISTINCT user_id FROM events) b ON a.user_id % 10 = b.user_id % 10 AND a.user_id < b.user_id"
COOCCUR = "SELECT DISTINCT CAST(least(a.user_id, b.user_id) AS BIGINT) AS u, CAST(greatest(a.user_id, b.user_id) AS BIGINT) AS v FROM events a JOIN events b ON b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 SECOND AND a.user_id <> b.user_id"


def order_part(q: int | None = None) -> str:
    return "SELECT DISTINCT CAST(l_orderkey AS BIGINT) * 8 AS u, CAST(l_partkey AS BIGINT) * 8 + 1 AS v FROM lineitem" + (f" WHERE l_quantity <= {q}" if q is not None else "")


def components(edges: str, extra: str | None = None, outer: str = "%s") -> str:
    """Least label of each vertex's component by flooding with a keyed recursion."""
    more = f" UNION SELECT * FROM ({extra}) t(x)" if extra else ""
    inner = "SELECT id AS vertex, comp AS component FROM cc"
    return f"""WITH RECURSIVE e AS ({edges}), arcs AS MATERIALIZED (SELECT u AS src, v AS dst FROM e WHERE u <> v UNION SELECT v, u FROM e WHERE u <> v),
ids AS (SELECT src AS id FROM arcs{more}),
cc(id, comp) USING KEY (id) AS (SELECT DISTINCT id, id FROM ids UNION
  (SELECT a.dst, min(c.comp) FROM cc c JOIN arcs a ON a.src = c.id JOIN recurring.cc r ON r.id = a.dst WHERE c.comp < r.comp GROUP BY a.dst))
{outer % inner}"""


def rings(k: int) -> str:
    return f"WITH n AS (SELECT count(*) // {k} AS size FROM events) SELECT i AS vertex, i // size * size AS component FROM n, range(0, (SELECT size * {k} FROM n)) t(i)"


PAGE_COMPONENTS = r"""WITH RECURSIVE e AS (SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS u, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS v FROM pages),
arcs AS MATERIALIZED (SELECT u AS src, v AS dst FROM e UNION SELECT v, u FROM e),
cc(id, comp) USING KEY (id) AS (SELECT DISTINCT src, src FROM arcs UNION
  (SELECT a.dst, min(c.comp) FROM cc c JOIN arcs a ON a.src = c.id JOIN recurring.cc r ON r.id = a.dst WHERE c.comp < r.comp GROUP BY a.dst))
SELECT id AS name, comp AS component_name FROM cc"""


def graph(edges: str) -> str:
    """Named tables arcs, verts (level = key mod 3) and lev; a query follows."""
    return f"""WITH e AS ({edges}), arcs AS (SELECT u AS src, v AS dst FROM e WHERE u <> v UNION SELECT v, u FROM e WHERE u <> v),
verts AS (SELECT DISTINCT src AS vid, CAST(src // 8 % 3 AS INTEGER) AS level FROM arcs),
lev AS (SELECT src, dst, s.level AS sl, d.level AS dl FROM arcs JOIN verts s ON s.vid = src JOIN verts d ON d.vid = dst)
"""


LINK = graph(GEO) + """, deg AS (SELECT src, count(*) AS d FROM arcs GROUP BY src),
cand AS (SELECT DISTINCT a.dst AS v, b.dst AS u FROM arcs a JOIN arcs b ON a.src = b.src AND a.dst <> b.dst JOIN deg ON deg.src = a.dst AND d < 4 WHERE NOT EXISTS (SELECT 1 FROM arcs x WHERE x.src = a.dst AND x.dst = b.dst)),
lst AS (SELECT src AS w, dst AS u, row_number() OVER (PARTITION BY src ORDER BY dst) AS r FROM arcs),
near AS (SELECT DISTINCT c.v, c.u FROM cand c JOIN arcs a ON a.src = c.v JOIN lst ON lst.w = a.dst AND lst.u = c.u AND lst.r <= 5),
pick AS (SELECT v, u FROM (SELECT n.v, n.u, d, row_number() OVER (PARTITION BY n.v ORDER BY n.u) AS r FROM near n JOIN deg ON deg.src = n.v) WHERE r <= 4 - d)
SELECT src, dst FROM arcs UNION SELECT v, u FROM pick UNION SELECT u, v FROM pick"""


def _saturated(beta0: float) -> str:
    return graph(GEO) + f""", direct AS (SELECT src AS v, sl AS level FROM lev WHERE sl = dl GROUP BY src, sl HAVING count(*) >= floor(pow({beta0}::DOUBLE, pow(1.25::DOUBLE, sl)))),
spread AS (SELECT v, level FROM direct UNION SELECT l.src, l.sl FROM lev l JOIN direct ON direct.v = l.dst WHERE l.sl = l.dl)
"""


SATURATED = _saturated(4)
LEADERS = _saturated(2) + """, leaders AS (SELECT v, level FROM spread WHERE CAST(('0x' || substr(md5('0:0:leader:' || CAST(v AS VARCHAR)), 1, 13)) AS BIGINT) / 4503599627370496.0::DOUBLE
  < least(1.0::DOUBLE, 0.3::DOUBLE * ln((SELECT count(*) FROM verts)) / pow(2.0::DOUBLE, pow(1.25::DOUBLE, level))))
"""
TWO_HOPS = """, own AS (SELECT src, dst FROM lev WHERE sl = dl), one AS (SELECT src, min(dst) AS pick FROM own JOIN leaders ON leaders.v = dst GROUP BY src),
two AS (SELECT own.src, min(one.pick) AS pick2 FROM own JOIN one ON one.src = own.dst GROUP BY own.src)
SELECT coalesce(one.src, two.src) AS v, coalesce(pick, pick2) AS leader, CAST(CASE WHEN pick IS NOT NULL THEN 1 ELSE 2 END AS INTEGER) AS hops FROM one FULL JOIN two ON one.src = two.src WHERE coalesce(one.src, two.src) <> coalesce(pick, pick2)"""
CLIQUE_TEST = components(order_part(3), outer="""SELECT component AS mu, k AS size FROM (SELECT component, count(*) AS k, sum(d) AS d FROM (%s) JOIN (SELECT src, count(*) AS d FROM arcs GROUP BY src) ON src = vertex GROUP BY component) WHERE d = k * (k - 1)""")
PICKS = graph(order_part(5)) + """, p1 AS (SELECT src AS tail, min(dst) AS head FROM arcs GROUP BY src),
p2 AS (SELECT tail, head FROM p1 WHERE NOT (tail > head AND EXISTS (SELECT 1 FROM p1 q WHERE q.tail = p1.head AND q.head = p1.tail))),
p3 AS (SELECT tail, head FROM p2 WHERE tail NOT IN (SELECT head FROM p2 GROUP BY head HAVING count(*) > 1)),
ctr AS (SELECT head FROM p3 GROUP BY head HAVING count(*) > 1),
star AS (SELECT tail, head FROM p3 WHERE head IN (SELECT head FROM ctr)),
p4 AS (SELECT tail, head FROM p3 WHERE head NOT IN (SELECT head FROM ctr) AND head NOT IN (SELECT tail FROM star)),
thin AS (SELECT tail, head FROM p4 WHERE CAST(('0x' || substr(md5('0:thin:' || CAST(tail AS VARCHAR)), 1, 13)) AS BIGINT) / 4503599627370496.0::DOUBLE < 1.0::DOUBLE / 3),
busy AS (SELECT v FROM (SELECT tail AS v FROM thin UNION ALL SELECT head FROM thin) GROUP BY v HAVING count(*) > 1),
lone AS (SELECT tail, head FROM thin WHERE tail NOT IN (SELECT v FROM busy) AND head NOT IN (SELECT v FROM busy))
"""
CYCLE_CUT = """WITH n AS (SELECT count(*) AS n FROM events), e AS (SELECT i AS u, (i + 1) % n AS v, n FROM n, range(0, (SELECT n FROM n)) t(i))
SELECT u, v FROM e WHERE CAST(('0x' || substr(md5('0:cycle:' || least(u, v) || '-' || greatest(u, v)), 1, 13)) AS BIGINT) / 4503599627370496.0::DOUBLE >= least(1.0::DOUBLE, 2.0::DOUBLE * ln(n) / 64)"""
CYCLE_CONTRACT = CYCLE_CUT.replace("SELECT u, v FROM e WHERE", "SELECT count(*) AS edges FROM e WHERE NOT")
DIAMETER = f"""WITH RECURSIVE e AS ({order_part(2)}), arcs AS MATERIALIZED (SELECT u AS src, v AS dst FROM e UNION SELECT v, u FROM e),
dist(s, t, d) USING KEY (s, t) AS (SELECT DISTINCT src, src, 0 FROM arcs UNION (SELECT x.s, a.dst, min(x.d + 1) FROM dist x JOIN arcs a ON a.src = x.t LEFT JOIN recurring.dist r ON r.s = x.s AND r.t = a.dst WHERE r.d IS NULL OR x.d + 1 < r.d GROUP BY x.s, a.dst))
SELECT component, CAST(max(ecc) AS INTEGER) AS diameter FROM (SELECT s, max(d) AS ecc, min(t) AS component FROM dist GROUP BY s) GROUP BY component"""
