"""SQL for DuckDB that gives what the queries must give, by other means: breadth-first levels, climbing edge by edge, cycles that cover tree edges. It
uses no back-depths, tours or range minima. CTE parts are strings that build on each other."""

from __future__ import annotations

from spanweave.schema import KIND_BITS, KINDS, vertex_sql

V = vertex_sql
HUB = KINDS["hub"] << KIND_BITS


def distinct_edges(rows: str) -> str:
    return f"SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM ({rows}) WHERE a <> b"


TRADE = distinct_edges(f"SELECT {V('part', 'l_partkey')} AS a, {V('supplier', 'l_suppkey')} AS b FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")
ORDER_PART = distinct_edges(f"SELECT {V('order', 'l_orderkey')} AS a, {V('part', 'l_partkey')} AS b FROM lineitem WHERE l_quantity >= 46")
PART_SUPP = distinct_edges(f"SELECT {V('part', 'l_partkey')} AS a, {V('supplier', 'l_suppkey')} AS b FROM lineitem")


def _ring(rows: str) -> str:
    """`rows`: part, ord, v, t (the vertex a ring closes through)."""
    return f"""SELECT v AS a, lead(v) OVER (PARTITION BY part ORDER BY ord) AS b FROM ({rows})
    UNION ALL SELECT arg_min(v, ord), any_value(t) FROM ({rows}) GROUP BY part UNION ALL SELECT arg_max(v, ord), any_value(t) FROM ({rows}) GROUP BY part"""


_ORDERS = f"SELECT o_custkey AS part, o_orderkey AS ord, {V('order', 'o_orderkey')} AS v, {V('customer', 'o_custkey')} AS t FROM orders"
_CUSTOMERS = f"SELECT c_nationkey AS part, c_custkey AS ord, {V('customer', 'c_custkey')} AS v, {V('nation', 'c_nationkey')} AS t FROM customer"
CACTUS = distinct_edges(f"""SELECT a, b FROM ({_ring(_ORDERS)}) UNION ALL SELECT a, b FROM ({_ring(_CUSTOMERS)})
    UNION ALL SELECT {V('nation', 'n_nationkey')}, {V('region', 'n_regionkey')} FROM nation
    UNION ALL SELECT {V('region', 'r_regionkey')}, {V('region', '(r_regionkey + 1) % (SELECT count(*) FROM region)')} FROM region""")
FK = distinct_edges(f"""SELECT {V('order', 'o_orderkey')} AS a, {V('customer', 'o_custkey')} AS b FROM orders UNION ALL SELECT {V('customer', 'c_custkey')}, {V('nation', 'c_nationkey')} FROM customer
    UNION ALL SELECT {V('nation', 'n_nationkey')}, {V('region', 'n_regionkey')} FROM nation UNION ALL SELECT {V('supplier', 's_suppkey')}, {V('nation', 's_nationkey')} FROM supplier""")
_HALF = "(SELECT count(*) // 2 FROM part)"
TWO_RINGS = distinct_edges(f"SELECT {V('part', 'p_partkey')} AS a, {V('part', f'p_partkey // {_HALF} * {_HALF} + (p_partkey % {_HALF} + 1) % {_HALF}')} AS b FROM part")
ONE_RING = distinct_edges(f"SELECT {V('part', 'p_partkey')} AS a, {V('part', '(p_partkey + 1) % (SELECT count(*) FROM part)')} AS b FROM part")
CHAINS = distinct_edges(f"SELECT {V('turn', 'conv_id * 16777216 + turn')} AS a, lead({V('turn', 'conv_id * 16777216 + turn')}) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations")


def hubbed(edges: str) -> str:
    return f"SELECT src, dst FROM ({edges}) UNION SELECT src, {HUB} FROM ({edges}) UNION SELECT dst, {HUB} FROM ({edges})"


def interned(pairs: str, kind: str = "token") -> str:
    """`pairs`: id, token."""
    return distinct_edges(f"SELECT id AS a, {V(kind, 'n')} AS b FROM ({pairs}) JOIN (SELECT token, row_number() OVER (ORDER BY encode(token)) AS n FROM (SELECT DISTINCT token FROM ({pairs}))) USING (token)")


LINE_PAIRS = f"""WITH x AS (SELECT DISTINCT {V('document', 'doc_id')} AS id, trim(u.l, ' ') AS token FROM documents, unnest(string_split(text, chr(10))) AS u(l) WHERE length(trim(u.l, ' ')) >= 20)
SELECT id, token FROM x WHERE token IN (SELECT token FROM x GROUP BY token HAVING count(*) > 1)"""
LINK_PAIRS = f"SELECT DISTINCT {V('page', 'page_id')} AS id, u.t AS token FROM pages, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS u(t)"


# ---- layers of common table expressions
def graph(edges: str) -> str:
    return f"e AS MATERIALIZED ({edges}), arcs AS MATERIALIZED (SELECT src AS v, dst AS w FROM e UNION ALL SELECT dst, src FROM e)"


COMPONENTS = """comp(v, c) USING KEY (v) AS (SELECT DISTINCT v, v FROM arcs
  UNION SELECT a.v, min(k.c) FROM comp k JOIN arcs a ON k.v = a.w JOIN recurring.comp r ON r.v = a.v WHERE k.c < r.c GROUP BY a.v)"""
FOREST = """f(v, parent, root, depth) USING KEY (v) AS (SELECT v, v, v, 0 FROM comp WHERE v = c
  UNION SELECT a.w, min(f.v), min(f.root), min(f.depth) + 1 FROM f JOIN arcs a ON a.v = f.v LEFT JOIN recurring.f r ON r.v = a.w WHERE r.v IS NULL GROUP BY a.w),
fo AS MATERIALIZED (SELECT * FROM f)"""
OFF = "off AS MATERIALIZED (SELECT src, dst FROM e JOIN fo x ON x.v = src JOIN fo y ON y.v = dst WHERE x.parent <> dst AND y.parent <> src)"


def climbing(pairs: str) -> str:
    """`up`: every step of every pair (qid, u, v) until its ends meet; pa, pb are the vertices left in the step before."""
    return f"""asked AS MATERIALIZED ({pairs}),
up(qid, u, v, a, b, da, db, pa, pb) AS (SELECT qid, u, asked.v, u, asked.v, x.depth, y.depth, CAST(NULL AS BIGINT), CAST(NULL AS BIGINT) FROM asked JOIN fo x ON x.v = u JOIN fo y ON y.v = asked.v AND x.root = y.root
  UNION ALL SELECT qid, u, up.v, CASE WHEN da >= db THEN x.parent ELSE a END, CASE WHEN db >= da THEN y.parent ELSE b END, CASE WHEN da >= db THEN da - 1 ELSE da END, CASE WHEN db >= da THEN db - 1 ELSE db END,
    CASE WHEN da >= db THEN a ELSE pa END, CASE WHEN db >= da THEN b ELSE pb END FROM up JOIN fo x ON x.v = a JOIN fo y ON y.v = b WHERE a <> b),
met AS MATERIALIZED (SELECT qid, u, v, a AS lca, CASE WHEN u <> a THEN pa END AS child_u, CASE WHEN v <> a THEN pb END AS child_v FROM up WHERE a = b)"""


OFF_PAIRS = "SELECT src AS qid, src AS u, dst AS v FROM off"
#: Tree edges (by their lower end) on the cycle of every edge off the forest.
COVER = """cover AS MATERIALIZED (SELECT u, v, pa AS x FROM up WHERE pa IS NOT NULL UNION SELECT u, v, pb FROM up WHERE pb IS NOT NULL)"""
BRIDGES = "SELECT least(v, parent) AS src, greatest(v, parent) AS dst FROM fo WHERE v <> parent AND v NOT IN (SELECT x FROM cover)"
BLOCKS = """cyc AS MATERIALIZED (SELECT u, v, -row_number() OVER (ORDER BY u, v) AS k FROM off o(u, v)),
inc AS MATERIALIZED (SELECT x AS p, k AS q FROM cover JOIN cyc USING (u, v)),
two AS MATERIALIZED (SELECT p, q FROM inc UNION ALL SELECT q, p FROM inc),
lab(n, c) USING KEY (n) AS (SELECT DISTINCT v, v FROM fo WHERE v <> parent UNION SELECT DISTINCT k, CAST(9223372036854775807 AS BIGINT) FROM cyc
  UNION SELECT t.p, min(l.c) FROM lab l JOIN two t ON l.n = t.q JOIN recurring.lab r ON r.n = t.p WHERE l.c < r.c GROUP BY t.p),
col AS MATERIALIZED (SELECT least(v, parent) AS src, greatest(v, parent) AS dst, c FROM fo JOIN lab ON n = v WHERE v <> parent UNION ALL SELECT u, v, c FROM cyc JOIN lab ON n = k),
nam AS (SELECT c, min(struct_pack(s := src, d := dst)) AS z FROM col GROUP BY c),
blocks AS MATERIALIZED (SELECT src, dst, z.s AS block_src, z.d AS block_dst FROM col JOIN nam USING (c)),
vb AS MATERIALIZED (SELECT src AS v, block_src, block_dst FROM blocks UNION SELECT dst, block_src, block_dst FROM blocks),
cut AS MATERIALIZED (SELECT v, count(*) AS blocks FROM vb GROUP BY v HAVING count(*) > 1)"""
SIZES = """anc(v, x) AS (SELECT v, v FROM fo UNION ALL SELECT anc.v, fo.parent FROM anc JOIN fo ON fo.v = anc.x WHERE fo.parent <> fo.v),
siz AS MATERIALIZED (SELECT x AS v, count(*) AS size FROM anc GROUP BY x),
gap AS MATERIALIZED (SELECT fo.v, parent, root, depth, size, CASE WHEN fo.v = parent THEN 0 ELSE 1 + coalesce(sum(CASE WHEN fo.v = parent THEN 0 ELSE 2 * size END) OVER (PARTITION BY parent, fo.v = parent ORDER BY fo.v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) END AS g FROM fo JOIN siz USING (v)),
spans AS MATERIALIZED (SELECT anc.v, CAST(1 + sum(g.g) AS BIGINT) AS first FROM anc JOIN gap g ON g.v = anc.x GROUP BY anc.v),
sp AS MATERIALIZED (SELECT root, v, first, first + 2 * size - 2 AS last FROM spans JOIN gap USING (v))"""


def select(final: str, *layers: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(layers) + "\n" + final


def on_forest(edges: str, final: str, *layers: str) -> str:
    return select(final, graph(edges), COMPONENTS, FOREST, *layers)


def on_cycles(edges: str, final: str, *layers: str) -> str:
    return on_forest(edges, final, OFF, climbing(OFF_PAIRS), COVER, *layers)


def bridges(edges: str) -> str:
    return on_cycles(edges, BRIDGES)


def blocks(edges: str, final: str = "SELECT * FROM blocks") -> str:
    return on_cycles(edges, final, BLOCKS)
