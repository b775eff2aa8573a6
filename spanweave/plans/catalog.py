"""Queries by name and, where SQL can express them, the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave import graphs
from spanweave.functions.udfs import BridgesOf
from spanweave.ledger import Budget, settle
from spanweave.operators import blocks as bl
from spanweave.operators import bridges as br
from spanweave.operators import hub, measures, pointers
from spanweave.operators.components import connected_components
from spanweave.operators.compress import step_of
from spanweave.operators.forest import spanning_forest
from spanweave.operators.lca import lca_batch
from spanweave.operators.paths import ancestor_paths
from spanweave.operators.positions import dense_positions
from spanweave.operators.rangemin import range_min
from spanweave.operators.tour import check_tour, dfs_sequence, subtree_sizes
from spanweave.plans import oracle as sql
from spanweave.plans import sqlviews
from spanweave.schema import vertex
from spanweave.sources.tables import read_table
from spanweave.streaming import edges as stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, answer: str | None = None):
    def enter(f):
        QUERIES[name] = f
        if answer:
            ORACLES[name] = answer
        return f

    return enter


def family(names: dict[str, Callable], answer: str | None) -> None:
    """Variants that must give the same rows."""
    for name, f in names.items():
        query(name, answer)(f)


# ---- bridges
def _bridges(build, **how):
    return lambda spark, d: br.find_bridges(build(spark, d), **how)


family(
    {
        "bridges_trade": _bridges(graphs.trade_sparse),
        "bridges_trade_interval": _bridges(graphs.trade_sparse, method="interval"),
        "bridges_trade_hook": _bridges(graphs.trade_sparse, method="hook"),
        "bridges_trade_contract": _bridges(graphs.trade_sparse, method="interval", forest="contract", tour_method="tour_ranking"),
        "bridges_trade_sampled": _bridges(graphs.trade_sparse, method="interval", s=64),
        "bridges_trade_local": _bridges(graphs.trade_sparse, method="local"),
        "bridges_trade_brute": _bridges(graphs.trade_sparse, method="brute"),
    },
    sql.bridges(sql.TRADE),
)
family({"bridges_cactus": _bridges(graphs.ring_cactus), "bridges_cactus_interval": _bridges(graphs.ring_cactus, method="interval")}, sql.bridges(sql.CACTUS))
query("bridges_forest", sql.bridges(sql.FK))(_bridges(graphs.fk_forest))
query("bridges_order_part", sql.bridges(sql.ORDER_PART))(_bridges(graphs.order_part, method="interval"))
query("bridges_links", sql.bridges(sql.interned(sql.LINK_PAIRS)))(_bridges(graphs.links, method="interval"))


# ---- blocks
def _blocks(build, **how):
    return lambda spark, d: bl.color_blocks(build(spark, d), **how)


def _two_hubbed(spark, d):
    return hub.add_hub(graphs.rings(spark, d, 2))


family(
    {
        "blocks_trade": _blocks(graphs.trade_sparse),
        "blocks_trade_interval": _blocks(graphs.trade_sparse, method="interval"),
        "blocks_trade_all_edges": _blocks(graphs.trade_sparse, aux="all_edges"),
        "blocks_trade_sparsified": _blocks(graphs.trade_sparse, method="interval", presparsify=True),
        "blocks_trade_local": _blocks(graphs.trade_sparse, method="local"),
    },
    sql.blocks(sql.TRADE),
)
query("blocks_cactus", sql.blocks(sql.CACTUS))(_blocks(graphs.ring_cactus))
query("blocks_hub_two", sql.blocks(sql.hubbed(sql.TWO_RINGS)))(lambda spark, d: bl.color_blocks(_two_hubbed(spark, d), method="interval"))
query("blocks_lines", sql.blocks(sql.interned(sql.LINE_PAIRS)))(_blocks(graphs.line_share, method="interval"))
query("cut_vertices_cactus", sql.blocks(sql.CACTUS, "SELECT v, blocks FROM cut"))(lambda spark, d: bl.cut_vertices(bl.color_blocks(graphs.ring_cactus(spark, d), method="interval")))
_SIZES = "SELECT block_src, block_dst, edges, vertices FROM (SELECT block_src, block_dst, count(*) AS edges FROM blocks GROUP BY ALL) JOIN (SELECT block_src, block_dst, count(*) AS vertices FROM vb GROUP BY ALL) USING (block_src, block_dst)"
query("block_sizes_trade", sql.blocks(sql.TRADE, _SIZES))(lambda spark, d: bl.block_sizes(bl.color_blocks(graphs.trade_sparse(spark, d), method="interval")))
query("block_cut_tree_cactus", sql.blocks(sql.CACTUS, "SELECT v AS cut, block_src, block_dst FROM vb WHERE v IN (SELECT v FROM cut)"))(lambda spark, d: bl.block_cut_tree(bl.color_blocks(graphs.ring_cactus(spark, d), method="interval")))
query("fundamental_cycles_trade", sql.on_cycles(sql.TRADE, "SELECT u AS cycle_src, cover.v AS cycle_dst, least(x, parent) AS src, greatest(x, parent) AS dst FROM cover JOIN fo ON fo.v = x UNION ALL SELECT src, dst, src, dst FROM off"))(
    lambda spark, d: bl.fundamental_cycles(graphs.trade_sparse(spark, d))
)
_CONDITION = """, fit AS (SELECT v FROM cut UNION SELECT v FROM arcs GROUP BY v HAVING count(*) = 1)"""
query("bridge_conditions_trade", sql.blocks(sql.TRADE, "SELECT src, dst FROM e WHERE src IN (SELECT v FROM fit) AND dst IN (SELECT v FROM fit)").replace("SELECT src, dst FROM e WHERE src IN", _CONDITION + " SELECT src, dst FROM e WHERE src IN"))(
    lambda spark, d: bl.bridge_conditions(graphs.trade_sparse(spark, d), bl.color_blocks(graphs.trade_sparse(spark, d), method="interval"))
)
_TWO_EDGE = """WITH RECURSIVE w AS MATERIALIZED ({inner}), vs AS MATERIALIZED (SELECT src AS v FROM ({edges}) UNION SELECT dst FROM ({edges})),
arcs2 AS MATERIALIZED (SELECT src AS v, dst AS w FROM ({edges}) t WHERE NOT EXISTS (SELECT 1 FROM w WHERE w.src = t.src AND w.dst = t.dst) UNION ALL SELECT dst, src FROM ({edges}) t WHERE NOT EXISTS (SELECT 1 FROM w WHERE w.src = t.src AND w.dst = t.dst)),
c2(v, c) USING KEY (v) AS (SELECT v, v FROM vs UNION SELECT a.v, min(k.c) FROM c2 k JOIN arcs2 a ON k.v = a.w JOIN recurring.c2 r ON r.v = a.v WHERE k.c < r.c GROUP BY a.v)
SELECT v, c AS comp FROM c2"""
query("two_edge_components_trade", _TWO_EDGE.format(inner=sql.bridges(sql.TRADE), edges=sql.TRADE))(lambda spark, d: br.two_edge_components(graphs.trade_sparse(spark, d), method="interval"))


@query("aux_graph_size_trade", sql.on_cycles(sql.TRADE, """SELECT (SELECT count(*) FROM fo) AS n, (SELECT count(*) FROM e) AS m, (SELECT count(*) FROM fo WHERE v <> parent) AS aux_vertices,
  (SELECT count(*) FROM fo g WHERE g.v <> g.parent AND g.depth > 1 AND EXISTS (SELECT 1 FROM cover c1 JOIN cover c2 ON c1.u = c2.u AND c1.v = c2.v WHERE c1.x = g.v AND c2.x = g.parent))
  + (SELECT count(*) FROM met WHERE lca <> u AND lca <> v) AS aux_edges,
  (SELECT count(*) FROM fo WHERE v <> parent) + (SELECT count(*) FROM off) AS aux_all_vertices, (SELECT max(depth) FROM fo) AS depth"""))
def aux_graph_size_trade(spark, d):
    return measures.aux_report(graphs.trade_sparse(spark, d))


# ---- components, forests, pointers
_COMPS = sql.select("SELECT v, c AS comp FROM comp", sql.graph(sql.ORDER_PART), sql.COMPONENTS)
family({f"components_order_part{'' if m == 'stars' else '_' + m}": (lambda spark, d, m=m: connected_components(graphs.order_part(spark, d), method=m)) for m in ("stars", "hook", "contract", "local")}, _COMPS)
_RING_COMPS = sql.select("SELECT v, c AS comp FROM comp", sql.graph(sql.TRADE), sql.COMPONENTS)
query("components_trade_naive", _RING_COMPS)(lambda spark, d: connected_components(graphs.trade_sparse(spark, d), method="naive"))
query("components_via_hub", _RING_COMPS)(lambda spark, d: hub.components_via_hub(graphs.trade_sparse(spark, d), method="interval"))
_CYCLES = " UNION ALL ".join(f"SELECT * FROM ({sql.select(f'SELECT CAST({k} AS BIGINT) AS rings, count(DISTINCT c) AS verdict FROM comp', sql.graph(edges), sql.COMPONENTS)})" for k, edges in ((1, sql.ONE_RING), (2, sql.TWO_RINGS)))
query("one_or_two_cycles", _CYCLES)(
    lambda spark, d: spark.createDataFrame([(k, hub.one_or_two_cycles(graphs.rings(spark, d, k), method="interval")) for k in (1, 2)], "rings long, verdict long")
)
_FOREST = "SELECT v, parent, root, depth FROM fo"
family({"forest_depths_trade": lambda spark, d: spanning_forest(graphs.trade_sparse(spark, d)), "forest_depths_trade_bfs": lambda spark, d: spanning_forest(graphs.trade_sparse(spark, d), method="bfs")}, sql.on_forest(sql.TRADE, _FOREST))
query("depths_by_doubling_cactus", sql.on_forest(sql.CACTUS, _FOREST))(lambda spark, d: pointers.depths(_forest(graphs.ring_cactus, spark, d)))
query("child_ranks_fk", sql.on_forest(sql.FK, "SELECT v, parent, CAST(CASE WHEN v = parent THEN 1 ELSE row_number() OVER (PARTITION BY parent, v = parent ORDER BY v) END AS INT) AS rank FROM fo"))(
    lambda spark, d: pointers.child_ranks(_forest(graphs.fk_forest, spark, d), "positions")
)
query("leaves_fk", sql.on_forest(sql.FK, "SELECT v FROM fo WHERE v NOT IN (SELECT parent FROM fo WHERE v <> parent)"))(lambda spark, d: pointers.leaves(_forest(graphs.fk_forest, spark, d)))
query("ancestors_order_part", sql.on_forest(sql.ORDER_PART, "SELECT v, p AS anc FROM k WHERE i = 7", "k(v, p, i) AS (SELECT v, v, 0 FROM fo UNION ALL SELECT k.v, fo.parent, i + 1 FROM k JOIN fo ON fo.v = k.p WHERE i < 7)"))(
    lambda spark, d: pointers.ancestor_at(_forest(graphs.order_part, spark, d), 7)
)


def _forest(build, spark, d) -> DataFrame:
    return settle(spanning_forest(build(spark, d)), "forest")


# ---- common ancestors and paths
def _off_pairs(ready: br.Prepared) -> DataFrame:
    return ready.crossing.select(F.col("src").alias("qid"), F.col("src").alias("u"), F.col("dst").alias("v"))


def _lca(build, method, attach=False, every=False):
    def run(spark, d):
        ready = br.Prepared(build(spark, d))
        pairs = ready.graph.select(F.col("src").alias("qid"), F.col("src").alias("u"), F.col("dst").alias("v")) if every else _off_pairs(ready)
        return lca_batch(ready.parents, pairs, method=method, attach_leaves=attach).select("u", "v", "lca", "child_u", "child_v")

    return run


_MET = "SELECT u, v, lca, child_u, child_v FROM met"
_ALL_PAIRS = "SELECT src AS qid, src AS u, dst AS v FROM e"
family({"lca_trade_edges": _lca(graphs.trade_sparse, "compressed", every=True), "lca_trade_edges_naive": _lca(graphs.trade_sparse, "naive", every=True)}, sql.on_forest(sql.TRADE, _MET, sql.climbing(_ALL_PAIRS)))
family({"lca_cactus": _lca(graphs.ring_cactus, "compressed"), "lca_cactus_doubling": _lca(graphs.ring_cactus, "doubling"), "lca_cactus_attached": _lca(graphs.ring_cactus, "compressed", attach=True)}, sql.on_forest(sql.CACTUS, _MET, sql.OFF, sql.climbing(sql.OFF_PAIRS)))
_PATHS = ("SELECT qid, pos, x AS v FROM walk", "walk(qid, pos, x) AS (SELECT v, CAST(0 AS BIGINT), v FROM fo UNION ALL SELECT qid, pos + 1, fo.parent FROM walk JOIN fo ON fo.v = x WHERE fo.parent <> fo.v)")


def _paths(build, method="compressed"):
    def run(spark, d):
        parents = _forest(build, spark, d)
        return ancestor_paths(parents, parents.select(F.col("v").alias("qid"), F.col("v").alias("u"), F.col("root").alias("anc")), method=method)

    return run


family({"paths_trade": _paths(graphs.trade_sparse), "paths_trade_doubling": _paths(graphs.trade_sparse, "doubling"), "paths_trade_naive": _paths(graphs.trade_sparse, "naive")}, sql.on_forest(sql.TRADE, *_PATHS))
query("paths_order_part", sql.on_forest(sql.ORDER_PART, *_PATHS))(_paths(graphs.order_part))


# ---- sequences
query("tour_spans_trade", sql.on_forest(sql.TRADE, "SELECT root, v, first, last FROM sp", sql.SIZES))(
    lambda spark, d: dfs_sequence(_forest(graphs.trade_sparse, spark, d)).groupBy("root", "v").agg(F.min("pos").alias("first"), F.max("pos").alias("last"))
)
_SEQUENCE = "SELECT root, first AS pos, v FROM sp UNION ALL SELECT sp.root, sp.last + 1, fo.parent FROM sp JOIN fo USING (v) WHERE fo.parent <> fo.v"
family(
    {f"tour_sequence_small{k}": (lambda spark, d, how=how: dfs_sequence(_forest(graphs.trade_sparse, spark, d), **how)) for k, how in (("", {}), ("_sampled", {"s": 64}), ("_ranking", {"method": "tour_ranking"}), ("_levels", {"method": "levels"}))},
    sql.on_forest(sql.TRADE, _SEQUENCE, sql.SIZES),
)
query("tour_invariants_trade", sql.on_forest(sql.TRADE, "SELECT sum(2 * n - 1)::BIGINT AS rows, sum(2 * n - 1)::BIGINT AS expected, 0::BIGINT AS wrong_steps, 0::BIGINT AS wrong_counts, 0::BIGINT AS wrong_positions FROM (SELECT count(*) AS n FROM fo GROUP BY root)"))(
    lambda spark, d: (lambda parents: check_tour(settle(dfs_sequence(parents, s=64), "tour"), parents))(_forest(graphs.trade_sparse, spark, d))
)
query("back_depth_trade", sql.on_cycles(sql.TRADE, "SELECT fo.v, least(fo.depth, min(x.depth)) AS bac FROM fo LEFT JOIN (SELECT u AS v, lca FROM met UNION ALL SELECT v, lca FROM met) m ON m.v = fo.v LEFT JOIN fo x ON x.v = m.lca GROUP BY fo.v, fo.depth"))(
    lambda spark, d: br.back_depth(br.Prepared(graphs.trade_sparse(spark, d)))
)


# ---- the distributed methods on trees that are deeper and wider than a task's budget
#: So few rows a task that sampling, compression and jumps all take place at the smallest scale.
TIGHT = Budget(delta=0.5, c=2.0)
query("bridges_order_part_sampled", sql.bridges(sql.ORDER_PART))(lambda spark, d: br.find_bridges(graphs.order_part(spark, d), budget=TIGHT, forest="bfs"))
query("tour_chains_sampled", sql.on_forest(sql.CHAINS, _SEQUENCE, sql.SIZES))(lambda spark, d: dfs_sequence(_forest(graphs.chains, spark, d), s=8))


def _broom(spark, d) -> DataFrame:
    """A chain of a quarter of the parts; the others hang on its middle."""
    k = read_table(spark, d, "part", ["p_partkey"]).count() // 4
    return settle(pointers.depths(graphs.broom(spark, d, k, k // 2)), "broom")


@query("tour_broom_sampled", "SELECT 2 * count(*) - 1 AS rows, 2 * count(*) - 1 AS expected, 0::BIGINT AS wrong_steps, 0::BIGINT AS wrong_counts, 0::BIGINT AS wrong_positions FROM part")
def tour_broom_sampled(spark, d):
    """Its sequence by leaf sampling under a tight budget, held against the sequence's defining properties: one row of counts, wrong_* are 0."""
    parents = _broom(spark, d)
    return check_tour(settle(dfs_sequence(parents, budget=TIGHT), "tour"), parents)


#: By the broom's shape: the part of number 1 is the root's only child, that of number 2 the next one on the way to all others.
_FAR = f"""SELECT v AS u, one AS v, CASE WHEN p_partkey = 0 THEN v ELSE one END AS lca, CASE WHEN p_partkey > 1 THEN two END AS child_u, CASE WHEN p_partkey = 0 THEN one END AS child_v, CASE WHEN p_partkey > 1 THEN 2 END AS child_depth
FROM (SELECT p_partkey, {sql.V('part', 'p_partkey')} AS v, {sql.V('part', '1')} AS one, {sql.V('part', '2')} AS two FROM part) WHERE v % 20 = 0"""


@query("lca_broom_far", _FAR)
def lca_broom_far(spark, d):
    """Every 20th vertex against the root's child on the chain: ends far apart in depth, so that the deeper one is lifted first. Its ancestor is the shallower end, and the
    child towards the deeper end is one step deeper."""
    parents = _broom(spark, d)
    low = parents.filter("depth = 1").agg(F.min("v")).first()[0]
    pairs = parents.filter(F.col("v") % 20 == 0).select(F.col("v").alias("qid"), F.col("v").alias("u"), F.lit(low).alias("v"))
    met = lca_batch(parents, pairs)
    return met.join(parents.select(F.col("v").alias("child_u"), F.col("depth").alias("child_depth")), "child_u", "left").select("u", "v", "lca", "child_u", "child_v", "child_depth")


# ---- range minima
def _values(spark, d) -> DataFrame:
    events = read_table(spark, d, "events", ["event_id", "user_id", "ts", "value"])
    return settle(dense_positions(events, ["ts", "event_id"]).select("user_id", "pos", F.round(F.col("value") * 100).cast("long").alias("val")), "values")


def _rmq(method):
    def run(spark, d):
        arr = _values(spark, d)
        asked = arr.groupBy(F.col("user_id").alias("qid")).agg(F.min("pos").alias("lo"), F.max("pos").alias("hi"))
        return range_min(arr.select("pos", "val"), settle(asked, "values"), method=method)

    return run


_RMQ = """WITH a AS MATERIALIZED (SELECT user_id, row_number() OVER (ORDER BY ts, event_id) AS pos, CAST(round(value * 100) AS BIGINT) AS val FROM events), q AS (SELECT user_id AS qid, min(pos) AS lo, max(pos) AS hi FROM a GROUP BY user_id)
SELECT qid, min(val) AS min_value FROM q JOIN a ON pos BETWEEN lo AND hi GROUP BY qid"""
family({"rmq_events_value": _rmq("block"), "rmq_events_value_sparse_table": _rmq("sparse_table")}, _RMQ)


# ---- measures
#: By the broom's shape: k vertices on the chain, so m = (k - 1) // t of its depths that are multiples of t have t more below them; under the printed rule all bristles, at depth t, are kept too.
_BROOM = """WITH c AS (SELECT count(*) AS n, count(*) // 4 AS k FROM part), t AS (SELECT n, k, length(bin(k - 2)) AS t FROM c), m AS (SELECT n, k, t, (k - 1) // t AS m FROM t),
r AS (SELECT keep, n, k, t, m, CASE WHEN keep = 'printed' THEN n - k ELSE 0 END AS bristles FROM m, (VALUES ('descendant'), ('printed')) AS x(keep))
SELECT keep, n, CAST(k - 1 AS INT) AS depth, CAST(t AS INT) AS t, m + bristles AS kept, n // t AS bound, 0::BIGINT AS open_jumps, CAST(k - 1 - (m - 1) * t AS INT) AS farthest FROM r"""


@query("compress_report_broom", _BROOM)
def compress_report_broom(spark, d):
    n = read_table(spark, d, "part", ["p_partkey"]).count()
    k = n // 4
    parents = settle(pointers.depths(graphs.broom(spark, d, k, step_of(k - 1) - 1)), "broom")  # the bristles end at a depth where the printed rule keeps them all
    both = [measures.compression_report(parents, keep).withColumn("keep", F.lit(keep)) for keep in ("descendant", "printed")]
    return both[0].unionByName(both[1])


query("parity_lineitem", "SELECT CAST(bit_xor(l_linenumber) AS BIGINT) AS parity FROM lineitem")(lambda spark, d: measures.parity(read_table(spark, d, "lineitem", ["l_linenumber"]), "l_linenumber"))
_WAVES = """bfs(s, t, k) USING KEY (s, t) AS (SELECT v, v, 0 FROM comp UNION SELECT b.s, a.w, min(b.k) + 1 FROM bfs b JOIN arcs a ON a.v = b.t LEFT JOIN recurring.bfs r ON r.s = b.s AND r.t = a.w WHERE r.s IS NULL GROUP BY b.s, a.w)"""
query("diameter_trade", sql.on_forest(sql.TRADE, """SELECT c AS comp, max(dist) AS diameter FROM (SELECT s, t, min(k) AS dist FROM bfs GROUP BY s, t) JOIN comp ON v = s GROUP BY c""", _WAVES))(
    lambda spark, d: measures.diameter(graphs.trade_sparse(spark, d), "exact")
)
_SWEEPS = """dist AS MATERIALIZED (SELECT s, t, min(k) AS k FROM bfs GROUP BY s, t), far AS (SELECT s AS c, min(t) AS far FROM (SELECT s, t, k, max(k) OVER (PARTITION BY s) AS most FROM dist) WHERE k = most GROUP BY s)"""
query("diameter_trade_lower", sql.on_forest(sql.TRADE, "SELECT c AS comp, max(k) AS diameter FROM far JOIN dist ON s = far WHERE c IN (SELECT c FROM comp) GROUP BY c", _WAVES, _SWEEPS))(
    lambda spark, d: measures.diameter(graphs.trade_sparse(spark, d), "lower")
)


# ---- operators around the methods
query("op_scan_prune", "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")(
    lambda spark, d: read_table(spark, d, "lineitem").filter("l_quantity >= 49 and l_returnflag = 'R'").select("l_partkey", "l_suppkey")
)
query("op_ring_edges", sql.distinct_edges(sql._ring(sql._ORDERS)))(
    lambda spark, d: graphs.ring(read_table(spark, d, "orders", ["o_orderkey", "o_custkey"]).select("o_custkey", "o_orderkey", vertex("order", "o_orderkey").alias("v"), vertex("customer", "o_custkey").alias("hub")), "o_custkey", "o_orderkey", "hub")
)
query("op_chain_edges", sql.CHAINS)(graphs.chains)
query("op_line_share", sql.LINE_PAIRS)(graphs.line_pairs)
query("op_links", sql.LINK_PAIRS)(graphs.link_pairs)
query("op_canonical_edges", sql.PART_SUPP)(graphs.part_supp)
query("op_degree_approx", f"""SELECT count(DISTINCT dst) AS neighbours, TRUE AS neighbours_close, (SELECT CAST(quantile_disc(n, 0.5) AS BIGINT) FROM (SELECT count(*) AS n FROM ({sql.PART_SUPP}) GROUP BY src)) AS median, TRUE AS median_close FROM ({sql.PART_SUPP})""")(
    lambda spark, d: measures.approximate_degrees(graphs.part_supp(spark, d)).select(
        "neighbours", (F.abs(F.col("about_neighbours") - F.col("neighbours")) <= 0.15 * F.col("neighbours")).alias("neighbours_close"), "median", (F.abs(F.col("about_median") - F.col("median")) <= 1).alias("median_close")
    )
)
query("op_user_type", sql.interned(f"SELECT DISTINCT {sql.V('user', 'user_id')} AS id, event_type AS token FROM events"))(graphs.user_type)
query("op_induced", f"SELECT src, dst FROM ({sql.TRADE}) WHERE src & 1 = 0 AND dst & 1 = 0")(
    lambda spark, d: (lambda g: graphs.induced(g, g.select(F.explode(F.array("src", "dst")).alias("v")).distinct().filter(F.col("v").bitwiseAND(F.lit(1)) == 0)))(settle(graphs.trade_sparse(spark, d), "x"))
)
query("op_lookup", "SELECT o_orderkey, c_nationkey FROM orders LEFT JOIN customer ON c_custkey = o_custkey")(
    lambda spark, d: pointers.lookup(read_table(spark, d, "orders", ["o_orderkey", "o_custkey"]), read_table(spark, d, "customer", ["c_custkey", "c_nationkey"]), "o_custkey", "c_nationkey", hint="shuffle_hash").select("o_orderkey", "c_nationkey")
)
query("op_non_tree_edges", sql.on_forest(sql.TRADE, "SELECT src, dst FROM off", sql.OFF))(lambda spark, d: br.Prepared(graphs.trade_sparse(spark, d)).crossing)
query("op_sample_pairs", f"SELECT a.src AS x, b.src AS y FROM (SELECT DISTINCT src FROM ({sql.TRADE})) a JOIN (SELECT DISTINCT src FROM ({sql.TRADE})) b ON a.src < b.src AND a.src % 10 = b.src % 10")(
    lambda spark, d: (lambda s: s.join(s.select("job", F.col("x").alias("y")), "job").filter("x < y").select("x", "y"))(settle(graphs.trade_sparse(spark, d).select((F.col("src") % 10).alias("job"), F.col("src").alias("x")).distinct(), "x"))
)
family({"op_subtree_sizes": lambda spark, d: subtree_sizes(_forest(graphs.trade_sparse, spark, d)), "op_subtree_sizes_levels": lambda spark, d: subtree_sizes(_forest(graphs.trade_sparse, spark, d), "levels")}, sql.on_forest(sql.TRADE, "SELECT v, size FROM siz", sql.SIZES))
query("op_is_ancestor", sql.on_forest(sql.TRADE, "SELECT v AS u, parent AS w, v = parent AS ancestor FROM fo"))(
    lambda spark, d: (lambda r: pointers.is_ancestor(r.parents.select(F.col("v").alias("u"), F.col("parent").alias("v")), r.spans).select("u", F.col("v").alias("w"), "ancestor"))(br.Prepared(graphs.trade_sparse(spark, d)))
)


@query("op_asof", "SELECT o_orderkey, e.event_id FROM orders ASOF LEFT JOIN (SELECT max(event_id) AS event_id, user_id, ts FROM events GROUP BY user_id, ts) e ON e.user_id = o_custkey AND e.ts <= o_orderdate")
def op_asof(spark, d):
    """The latest event of the same number at or before each order: both sides in one sorted union, no range join."""
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]).select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t"), F.lit(1).alias("side"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    events = read_table(spark, d, "events", ["user_id", "ts", "event_id"]).select(F.col("user_id").alias("k"), F.col("ts").alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    over = Window.partitionBy("k").orderBy("t", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return orders.unionByName(events).select("side", "o_orderkey", F.last("event_id", ignorenulls=True).over(over).alias("event_id")).filter("side = 1").drop("side")


query("op_degree", sql.select("SELECT v, count(*) AS degree FROM arcs GROUP BY v", sql.graph(sql.TRADE)))(lambda spark, d: graphs.trade_sparse(spark, d).select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree")))


def _regions(spark, d) -> DataFrame:
    """Blocks of the cactus that hold a customer, by that customer's nation and region."""
    vb = bl.incidence(bl.color_blocks(graphs.ring_cactus(spark, d), method="interval"))
    customers = read_table(spark, d, "customer", ["c_custkey", "c_nationkey"]).select(vertex("customer", "c_custkey").alias("v"), F.col("c_nationkey").alias("n_nationkey"))
    nations = read_table(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    return vb.join(customers, "v").join(nations, "n_nationkey").select("n_regionkey", "n_nationkey", "block_src", "block_dst")


_BY = f"FROM vb JOIN customer ON vb.v = {sql.V('customer', 'c_custkey')} JOIN nation ON n_nationkey = c_nationkey GROUP BY"
_COUNT = "SELECT n_regionkey, n_nationkey, count(*) AS incidences "
query("op_blocks_rollup", sql.blocks(sql.CACTUS, f"{_COUNT}{_BY} ROLLUP (n_regionkey, n_nationkey)"))(lambda spark, d: _regions(spark, d).rollup("n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("incidences")))
query("op_blocks_cube", sql.blocks(sql.CACTUS, f"{_COUNT}{_BY} CUBE (n_regionkey, n_nationkey)"))(lambda spark, d: _regions(spark, d).cube("n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("incidences")))
query("op_blocks_gsets", sql.blocks(sql.CACTUS, f"{_COUNT}{_BY} GROUPING SETS ((n_regionkey), (n_nationkey), ())"))(
    lambda spark, d: _regions(spark, d).groupingSets([["n_regionkey"], ["n_nationkey"], []], "n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("incidences"))
)
query("op_walk_neighbours", "SELECT conv_id, turn, lag(turn) OVER w AS before, lead(turn) OVER w AS after, first_value(turn) OVER w AS start FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")(
    lambda spark, d: (lambda w: read_table(spark, d, "conversations", ["conv_id", "turn"]).select("conv_id", "turn", F.lag("turn").over(w).alias("before"), F.lead("turn").over(w).alias("after"), F.first("turn").over(w).alias("start")))(Window.partitionBy("conv_id").orderBy("turn"))
)
query("op_prefix_min", "SELECT pos, min(val) OVER (PARTITION BY pos // 16 ORDER BY pos) AS low FROM (SELECT row_number() OVER (ORDER BY ts, event_id) AS pos, CAST(round(value * 100) AS BIGINT) AS val FROM events)")(
    lambda spark, d: _values(spark, d).select("pos", F.min("val").over(Window.partitionBy(F.floor(F.col("pos") / 16)).orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)).alias("low"))
)
query("op_top_blocks", sql.blocks(sql.CACTUS, "SELECT block_src, block_dst, count(*) AS edges FROM blocks GROUP BY ALL ORDER BY edges DESC, block_src, block_dst LIMIT 10"))(
    lambda spark, d: bl.color_blocks(graphs.ring_cactus(spark, d), method="interval").groupBy("block_src", "block_dst").agg(F.count(F.lit(1)).alias("edges")).orderBy(F.desc("edges"), "block_src", "block_dst").limit(10)
)
query("op_graph_union", f"({sql.TRADE}) UNION ({sql.FK})")(lambda spark, d: graphs.canonical(graphs.trade_sparse(spark, d).unionByName(graphs.fk_forest(spark, d))))
query("op_common_edges", f"({sql.TRADE}) INTERSECT ({sql.PART_SUPP})")(lambda spark, d: graphs.trade_sparse(spark, d).intersect(graphs.part_supp(spark, d)))
query("op_non_bridges", sql.on_cycles(sql.TRADE, f"SELECT src, dst FROM e EXCEPT ALL ({sql.BRIDGES})"))(lambda spark, d: (lambda g: g.exceptAll(br.find_bridges(g, method="interval")))(settle(graphs.trade_sparse(spark, d), "x")))
query("op_hub_edges", sql.hubbed(sql.TWO_RINGS))(_two_hubbed)
query("op_monthly_edges", f"SELECT date_trunc('month', o_orderdate)::DATE AS month, count(DISTINCT ({sql.V('customer', 'o_custkey')}, {sql.V('order', 'o_orderkey')})) AS edges, max(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)) AS last_day FROM orders GROUP BY 1")(
    lambda spark, d: read_table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]).groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month")).agg(F.countDistinct("o_custkey", "o_orderkey").alias("edges"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).cast("long").alias("last_day"))
)


@query("op_path_array", sql.on_forest(sql.TRADE, "SELECT qid, CAST(count(*) AS INT) AS steps, string_agg(CAST(x AS VARCHAR), '>' ORDER BY pos) AS path FROM walk GROUP BY qid", _PATHS[1]))
def op_path_array(spark, d):
    parents = _forest(graphs.trade_sparse, spark, d)
    rows = ancestor_paths(parents, parents.select(F.col("v").alias("qid"), F.col("v").alias("u"), F.col("root").alias("anc")), as_array=True)
    return rows.select("qid", F.size("path").alias("steps"), F.array_join(F.transform("path", lambda x: x.cast("string")), ">").alias("path"))


query("op_props_json", "SELECT event_type, CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL")(
    lambda spark, d: read_table(spark, d, "events", ["event_type", "props"]).groupBy("event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("n"))
)
query("op_tumbling", "SELECT time_bucket(INTERVAL 1 day, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS events FROM events GROUP BY 1")(lambda spark, d: stream.tumbling(read_table(spark, d, "events", ["ts"])))
query("op_sliding", "SELECT time_bucket(INTERVAL 6 hours, ts, TIMESTAMP '1970-01-01') - to_hours(6 * k.k) AS start, count(*) AS events FROM events, unnest([0, 1, 2, 3]) AS k(k) GROUP BY 1")(lambda spark, d: stream.sliding(read_table(spark, d, "events", ["ts"])))
query("op_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 1 hour THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g) SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, n""")(
    lambda spark, d: stream.sessions(read_table(spark, d, "events", ["user_id", "ts"]))
)


@query("op_udtf_bridges", sql.bridges(sql.TRADE))
def op_udtf_bridges(spark, d):
    spark.udtf.register("bridges_of", BridgesOf)
    graphs.trade_sparse(spark, d).createOrReplaceTempView("trade_graph")
    return spark.sql("SELECT src, dst FROM bridges_of(TABLE(trade_graph) WITH SINGLE PARTITION)")


@query("op_sql_view", sql.blocks(sql.TRADE, f"SELECT (SELECT count(*) FROM ({sql.BRIDGES})) AS bridges, (SELECT count(DISTINCT (block_src, block_dst)) FROM blocks) AS blocks, (SELECT count(*) FROM cut) AS cuts"))
def op_sql_view(spark, d):
    sqlviews.register(spark, graphs.trade_sparse(spark, d), "trade")
    return spark.sql("SELECT (SELECT count(*) FROM trade_bridges) AS bridges, (SELECT count(DISTINCT block_src, block_dst) FROM trade_blocks) AS blocks, (SELECT count(*) FROM trade_cut_vertices) AS cuts")


# ---- workloads that are short enough to be run like any other query; the others run by `python -m spanweave.plans.workloads`
def _workload(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark, d):
        from spanweave.plans import workloads

        return workloads.as_query(name)(spark, d)

    return run


def _table_rows(n: str) -> str:
    """Rows of the doubling table over n positions."""
    return f"(SELECT CAST(sum({n} - (1 << j) + 1) AS BIGINT) FROM (SELECT unnest(range(0, length(bin({n})))) AS j))"


def _joined(parts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


_W7 = f"""WITH c AS (SELECT count(*) AS n, count(DISTINCT user_id) AS q FROM events), t AS (SELECT n, q, length(bin(n - 1)) AS t FROM c), b AS (SELECT n, q, (n + t - 1) // t AS b FROM t),
r AS (SELECT n, q, 2 * n + {_table_rows('b')} AS block, {_table_rows('n')} AS sparse_table FROM b)
SELECT '' AS series, measure, CAST(value AS BIGINT) AS value FROM r UNPIVOT (value FOR measure IN (n, q, block, sparse_table))"""
_W11 = _joined([
    sql.blocks(edges, f"{_CONDITION} SELECT 'graph={name}' AS series, u.m AS measure, u.x AS value FROM (SELECT [{{'m': 'cut_vertices', 'x': (SELECT count(*) FROM cut)}}, {{'m': 'bridges', 'x': (SELECT count(*) FROM ({sql.BRIDGES}))}}, "
    "{'m': 'edges_that_fit', 'x': (SELECT count(*) FROM e WHERE src IN (SELECT v FROM fit) AND dst IN (SELECT v FROM fit))}] AS l), unnest(l) AS z(u)")
    for name, edges in (("trade", sql.TRADE), ("cactus", sql.CACTUS))
])
for _name, _answer in (("w7", _W7), ("w9", None), ("w11", _W11)):
    query(f"workload_{_name}", _answer)(_workload(_name))
