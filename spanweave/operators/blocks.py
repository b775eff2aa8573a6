"""Biconnected blocks: a colour for every edge, the least edge of its block; and what follows from them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.graphs import canonical
from spanweave.ledger import settle
from spanweave.operators.bridges import Prepared, _local_solver
from spanweave.operators.components import connected_components
from spanweave.operators.forest import sparsified, spanning_forest
from spanweave.operators.paths import ancestor_paths
from spanweave.operators.positions import dense_positions
from spanweave.operators.pointers import hop


def auxiliary_graph(ready: Prepared, aux: str = "tree", method: str = "paper") -> tuple[DataFrame, DataFrame]:
    """(vertices (v), edges (src, dst)) whose components are the blocks.

    tree: every non-root vertex stands for its parent edge; it is linked to its parent where its subtree reaches above the parent, and the ends of an edge off the forest are linked where neither is
    an ancestor of the other. all_edges: every edge off the forest is a vertex too (a negative id), tied to the parent edge of its deeper end. With
    method="interval" both tests read tour positions instead of depths of common ancestors."""
    if method == "interval":
        inner = ready.reached.filter("v <> parent").select("v")
        up = hop(ready.reached.filter("depth > 1"), ready.reached, "parent", {"pf": "first", "pl": "last"}, name="v").filter("low < pf or high > pl")
        # The edges of the forest join ancestors, so they need not be taken out.
        both = hop(hop(ready.graph, ready.reached, "src", {"sf": "first", "sl": "last"}, name="v"), ready.reached, "dst", {"df": "first", "dl": "last"}, name="v")
        across = both.filter("not (sf <= df and dl <= sl) and not (df <= sf and sl <= dl)").select("src", "dst")
    else:
        inner = ready.parents.filter("v <> parent").select("v")
        up = ready.lows.filter("low < depth - 1")
        across = ready.met.filter("lca <> u and lca <> v").select(F.col("u").alias("src"), F.col("v").alias("dst"))
    links = up.select(F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst")).unionByName(across.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))
    if aux == "tree":
        return inner, links
    from spanweave.operators.positions import dense_positions

    numbered = dense_positions(ready.crossing, ["src", "dst"], "number")
    depth = ready.parents.select("v", "depth")
    ends = hop(hop(numbered, depth, "src", {"ds": "depth"}, name="v"), depth, "dst", {"dd": "depth"}, name="v")
    tie = ends.select((-F.col("number")).alias("src"), F.when(F.col("ds") >= F.col("dd"), F.col("src")).otherwise(F.col("dst")).alias("dst"))
    return inner.unionByName(tie.select(F.col("src").alias("v"))), links.unionByName(tie)


def color_blocks(edges: DataFrame, method: str = "paper", ready: Prepared | None = None, aux: str = "tree", components: str = "local", presparsify: bool = False, **options) -> DataFrame:
    """(src, dst, block_src, block_dst): every edge with the least edge of its block.

    paper: components of the auxiliary graph by back-depths. interval: the same without common ancestors. local: one task. `aux="all_edges"` takes the larger auxiliary graph.
    `presparsify` works on two breadth-first forests (at most 2n edges); a dropped edge has the colour of its deeper end's parent edge."""
    if method == "local":
        return _local_solver(edges).select("src", "dst", "block_src", "block_dst")
    dropped = None
    if presparsify:
        graph = settle(canonical(edges), "normalise")
        first = settle(spanning_forest(graph), "sparsify")
        kept, dropped = sparsified(graph, first)
        ready = Prepared(kept, parents_given=first, **options)
    ready = ready or Prepared(edges, **options)
    inner, links = auxiliary_graph(ready, aux, method)
    color = settle(connected_components(links, inner, method=components), "colors")
    depth = (ready.reached if method == "interval" else ready.parents).select("v", "depth")
    every = ready.graph if dropped is None else ready.graph.unionByName(dropped)
    ends = hop(hop(every, depth, "src", {"ds": "depth"}, name="v"), depth, "dst", {"dd": "depth"}, name="v")
    deeper = ends.select("src", "dst", F.when(F.col("ds") >= F.col("dd"), F.col("src")).otherwise(F.col("dst")).alias("v"))
    colored = settle(deeper.join(color, "v").select("src", "dst", "comp"), "colors")
    name = colored.groupBy("comp").agg(F.min(F.struct("src", "dst")).alias("least"))
    return colored.join(name, "comp").select("src", "dst", F.col("least.src").alias("block_src"), F.col("least.dst").alias("block_dst"))


def incidence(colors: DataFrame) -> DataFrame:
    """(v, block_src, block_dst): every vertex of every block, once."""
    return colors.select(F.explode(F.array("src", "dst")).alias("v"), "block_src", "block_dst").distinct()


def cut_vertices(colors: DataFrame) -> DataFrame:
    """(v, blocks): vertices on two blocks or more."""
    return incidence(colors).groupBy("v").agg(F.count(F.lit(1)).alias("blocks")).filter("blocks > 1")


def block_sizes(colors: DataFrame) -> DataFrame:
    """(block_src, block_dst, edges, vertices) of every block."""
    edges = colors.groupBy("block_src", "block_dst").agg(F.count(F.lit(1)).alias("edges"))
    return edges.join(incidence(colors).groupBy("block_src", "block_dst").agg(F.count(F.lit(1)).alias("vertices")), ["block_src", "block_dst"])


def block_cut_tree(colors: DataFrame) -> DataFrame:
    """(cut, block_src, block_dst): which cut vertex lies on which block."""
    return incidence(colors).join(cut_vertices(colors).select("v"), "v", "left_semi").select(F.col("v").alias("cut"), "block_src", "block_dst")


def is_biconnected(edges: DataFrame, vertices: DataFrame | None = None, method: str = "paper", **options) -> bool:
    """Whether the graph is connected and has one block: three vertices or more, no cut vertex."""
    how = {k: options.pop(k) for k in ("aux", "components", "presparsify") if k in options}
    ready = Prepared(edges, **options)
    ends = ready.graph.select(F.explode(F.array("src", "dst")).alias("v"))
    lone = vertices is not None and not vertices.select("v").join(ends, "v", "left_anti").isEmpty()
    if lone or ready.graph.limit(2).count() < 2:  # two edges have three ends
        return False
    colors = color_blocks(ready.graph, method, **how, **options) if how.get("presparsify") else color_blocks(edges, method, ready, **how)
    return colors.select("block_src", "block_dst").distinct().limit(2).count() == 1


def fundamental_cycles(edges: DataFrame, ready: Prepared | None = None, **options) -> DataFrame:
    """(cycle_src, cycle_dst, src, dst): the edges of the cycle that each edge off the forest closes, itself included; a basis of all cycles."""
    ready = ready or Prepared(edges, **options)
    met = ready.met
    sides = met.select(F.col("u").alias("cycle_src"), F.col("v").alias("cycle_dst"), F.col("u").alias("x"), "lca").unionByName(met.select(F.col("u").alias("cycle_src"), F.col("v").alias("cycle_dst"), F.col("v").alias("x"), "lca"))
    sides = settle(dense_positions(sides, ["cycle_src", "cycle_dst", "x"], "qid"), "cycles")
    rows = ancestor_paths(ready.parents, sides.select("qid", F.col("x").alias("u"), F.col("lca").alias("anc")))
    steps = hop(rows.join(sides.select("qid", "cycle_src", "cycle_dst", "lca"), "qid").filter("v <> lca"), ready.parents, "v", {"p": "parent"}, name="v")
    along = steps.select("cycle_src", "cycle_dst", F.least("v", "p").alias("src"), F.greatest("v", "p").alias("dst"))
    return along.unionByName(met.select(F.col("u").alias("cycle_src"), F.col("v").alias("cycle_dst"), F.col("u").alias("src"), F.col("v").alias("dst")))


def bridge_conditions(edges: DataFrame, colors: DataFrame) -> DataFrame:
    """Edges both of whose ends are cut vertices or have degree 1: necessary for a bridge, not sufficient (a triangle with a pendant at each corner)."""
    graph = canonical(edges)
    ends = graph.select(F.explode(F.array("src", "dst")).alias("v"))
    lone = ends.groupBy("v").count().filter("count = 1").select("v")
    fit = cut_vertices(colors).select("v").unionByName(lone).distinct()
    return graph.join(fit.select(F.col("v").alias("src")), "src", "left_semi").join(fit.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst")


