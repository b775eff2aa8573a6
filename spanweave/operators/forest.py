"""Rooted spanning forests: (v, parent, root, depth), a root pointing to itself."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.ledger import Budget, settle
from spanweave.operators.arrays import ARRAY_ROWS, in_one, in_packs, packed, rooted_forest
from spanweave.operators.components import both_ways, connected_components, contracted, hooked
from spanweave.schema import Failed

_PARENTS = "v long, parent long, root long, depth int"


def spanning_forest(edges: DataFrame, vertices: DataFrame | None = None, method: str = "auto", local_rows: int | None = None, budget: Budget | None = None, max_rounds: int = 2000, seed: int = 0) -> DataFrame:
    """A spanning forest of (src, dst), isolated `vertices` included.

    bfs: breadth-first from the least id of each component, parents the least neighbour one level up (the canonical forest; depth at most the
    diameter, a round a level). auto: the same forest, components of up to `local_rows` edges (default: what `budget` allows a task, N**delta; ARRAY_ROWS without one) each solved in one task, many small ones together, the others by rounds. hook: tree edges of
    least-edge hooking, rooted by ranking their tour, logarithmic rounds and any depth. contract: tree edges of budgeted leader contraction, rooted likewise."""
    edges = edges.filter("src <> dst").select("src", "dst").distinct()
    if method == "auto":
        edges = settle(edges, "forest", 0)
        found = _auto(edges, local_rows if local_rows is not None else budget.local(edges.count()) if budget else ARRAY_ROWS, max_rounds)
    elif method == "bfs":
        found = _bfs(edges, max_rounds)
    else:
        from spanweave.operators.tour import rooted

        label, tree = hooked(edges) if method == "hook" else contracted(edges, budget or Budget(), seed)
        found = rooted(tree, label.select("comp").distinct().select(F.col("comp").alias("root")))
    if vertices is None:
        return found
    lone = vertices.select("v").distinct().join(found.select("v"), "v", "left_anti")
    return found.unionByName(lone.select("v", F.col("v").alias("parent"), F.col("v").alias("root"), F.lit(0).alias("depth")))


def _auto(edges: DataFrame, local_rows: int, max_rounds: int) -> DataFrame:
    if edges.count() <= local_rows:
        return in_one(edges, rooted_forest, _PARENTS)
    label = settle(connected_components(edges, method="local"), "forest", 0)
    held = settle(edges.join(label.select(F.col("v").alias("src"), "comp"), "src"), "forest", 0)
    size = held.groupBy("comp").agg(F.count(F.lit(1)).alias("n"))
    large = settle(size.filter(F.col("n") > local_rows).select("comp"), "forest", 0)
    small = held.join(large, "comp", "left_anti")
    small = in_packs(small.select("src", "dst", "comp"), packed("comp", held.count()), held.count(), rooted_forest, _PARENTS)
    if large.isEmpty():
        return small
    many = held.join(large, "comp", "left_semi")
    return small.unionByName(_bfs(many.select("src", "dst"), max_rounds, large.select(F.col("comp").alias("v"))))


def breadth_first_from(edges: DataFrame, roots: DataFrame, max_rounds: int = 2000) -> DataFrame:
    """The forest of `bfs` where the least id of each component is known: `roots` (v)."""
    return _bfs(edges, max_rounds, roots)


def _bfs(edges: DataFrame, max_rounds: int, roots: DataFrame | None = None) -> DataFrame:
    """One frontier for all components, from `roots` (v) where they are known; each level is written apart, so a round reads only the frontier, its arcs and the ids seen."""
    arcs = settle(both_ways(edges), "forest", 0)
    roots = roots if roots is not None else connected_components(edges, method="local").select(F.col("comp").alias("v")).distinct()
    front = settle(roots.select("v", F.col("v").alias("parent"), F.col("v").alias("root"), F.lit(0).alias("depth")), "forest", 0)
    seen = [front]
    for turn in range(1, max_rounds):
        before = seen[-1].select("v") if turn == 1 else seen[-1].select("v").unionByName(seen[-2].select("v"))
        # A neighbour of the frontier lies in the frontier's level, the one before or the one after: two levels are all that need be known.
        step = arcs.join(front.select("v", "root"), "v").groupBy(F.col("w").alias("v")).agg(F.min("v").alias("parent"), F.min("root").alias("root"))
        front = settle(step.join(before, "v", "left_anti").select("v", "parent", "root", F.lit(turn).alias("depth")), "forest", turn)
        if front.isEmpty():
            break
        seen.append(front)
        if len(seen) > 48:  # keep the plan of the union short
            merged = seen[0]
            for part in seen[1:-2]:
                merged = merged.unionByName(part)
            seen = [settle(merged, "forest", turn), *seen[-2:]]
    else:
        raise Failed(f"the forest is deeper than {max_rounds}")
    out = seen[0]
    for part in seen[1:]:
        out = out.unionByName(part)
    return out


def sparsified(edges: DataFrame, first: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(kept edges, dropped edges): a breadth-first forest of the graph and one of what remains. Blocks of the kept edges are those of the graph; a
    dropped edge has the colour of its deeper endpoint's parent edge in `first`."""
    tree = first.filter("v <> parent").select(F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst"))
    rest = settle(edges.select("src", "dst").join(tree, ["src", "dst"], "left_anti"), "sparsify", 0)
    second = spanning_forest(rest).filter("v <> parent").select(F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst"))
    kept = settle(tree.unionByName(second), "sparsify", 1)
    return kept, rest.join(kept, ["src", "dst"], "left_anti")


def tree_edges(parents: DataFrame) -> DataFrame:
    return parents.filter("v <> parent").select(F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst"))


