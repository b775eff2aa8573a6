"""Compressed trees: one vertex in about t of a tree, with jumps of t steps; and jump tables over them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.ledger import settle
from spanweave.operators.pointers import ancestor_at, doubling, hop


def step_of(depth: int) -> int:
    """Steps of a jump: the depth's binary logarithm, rounded up, at least 1."""
    return max(1, (depth - 1).bit_length()) if depth > 0 else 1


@dataclass
class Compressed:
    """`vertices` (v, jump_parent, cdepth, depth) of the kept vertices, the step t, the forest's depth."""

    vertices: DataFrame
    t: int
    depth: int


def compress_tree(parents: DataFrame, keep: str = "descendant") -> Compressed:
    """Kept vertices of a forest (v, parent, root, depth).

    descendant: those that have a descendant exactly t below, at depths that are multiples of t; found as images of the t-th ancestor, so there are
    at most n/t of them, roots of shallow trees apart. printed: all at such depths with t or more levels below in the tree as a whole; that many can be a constant share of all vertices
    (kept for comparison). Roots are always kept."""
    deepest = parents.agg(F.coalesce(F.max("depth"), F.lit(0))).first()[0]
    t = step_of(deepest)
    base = parents.filter((F.col("depth") % t == 0) & (F.col("depth") >= t)).select("v")
    jumps = ancestor_at(parents, t, base)
    if keep == "descendant":
        chosen = jumps.select(F.col("anc").alias("v")).distinct()
    elif keep == "printed":
        bottom = parents.groupBy("root").agg(F.max("depth").alias("_d"))
        chosen = parents.join(bottom, "root").filter((F.col("depth") % t == 0) & (F.col("depth") + t <= F.col("_d"))).select("v")
    else:
        raise ValueError(keep)
    kept = chosen.unionByName(parents.filter("v = parent").select("v")).distinct()
    placed = hop(hop(kept, parents, "v", {"depth": "depth"}), jumps, "v", {"_j": "anc"})
    out = placed.select("v", F.coalesce("_j", "v").alias("jump_parent"), (F.col("depth") / t).cast("int").alias("cdepth"), "depth")
    return Compressed(settle(out, "compress"), t, deepest)


def jump_tables(tree: Compressed) -> DataFrame:
    """(j, v, anc, anc_depth): the 2**j-th ancestors in the compressed tree, up to the first j that takes all to their roots."""
    deepest = tree.vertices.agg(F.coalesce(F.max("cdepth"), F.lit(0))).first()[0]
    level = tree.vertices.select("v", F.col("jump_parent").alias("anc"))
    depth_of = tree.vertices.select("v", "depth")
    out = None
    for j in range(deepest.bit_length() + 1):
        row = hop(level, depth_of, "anc", {"anc_depth": "depth"}).select(F.lit(j).alias("j"), "v", "anc", "anc_depth")
        out = row if out is None else out.unionByName(row)
        if j < deepest.bit_length():
            level = settle(hop(level, level, "anc", {"_n": "anc"}, name="v").select("v", F.col("_n").alias("anc")), "jump tables", j)
    return settle(out, "jump tables")


def levels(tables: DataFrame) -> int:
    return tables.agg(F.coalesce(F.max("j"), F.lit(0))).first()[0]


def nearest_kept(parents: DataFrame, tree: Compressed) -> DataFrame:
    """(v, kept): the nearest kept ancestor of every vertex, itself if kept; one row a vertex, within 2t steps."""
    marked = hop(parents.select("v", "parent"), tree.vertices.select("v", F.lit(1).alias("one")), "v", {"_one": "one"})
    start = marked.select("v", F.when(F.col("_one").isNotNull(), F.col("v")).otherwise(F.col("parent")).alias("ptr"))
    return doubling(start, phase="nearest kept").withColumnRenamed("ptr", "kept")
