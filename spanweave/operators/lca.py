"""Batched lowest common ancestors with the two children toward the queries' ends."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.ledger import settle
from spanweave.operators.arrays import ARRAY_ROWS, PACK_ROWS, in_one, meetings
from spanweave.operators.compress import Compressed, compress_tree, jump_tables, levels, nearest_kept, step_of
from spanweave.operators.pointers import hop

#: Single steps that one round takes at once.
UNROLL = 4
#: Stands for the common ancestor of vertices in different trees while queries run; no vertex has this id.
APART = -1


@dataclass
class TreeIndex:
    """What batches over one forest share: parents, compressed tree, jump tables, nearest kept vertices."""

    parents: DataFrame
    tree: Compressed
    tables: DataFrame
    kept: DataFrame
    top: int

    @staticmethod
    def of(parents: DataFrame, keep: str = "descendant") -> TreeIndex:
        tree = compress_tree(parents, keep)
        tables = jump_tables(tree)
        return TreeIndex(parents, tree, tables, nearest_kept(parents, tree), levels(tables))


#: a, b: where the ends stand, the deeper first, da, db their depths, pa, pb where they stood a step before; a0, b0, da0, db0: where the near search began.
_STATE = ["qid", "u", "v", "a", "b", "da", "db", "pa", "pb", "a0", "b0", "da0", "db0", "swapped", "lca"]


def _start(parents: DataFrame, queries: DataFrame) -> DataFrame:
    """State of each query: a the deeper end; ends in different trees have no common ancestor and are marked APART."""
    both = hop(hop(queries.select("qid", "u", "v"), parents, "u", {"_du": "depth", "_ru": "root"}), parents, "v", {"_dv": "depth", "_rv": "root"})
    swap = F.col("_du") < F.col("_dv")
    pick = lambda x, y: F.when(swap, F.col(y)).otherwise(F.col(x))
    none = F.lit(None).cast("long")
    apart = F.col("_ru").isNull() | F.col("_rv").isNull() | (F.col("_ru") != F.col("_rv"))
    return both.select("qid", "u", "v", pick("u", "v").alias("a"), pick("v", "u").alias("b"), pick("_du", "_dv").alias("da"), pick("_dv", "_du").alias("db"), none.alias("pa"), none.alias("pb"), none.alias("a0"), none.alias("b0"), none.cast("int").alias("da0"), none.cast("int").alias("db0"), swap.alias("swapped"), F.when(apart, F.lit(-1)).when(F.col("u") == F.col("v"), F.col("u")).cast("long").alias("lca"))


def _climbed(state: DataFrame, parents: DataFrame) -> DataFrame:
    """One step: the deeper end, or both where they are level, go to their parents."""
    up = hop(hop(state, parents, "a", {"_na": "parent"}), parents, "b", {"_nb": "parent"})
    live, level = F.col("lca").isNull(), F.col("da") == F.col("db")
    both = live & level
    moved = lambda c, new, when: F.when(when, new).otherwise(F.col(c)).alias(c)
    out = up.select("qid", "u", "v", moved("a", F.col("_na"), live), moved("b", F.col("_nb"), both), moved("da", F.col("da") - 1, live), moved("db", F.col("db") - 1, both), moved("pa", F.col("a"), live), moved("pb", F.col("b"), both), "a0", "b0", "da0", "db0", "swapped", "lca")
    return out.withColumn("lca", F.when(live & (F.col("a") == F.col("b")), F.col("a")).otherwise(F.col("lca")))


def _climb(live: DataFrame, done: list[DataFrame], parents: DataFrame, steps: int | None, phase: str) -> DataFrame:
    """Up to `steps` single steps (None: until all are settled); settled queries leave the state, the rest is returned."""
    taken = 0
    while steps is None or taken < steps:
        now = UNROLL if steps is None else min(UNROLL, steps - taken)
        for _ in range(now):
            live = _climbed(live, parents)
        taken += now
        both = settle(live, phase, taken)
        done.append(both.filter("lca is not null"))
        live = both.filter("lca is null")
        if live.isEmpty():
            break
    return live


def _finish(done: list[DataFrame]) -> DataFrame:
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    lca = F.when(F.col("lca") != APART, F.col("lca"))
    one, two = F.when(F.col("swapped"), F.col("pb")).otherwise(F.col("pa")), F.when(F.col("swapped"), F.col("pa")).otherwise(F.col("pb"))
    return out.select("qid", "u", "v", lca.alias("lca"), F.when(lca != F.col("u"), one).alias("child_u"), F.when(lca != F.col("v"), two).alias("child_v"))


def lca_batch(parents: DataFrame, queries: DataFrame, method: str = "compressed", index: TreeIndex | Callable[[], TreeIndex] | None = None, attach_leaves: bool = False) -> DataFrame:
    """(qid, u, v, lca, child_u, child_v) of query pairs (qid, u, v) over a forest (v, parent, root, depth).

    A child is null where that end is the ancestor itself; all three are null where the ends lie in different trees. With `attach_leaves` queries on inner vertices are put to
    leaves hung below them instead, and that side's child is null again where the leaf itself would be returned.

    compressed: jumps over the compressed tree, linear space, rounds by log depth (default). doubling: every 2**i-th ancestor of every vertex, n log depth rows. naive: step by step.
    The first two take the same steps in one task with arrays where the forest has more than PACK_ROWS rows and, with the queries, at most ARRAY_ROWS; on others they go by rounds. `index` may be a call that
    makes one where it is needed."""
    if attach_leaves:
        return _with_leaves(parents, queries, method)
    if method != "naive" and PACK_ROWS < (rows := parents.count()) and rows + queries.count() <= ARRAY_ROWS:
        vertex, asked = (F.col("v"), F.col("parent"), F.col("depth").cast("long")), (F.col("qid"), F.col("u"), F.col("v"))
        each = [df.select(F.lit(kind).cast("byte").alias("kind"), *(c.alias(n) for c, n in zip(cols, "xyz", strict=True))) for kind, (df, cols) in enumerate([(parents, vertex), (queries, asked)])]
        return in_one(each[0].unionByName(each[1]), meetings(method, step_of), "qid long, u long, v long, lca long, child_u long, child_v long")
    state = settle(_start(parents, queries).select(*_STATE), "lca", 0)
    done = [state.filter("lca is not null")]
    live = state.filter("lca is null")
    if live.isEmpty():
        return _finish(done)
    if method == "naive":
        _climb(live, done, parents, None, "lca naive")
        return _finish(done)
    if method == "doubling":
        return _finish([*done, _by_doubling(parents, live)])
    index = index if isinstance(index, TreeIndex) else index() if index else TreeIndex.of(parents)
    t = index.tree.t
    far = live.filter(F.col("da") > F.col("db") + 2 * t)
    if not far.isEmpty():
        live = live.filter(F.col("da") <= F.col("db") + 2 * t).unionByName(_lifted(far, index))
    live = _climb(live.withColumns({f"{c}0": F.col(c) for c in ("a", "b", "da", "db")}), done, parents, 4 * t, "lca near")
    if live.isEmpty():
        return _finish(done)
    live = _in_compressed(live, index)
    left = _climb(live, done, parents, 2 * t, "lca last")
    if not left.isEmpty():
        raise AssertionError("a query was not settled by its last climb")
    return _finish(done)


def _lifted(far: DataFrame, index: TreeIndex) -> DataFrame:
    """The deeper end at its nearest kept ancestor, then jumps, long ones first, while it stays deeper than the other end."""
    at = hop(hop(far, index.kept, "a", {"_k": "kept"}), index.tree.vertices, "_k", {"_d": "depth"})
    at = at.withColumn("a", F.col("_k")).withColumn("da", F.col("_d")).drop("_k", "_d")
    for j in range(index.top, -1, -1):
        at = hop(at, index.tables.filter(F.col("j") == j), "a", {"_n": "anc", "_d": "anc_depth"}, name="v")
        go = F.col("_d") > F.col("db")
        at = at.withColumn("a", F.when(go, F.col("_n")).otherwise(F.col("a"))).withColumn("da", F.when(go, F.col("_d")).otherwise(F.col("da"))).drop("_n", "_d")
    return settle(at.select(*_STATE), "lca lift")


def _in_compressed(live: DataFrame, index: TreeIndex) -> DataFrame:
    """Both ends at the last kept ancestors that are still different. The search starts again from where the near search began: the common ancestor is over 2t above
    both ends there, and so above their nearest kept ancestors, but may be just above where the near search stopped."""
    at = live.withColumns({c: F.col(f"{c}0") for c in ("a", "b", "da", "db")})
    for end, depth in (("a", "da"), ("b", "db")):
        at = hop(hop(at, index.kept, end, {"_k": "kept"}), index.tree.vertices, "_k", {"_d": "depth"})
        at = at.withColumn(end, F.col("_k")).withColumn(depth, F.col("_d")).drop("_k", "_d")
    for j in range(index.top, -1, -1):  # level them
        table = index.tables.filter(F.col("j") == j)
        for end, depth, other in (("a", "da", "db"), ("b", "db", "da")):
            at = hop(at, table, end, {"_n": "anc", "_d": "anc_depth"}, name="v")
            go = (F.col("_d") >= F.col(other)) & (F.col("_d") < F.col(depth))
            at = at.withColumn(end, F.when(go, F.col("_n")).otherwise(F.col(end))).withColumn(depth, F.when(go, F.col("_d")).otherwise(F.col(depth))).drop("_n", "_d")
    at = settle(at.select(*_STATE), "lca compressed")
    for j in range(index.top, -1, -1):
        table = index.tables.filter(F.col("j") == j)
        at = hop(hop(at, table, "a", {"_n": "anc", "_d": "anc_depth"}, name="v"), table, "b", {"_m": "anc"}, name="v")
        go = F.col("_n") != F.col("_m")
        at = at.withColumn("a", F.when(go, F.col("_n")).otherwise(F.col("a"))).withColumn("b", F.when(go, F.col("_m")).otherwise(F.col("b")))
        at = at.withColumn("da", F.when(go, F.col("_d")).otherwise(F.col("da"))).withColumn("db", F.col("da")).drop("_n", "_m", "_d")
    return settle(at.select(*_STATE), "lca compressed")


def ancestor_tables(parents: DataFrame, deepest: int) -> DataFrame:
    """(j, v, anc): every 2**j-th ancestor of every vertex, n log depth rows: what compression avoids."""
    level, out = parents.select("v", F.col("parent").alias("anc")), None
    for j in range(max(1, deepest.bit_length())):
        row = level.select(F.lit(j).alias("j"), "v", "anc")
        out = row if out is None else out.unionByName(row)
        level = settle(hop(level, level, "anc", {"_n": "anc"}, name="v").select("v", F.col("_n").alias("anc")), "ancestor tables", j)
    return settle(out, "ancestor tables")


def _by_doubling(parents: DataFrame, live: DataFrame) -> DataFrame:
    deepest = parents.agg(F.max("depth")).first()[0]
    tables, at = ancestor_tables(parents, deepest), live
    top = max(1, deepest.bit_length()) - 1
    for j in range(top, -1, -1):  # the deeper end to one step above level, so that its last step is known
        at = hop(at, tables.filter(F.col("j") == j), "a", {"_n": "anc"}, name="v")
        go = F.col("da") - (1 << j) > F.col("db")
        at = at.withColumn("a", F.when(go, F.col("_n")).otherwise(F.col("a"))).withColumn("da", F.when(go, F.col("da") - (1 << j)).otherwise(F.col("da"))).drop("_n")
    at = hop(at, parents, "a", {"_n": "parent"})
    up = F.col("da") > F.col("db")
    at = at.withColumn("pa", F.when(up, F.col("a"))).withColumn("a", F.when(up, F.col("_n")).otherwise(F.col("a"))).drop("_n")
    at = settle(at.withColumn("lca", F.when(F.col("a") == F.col("b"), F.col("a"))).select(*_STATE), "lca doubling")
    met, at = at.filter("lca is not null"), at.filter("lca is null")
    for j in range(top, -1, -1):
        table = tables.filter(F.col("j") == j)
        at = hop(hop(at, table, "a", {"_n": "anc"}, name="v"), table, "b", {"_m": "anc"}, name="v")
        go = F.col("_n") != F.col("_m")
        at = at.withColumn("a", F.when(go, F.col("_n")).otherwise(F.col("a"))).withColumn("b", F.when(go, F.col("_m")).otherwise(F.col("b"))).drop("_n", "_m")
    at = hop(at, parents, "a", {"_n": "parent"}).withColumn("pa", F.col("a")).withColumn("pb", F.col("b")).withColumn("lca", F.col("_n"))
    return met.unionByName(settle(at.select(*_STATE), "lca doubling"))


def _with_leaves(parents: DataFrame, queries: DataFrame, method: str) -> DataFrame:
    """Every inner vertex that a query asks for gets an artificial leaf (-2 - v) below it, which stands for it there."""
    asked = queries.select(F.explode(F.array("u", "v")).alias("v")).distinct()
    inner = settle(asked.join(parents.filter("v <> parent").select(F.col("parent").alias("v")), "v", "left_semi").join(parents, "v"), "leaves")
    leaf = inner.select((-2 - F.col("v")).alias("v"), F.col("v").alias("parent"), "root", (F.col("depth") + 1).alias("depth"))
    marks = inner.select("v", F.lit(1).alias("one"))
    moved = hop(hop(queries.select("qid", "u", "v"), marks, "u", {"_u": "one"}), marks, "v", {"_v": "one"})
    asked = moved.select("qid", F.when(F.col("_u").isNotNull(), -2 - F.col("u")).otherwise(F.col("u")).alias("u"), F.when(F.col("_v").isNotNull(), -2 - F.col("v")).otherwise(F.col("v")).alias("v"))
    found = lca_batch(settle(parents.select("v", "parent", "root", "depth").unionByName(leaf), "leaves"), asked, method)
    back = lambda c: F.when(F.col(c) < 0, -2 - F.col(c)).otherwise(F.col(c)).alias(c)
    bare = lambda c: F.when(F.col(c) >= 0, F.col(c)).alias(c)
    return found.select("qid", back("u"), back("v"), back("lca"), bare("child_u"), bare("child_v"))
