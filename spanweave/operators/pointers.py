"""Parent pointers: validity, k-th ancestors, depths, ranks, leaves. A root points to itself."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave.ledger import settle
from spanweave.operators.arrays import ARRAY_ROWS, PACK_ROWS, doubled, in_one
from spanweave.operators.positions import dense_positions


def hop(frame: DataFrame, table: DataFrame, key: str, columns: dict[str, str], name: str = "at", keep: str = "left") -> DataFrame:
    """`frame` with `columns` {new: old} looked up in `table` (unique by its first column or `name`) at frame[key].

    A plain equi-join: small tables are broadcast under the session's own threshold, large ones meet by key, and skewed keys are split at run time."""
    first = table.columns[0] if name not in table.columns else name
    side = table.select(F.col(first).alias("_key"), *(F.col(old).alias(new) for new, old in columns.items()))
    return frame.join(side, F.col(key) == F.col("_key"), keep).drop("_key")


def lookup(queries: DataFrame, mapping: DataFrame, key: str, out: str, hint: str | None = None) -> DataFrame:
    """Every query's value under `mapping` (key, value), all at once; null where it has none. `hint` forces a join strategy:
    broadcast, merge or shuffle_hash."""
    side = mapping.select(F.col(mapping.columns[0]).alias("_key"), F.col(mapping.columns[1]).alias(out))
    return queries.join(side.hint(hint) if hint else side, F.col(key) == F.col("_key"), "left").drop("_key")


def _doubled(state: DataFrame, sums: tuple[str, ...] = ()) -> DataFrame:
    """One round: every pointer to its pointer's pointer, sums along the way added; `moved` tells which changed."""
    far = state.select(F.col("v").alias("_v"), F.col("ptr").alias("_ptr"), *(F.col(s).alias(f"_{s}") for s in sums))
    joined = state.join(far, F.col("ptr") == F.col("_v"))
    extra = [c for c in state.columns if c not in ("v", "ptr", "moved", *sums)]
    return joined.select("v", F.col("_ptr").alias("ptr"), *((F.col(s) + F.col(f"_{s}")).alias(s) for s in sums), *extra, (F.col("_ptr") != F.col("ptr")).alias("moved"))


def doubling(state: DataFrame, sums: tuple[str, ...] = (), phase: str = "doubling", max_rounds: int = 64) -> DataFrame:
    """Pointers (v, ptr, sums) followed to their ends, with sums over the path; ends have sums 0. Logarithmic in the longest path, one row a vertex alive.

    A row whose pointer is an end is done and leaves the rounds; it learns so from the row it points to, whose own pointer is one. So the rounds shrink, and after the first no two rows are joined
    on an end, however many hang below it. More than PACK_ROWS and at most ARRAY_ROWS pointers are doubled in one task with arrays."""
    extra = [c for c in state.columns if c not in ("v", "ptr", *sums)]
    if not extra and dict(state.dtypes)["v"] == "bigint" and PACK_ROWS < state.count() <= ARRAY_ROWS // (1 + len(sums) // 2):
        schema = ", ".join(f"{c} long" for c in ("v", "ptr", *(f"s{k}" for k in range(len(sums)))))
        return settle(in_one(state.select("v", "ptr", *(F.col(c).cast("long") for c in sums)), doubled, schema), phase).toDF("v", "ptr", *sums)
    live, done = state.withColumn("_end", F.col("v") == F.col("ptr")), []
    for turn in range(max_rounds):
        far = reduce(DataFrame.unionByName, [live, *done]).select(F.col("v").alias("_v"), F.col("ptr").alias("_ptr"), F.col("_end").alias("_fixed"), *(F.col(s).alias(f"_{s}") for s in sums))
        near = live if turn == 0 else live.filter("not _end")
        step = near.join(far, F.col("ptr") == F.col("_v"))
        step = settle(step.select("v", F.col("_ptr").alias("ptr"), *((F.col(s) + F.col(f"_{s}")).alias(s) for s in sums), *extra, F.col("_fixed").alias("_end")), phase, turn)
        done.append(step.filter("_end"))
        live = step.filter("not _end")
        if live.isEmpty():
            return reduce(DataFrame.unionByName, done).drop("_end")
    raise ValueError("pointers do not end: they hold a cycle")


def path_sums(parents: DataFrame, weight: Column, name: str = "sum", phase: str = "path sums") -> DataFrame:
    """(v, root, name): `weight` added up over all vertices from v up to, but not including, the root."""
    start = parents.select("v", F.col("parent").alias("ptr"), F.when(F.col("v") == F.col("parent"), 0).otherwise(weight).cast("long").alias(name))
    return doubling(start, (name,), phase).withColumnRenamed("ptr", "root")


def depths(parents: DataFrame) -> DataFrame:
    """(v, parent, root, depth) of pointers (v, parent)."""
    found = path_sums(parents, F.lit(1), "depth", "depths")
    return parents.select("v", "parent").join(found, "v").select("v", "parent", "root", F.col("depth").cast("int").alias("depth"))


def check_forest(parents: DataFrame, max_rounds: int = 64) -> None:
    """ValueError unless every parent is a vertex, ids are unique, and every vertex ends at a self-loop."""
    bare = parents.select("v", "parent")
    if not bare.groupBy("v").count().filter("count > 1").isEmpty():
        raise ValueError("a vertex has two parents")
    if not bare.join(bare.select(F.col("v").alias("parent")), "parent", "left_anti").isEmpty():
        raise ValueError("a parent is no vertex")
    rounds = max(1, bare.count()).bit_length() + 1
    state = bare.select("v", F.col("parent").alias("ptr"))
    for turn in range(min(rounds, max_rounds)):
        state = settle(_doubled(state), "check", turn)
        if state.filter("moved").isEmpty():
            break
    roots = bare.filter("v = parent").select(F.col("v").alias("ptr"))
    if not state.join(roots, "ptr", "left_anti").isEmpty():
        raise ValueError("pointers hold a cycle")


def ancestor_at(parents: DataFrame, k: int, of: DataFrame | None = None) -> DataFrame:
    """(v, anc): the k-th ancestor of every vertex, or of the vertices `of` (v); a root absorbs. log k rounds."""
    power = parents.select("v", F.col("parent").alias("to"))
    found = (of if of is not None else parents).select("v", F.col("v").alias("anc"))
    while k:
        if k & 1:
            found = hop(found, power, "anc", {"_to": "to"}).select("v", F.col("_to").alias("anc"))
        k >>= 1
        if k:
            power = settle(hop(power, power, "to", {"_to": "to"}).select("v", F.col("_to").alias("to")), "ancestors")
    return found


def child_ranks(parents: DataFrame, method: str = "positions") -> DataFrame:
    """(v, parent, rank) by child id from 1; a root has rank 1. positions: without bringing one parent's children together (default). window: one parent's children in one task."""
    children = parents.filter("v <> parent").select("v", "parent")
    roots = parents.filter("v = parent").select("v", "parent", F.lit(1).alias("rank"))
    if method == "window":
        ranked = children.select("v", "parent", F.row_number().over(Window.partitionBy("parent").orderBy("v")).alias("rank"))
    else:
        placed = dense_positions(children, ["parent", "v"])
        first = placed.groupBy("parent").agg(F.min("pos").alias("_first"))
        ranked = placed.join(first, "parent").select("v", "parent", (F.col("pos") - F.col("_first") + 1).cast("int").alias("rank"))
    return ranked.unionByName(roots)


def child_counts(parents: DataFrame) -> DataFrame:
    """(v, children) of every vertex."""
    counts = parents.filter("v <> parent").groupBy("parent").agg(F.count(F.lit(1)).alias("n"))
    return hop(parents.select("v"), counts, "v", {"n": "n"}, name="parent").select("v", F.coalesce("n", F.lit(0)).cast("long").alias("children"))


def kth_child(parents: DataFrame, k: int) -> DataFrame:
    """(parent, v): the k-th child where there is one."""
    return child_ranks(parents).filter((F.col("rank") == k) & (F.col("v") != F.col("parent"))).select("parent", "v")


def leaves(parents: DataFrame) -> DataFrame:
    """Vertices without children; a lone root is one."""
    inner = parents.filter("v <> parent").select(F.col("parent").alias("v")).distinct()
    return parents.select("v").join(inner, "v", "left_anti")


def is_ancestor(pairs: DataFrame, spans: DataFrame) -> DataFrame:
    """`pairs` (u, v, ...) with `ancestor`: whether u is an ancestor of v or v itself, by containment of their spans."""
    both = hop(hop(pairs, spans, "u", {"_uf": "first", "_ul": "last"}), spans, "v", {"_vf": "first", "_vl": "last"})
    return both.withColumn("ancestor", (F.col("_uf") <= F.col("_vf")) & (F.col("_vl") <= F.col("_ul"))).drop("_uf", "_ul", "_vf", "_vl")
