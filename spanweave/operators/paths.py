"""Batched paths from vertices to their ancestors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.ledger import settle
from spanweave.operators.lca import UNROLL, TreeIndex, ancestor_tables
from spanweave.operators.pointers import hop


def ancestor_paths(parents: DataFrame, queries: DataFrame, method: str = "compressed", index: TreeIndex | None = None, as_array: bool = False) -> DataFrame:
    """(qid, pos, v) for queries (qid, u, anc), anc an ancestor of u or u itself: pos 0 at u, growing toward anc. ValueError where anc is none.

    compressed: a path of up to 2t steps is climbed; of a longer one the kept vertices are found by jump tables and every gap, of at most 2t, fills itself by climbing; linear
    space. doubling: by tables of all 2**i-th ancestors. naive: climbing the whole way. `as_array` gathers (qid, path) instead: a path can be as long as the tree is deep."""
    asked = hop(hop(queries.select("qid", "u", "anc"), parents, "u", {"du": "depth"}), parents, "anc", {"dx": "depth"})
    asked = settle(asked, "paths", 0)
    if not asked.filter("du is null or dx is null or dx > du").isEmpty():
        raise ValueError("an end of a path is no ancestor")
    if method == "naive":
        out = _filled(parents, asked.select("qid", F.col("u").alias("x"), F.col("du").alias("d"), F.col("dx").alias("stop"), "du"), None)
    elif method == "doubling":
        deepest = asked.agg(F.coalesce(F.max(F.col("du") - F.col("dx")), F.lit(0))).first()[0]
        tables = ancestor_tables(parents, max(1, deepest))
        rows = _steps(asked.select("qid", F.lit(0).alias("i"), F.col("u").alias("x"), (F.col("du") - F.col("dx")).alias("most")), tables, deepest.bit_length())
        out = rows.select("qid", F.col("i").alias("pos"), F.col("x").alias("v"))
    else:
        index = index or TreeIndex.of(parents)
        t = index.tree.t
        short = asked.filter(F.col("du") - F.col("dx") <= 2 * t).select("qid", F.col("u").alias("x"), F.col("du").alias("d"), F.col("dx").alias("stop"), "du")
        long = asked.filter(F.col("du") - F.col("dx") > 2 * t)
        gaps = short
        if not long.isEmpty():
            gaps = gaps.unionByName(_gaps(long, index))
        out = _filled(parents, gaps, 2 * t)
    checked = out.join(asked.select("qid", "anc", (F.col("du") - F.col("dx")).alias("last")), "qid")
    if not checked.filter("pos = last and v <> anc").isEmpty():
        raise ValueError("an end of a path is no ancestor")
    out = out.select("qid", F.col("pos").cast("long").alias("pos"), "v")
    if as_array:
        return out.groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda r: r["v"]).alias("path"))
    return out


def _steps(rows: DataFrame, tables: DataFrame, rounds: int) -> DataFrame:
    """All i-th ancestors, i = 0..most, of x: each round doubles the stretch that is known."""
    for j in range(rounds):
        more = hop(rows.filter(F.col("i") + (1 << j) <= F.col("most")), tables.filter(F.col("j") == j), "x", {"_n": "anc"}, name="v")
        rows = settle(rows.unionByName(more.select("qid", (F.col("i") + (1 << j)).alias("i"), F.col("_n").alias("x"), "most")), "paths doubling", j)
    return rows


def _gaps(long: DataFrame, index: TreeIndex) -> DataFrame:
    """For each long query the stretches between its end, the kept vertices on its path, and its ancestor: (qid, x, d, stop, du), x written down to
    depth `stop`, which belongs to the stretch of the last gap only."""
    t = index.tree.t
    at = hop(hop(long, index.kept, "u", {"k": "kept"}), index.tree.vertices, "k", {"dk": "depth"})
    at = settle(at.withColumn("most", F.floor((F.col("dk") - F.col("dx")) / t).cast("int")), "paths", 1)
    deepest = at.agg(F.coalesce(F.max("most"), F.lit(0))).first()[0]
    kept = _steps(at.select("qid", F.lit(0).alias("i"), F.col("k").alias("x"), "most"), index.tables, max(0, deepest.bit_length()))
    placed = kept.join(at.select("qid", "dk", "dx", "du"), "qid").select("qid", "x", (F.col("dk") - F.col("i") * t).alias("d"), "i", "most", "dx", "du")
    inner = placed.select("qid", "x", "d", F.when(F.col("i") == F.col("most"), F.col("dx")).otherwise(F.col("d") - t + 1).alias("stop"), "du")
    first = at.filter("u <> k").select("qid", F.col("u").alias("x"), F.col("du").alias("d"), (F.col("dk") + 1).alias("stop"), "du")
    return inner.unionByName(first)


def _filled(parents: DataFrame, gaps: DataFrame, most: int | None) -> DataFrame:
    """(qid, pos, v) of every gap: climb from x while its depth exceeds `stop`, all gaps side by side."""
    live, taken = settle(gaps.select("qid", F.col("x"), F.col("d").cast("int").alias("d"), F.col("stop").cast("int").alias("stop"), F.col("du").cast("int").alias("du")), "paths fill", 0), 0
    out = live.select("qid", (F.col("du") - F.col("d")).alias("pos"), F.col("x").alias("v"))
    parts = [out]
    while most is None or taken < most:
        wide = live.filter("d > stop").withColumn("x0", F.col("x"))
        steps = UNROLL if most is None else min(UNROLL, most - taken)
        for k in range(steps):
            wide = hop(wide, parents, f"x{k}", {f"x{k + 1}": "parent"})
        rows = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"x{k}").alias("y")) for k in range(1, steps + 1)))).alias("s")
        found = wide.select("qid", "d", "stop", "du", rows).filter(F.col("d") - F.col("s.k") >= F.col("stop"))
        found = settle(found.select("qid", F.col("s.y").alias("x"), (F.col("d") - F.col("s.k")).alias("d"), "stop", "du", F.col("s.k").alias("k")), "paths fill", taken)
        parts.append(found.select("qid", (F.col("du") - F.col("d")).alias("pos"), F.col("x").alias("v")))
        taken += steps
        live = found.filter(F.col("k") == steps).drop("k")
        if live.filter("d > stop").isEmpty():
            break
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
