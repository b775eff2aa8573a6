"""The paper-style claims as runs W1 to W12 on the given tables: each returns rows of a series. `python -m spanweave.plans.workloads SF_DIR [W..]` prints them."""

from __future__ import annotations

import math
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave import graphs
from spanweave.ledger import Budget, Ledger, settle
from spanweave.operators import blocks as bl
from spanweave.operators import bridges as br
from spanweave.operators import hub, measures, pointers
from spanweave.operators.components import connected_components
from spanweave.operators.compress import compress_tree, jump_tables, step_of
from spanweave.operators.forest import spanning_forest
from spanweave.operators.lca import TreeIndex, ancestor_tables, lca_batch
from spanweave.operators.paths import ancestor_paths
from spanweave.operators.tour import dfs_sequence
from spanweave.sources.tables import read_table
from spanweave.schema import Failed

Rows = list[dict]


def timed(run: Callable[[], DataFrame | int | bool]) -> dict:
    """Result size or value, seconds, rounds, most rows alive, fullest task."""
    ledger, began = Ledger(), time.time()
    with ledger.open():
        out = run()
        value = out.count() if isinstance(out, DataFrame) else out
    return {"value": value, "seconds": round(time.time() - began, 2), "rounds": ledger.rounds(), "live_rows": ledger.live_rows(), "max_rows_per_task": max((r[4] for r in ledger.rows), default=0)}


def w1(spark: SparkSession, d: str) -> Rows:
    """Bridges end to end by every method."""
    built = {"trade": graphs.trade_sparse, "cactus": graphs.ring_cactus, "forest": graphs.fk_forest}
    return [{"graph": g, "method": m} | timed(lambda: br.find_bridges(build(spark, d), method=m)) for g, build in built.items() for m in ("paper", "interval", "hook", "local")]


def w2(spark: SparkSession, d: str) -> Rows:
    """Blocks end to end."""
    built = {"trade": graphs.trade_sparse, "cactus": graphs.ring_cactus, "hub of two rings": lambda s, p: hub.add_hub(graphs.rings(s, p, 2))}
    return [{"graph": g, "method": m} | timed(lambda: bl.color_blocks(build(spark, d), method=m)) for g, build in built.items() for m in ("paper", "interval", "local")]


def w3(spark: SparkSession, d: str, sizes=(16, 32, 64, 128)) -> Rows:
    """Rounds against diameter on rings of growing length: contraction and stars grow with its logarithm, propagation with the diameter itself."""
    return [{"ring": n, "log2_diameter": round(math.log2(n / 2), 1), "method": m} | timed(lambda: connected_components(graphs.rings(spark, d, 1, below=n), method=m)) for n in sizes for m in ("naive", "stars", "hook", "contract")]


def w4(spark: SparkSession, d: str) -> Rows:
    """Rounds of contraction against density and extra space."""
    return [{"cut": cut, "gamma": gamma} | timed(lambda: connected_components(graphs.trade_sparse(spark, d, cut), method="contract", budget=Budget(gamma=gamma))) for cut in (49, 40, 25) for gamma in (0.0, 0.5)]


def w5(spark: SparkSession, d: str) -> Rows:
    """Rows stored by the tree part: compressed against all powers, printed keep-rule against the repaired one."""
    n = read_table(spark, d, "part", ["p_partkey"]).count()
    trees = {"cactus": spanning_forest(graphs.ring_cactus(spark, d)), "chains": spanning_forest(graphs.chains(spark, d)), "broom": pointers.depths(graphs.broom(spark, d, n // 4, step_of(n // 4 - 1) - 1))}
    out = []
    for name, parents in trees.items():
        parents = settle(parents, "workload")
        depth = parents.agg(F.max("depth")).first()[0]
        row = {"tree": name, "n": parents.count(), "depth": depth, "all_powers": ancestor_tables(parents, depth).count()}
        for keep in ("descendant", "printed"):
            tree = compress_tree(parents, keep)
            row |= {f"kept_{keep}": tree.vertices.count(), f"jumps_{keep}": jump_tables(tree).count(), "bound": row["n"] // tree.t}
        out.append(row)
    return out


def w6(spark: SparkSession, d: str, sizes=(16, 64)) -> Rows:
    """One cycle or two by the hub reduction: diameter 2, cycles as long as the graph."""
    return [{"length": n, "cycles": k} | timed(lambda: hub.one_or_two_cycles(graphs.rings(spark, d, k, below=n), method="interval")) for n in sizes for k in (1, 2)]


def w7(spark: SparkSession, d: str) -> Rows:
    """Rows stored for range minima: n + q against n log n."""
    from spanweave.plans.catalog import _values

    arr = _values(spark, d)
    asked = settle(arr.groupBy(F.col("user_id").alias("qid")).agg(F.min("pos").alias("lo"), F.max("pos").alias("hi")), "workload")
    return [{"n": arr.count(), "q": asked.count()} | measures.rows_of_range_min(arr.select("pos", "val"), asked)]


def w8(spark: SparkSession, d: str) -> Rows:
    """Batches of common ancestors and paths: all edges as queries."""
    out = []
    for name, build in (("trade", graphs.trade_sparse), ("cactus", graphs.ring_cactus)):
        ready = br.Prepared(build(spark, d))
        pairs = settle(ready.graph.select(F.xxhash64("src", "dst").alias("qid"), F.col("src").alias("u"), F.col("dst").alias("v")), "workload")
        parents, index = ready.parents, TreeIndex.of(ready.parents)
        ups = settle(parents.select(F.col("v").alias("qid"), F.col("v").alias("u"), F.col("root").alias("anc")), "workload")
        for m in ("compressed", "doubling", "naive"):
            given = {"index": index} if m == "compressed" else {}
            out.append({"graph": name, "batch": "lca", "method": m} | timed(lambda: lca_batch(parents, pairs, method=m, **given)))
            out.append({"graph": name, "batch": "paths", "method": m} | timed(lambda: ancestor_paths(parents, ups, method=m, **given)))
    return out


def w9_runs(spark: SparkSession, d: str, seeds: int = 100, s: int = 64, c: float = 0.25) -> Rows:
    """Real runs of the sequence under the printed rule (more than s squares of samples: give up): how many of `seeds` give up, on a forest of chains."""
    parents = settle(spanning_forest(graphs.trade_sparse(spark, d)), "workload")
    failed = 0
    for seed in range(seeds):
        try:
            dfs_sequence(parents, s=s, c=c, seed=seed, printed_bound=True)
        except Failed:
            failed += 1
    return [{"s": s, "c": c, "runs": seeds, "failed": failed}]


def w9(spark: SparkSession, d: str, seeds: int = 100) -> Rows:
    """Share of runs that would give up at the first level, by the bound on samples and by a budget of pairs: sample counts are drawn, the sequence is not run (`w9_runs` runs it)."""
    parents = settle(spanning_forest(graphs.ring_cactus(spark, d)), "workload")
    leaf, n = pointers.leaves(parents).count(), parents.count()
    return [{"s": s, "c": c} | measures.sampled_verdicts(leaf, n, s, c, 20_000, range(seeds)) for s in (64, 512, 4096) for c in (0.25, 1.0)]


def w10(spark: SparkSession, d: str) -> Rows:
    """Size and diameter of the auxiliary graph against their bounds, small graphs."""
    out = []
    for name, build in (("trade", graphs.trade_sparse), ("cactus", graphs.ring_cactus)):
        row = {"graph": name} | measures.aux_report(build(spark, d)).first().asDict()
        try:
            row["aux_diameter"] = measures.aux_diameter(build(spark, d))
            row["bi_diameter"] = measures.bi_diameter(build(spark, d)).agg(F.max("length")).first()[0]
        except Failed as refused:
            row["not_computed"] = str(refused)
        out.append(row)
    return out


def w11(spark: SparkSession, d: str) -> Rows:
    """Cut vertices, and the condition that bridges meet but others may too."""
    out = []
    for name, build in (("trade", graphs.trade_sparse), ("cactus", graphs.ring_cactus)):
        colors = settle(bl.color_blocks(build(spark, d), method="interval"), "workload")
        bridges = bl.block_sizes(colors).filter("edges = 1").count()
        out.append({"graph": name, "cut_vertices": bl.cut_vertices(colors).count(), "bridges": bridges, "edges_that_fit": bl.bridge_conditions(build(spark, d), colors).count()})
    return out


def w12(spark: SparkSession, d: str) -> Rows:
    """Local memory: rows of the fullest task and rounds as tasks are allowed less."""
    out = []
    for delta in (0.3, 0.5, 0.7):
        budget = Budget(delta=delta)
        rows = graphs.part_supp(spark, d).count()
        old = spark.conf.get("spark.sql.shuffle.partitions")
        spark.conf.set("spark.sql.shuffle.partitions", str(min(512, budget.partitions(rows))))
        try:
            out.append({"delta": delta, "allowed": budget.local(rows)} | timed(lambda: connected_components(graphs.part_supp(spark, d))))
        finally:
            spark.conf.set("spark.sql.shuffle.partitions", old)
    return out


def series(rows: Rows) -> list[tuple[str, str, int]]:
    """(series, measure, value) of what does not depend on the machine; shares are given in thousandths."""
    out = []
    for row in rows:
        label = ", ".join(f"{k}={v}" for k, v in row.items() if k in LABELS)
        counted = {k: v for k, v in row.items() if k not in LABELS and k not in ("seconds", "max_rows_per_task", "exchange_rows")}
        out += [(label, k, int(v)) if isinstance(v, bool | int) else (label, f"{k}_per_mille", round(v * 1000)) for k, v in counted.items() if isinstance(v, bool | int | float)]
    return out


#: What names a series; everything else that is counted is a measure of it.
LABELS = ("graph", "method", "ring", "log2_diameter", "cut", "gamma", "tree", "length", "cycles", "batch", "s", "c", "delta")


def as_query(name: str) -> Callable[[SparkSession, str], DataFrame]:
    """A workload as a frame (series, measure, value)."""
    return lambda spark, d: spark.createDataFrame(series(WORKLOADS[name](spark, d)), "series string, measure string, value long")


WORKLOADS = {f.__name__: f for f in (w1, w2, w3, w4, w5, w6, w7, w8, w9, w9_runs, w10, w11, w12)}


def main(args: list[str]) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in args[1:] or WORKLOADS:
        for row in WORKLOADS[name](spark, args[0]):
            print(name, row, flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
