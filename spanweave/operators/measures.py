"""Cost and accuracy measures: diameter, cycle lengths, bounds on compressed trees and auxiliary graphs, failure rates."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.graphs import canonical
from spanweave.ledger import Budget, Ledger, settle
from spanweave.operators.bridges import Prepared
from spanweave.operators.blocks import auxiliary_graph, block_sizes, color_blocks
from spanweave.operators.arrays import ARRAY_ROWS, adjacency, numbered, spread
from spanweave.operators.components import LOCAL_ROWS, both_ways, by_size, connected_components
from spanweave.operators.compress import compress_tree, nearest_kept
from spanweave.operators.pointers import hop
from spanweave.operators.rangemin import range_min
from spanweave.operators.tour import dfs_sequence
from spanweave.schema import Failed


def eccentricities(edges: DataFrame, sources: DataFrame, max_rounds: int = 5000) -> DataFrame:
    """(source, ecc): steps to the farthest vertex, by a breadth-first wave from all `sources` (v) side by side: sources times vertices rows."""
    arcs = settle(both_ways(canonical(edges)), "diameter", 0)
    front = sources.select(F.col("v").alias("source"), "v")
    seen, last = front, front.select("source", F.lit(0).alias("d"))
    for turn in range(1, max_rounds):
        nxt = front.join(arcs, "v").select("source", F.col("w").alias("v")).distinct().join(seen, ["source", "v"], "left_anti")
        nxt = settle(nxt, "diameter", turn)
        if nxt.isEmpty():
            break
        last = last.unionByName(nxt.select("source").distinct().withColumn("d", F.lit(turn)))
        front, seen = nxt, settle(seen.unionByName(nxt), "diameter", turn)
    return last.groupBy("source").agg(F.max("d").alias("ecc"))


def waves(start: np.ndarray, near: np.ndarray, of: np.ndarray) -> int:
    """The greatest distance from any of the places `of`: a bit a source at every vertex, one wave from all of them."""
    seen = np.zeros((len(start) - 1, -(-len(of) // 64)), np.uint64)
    at = np.arange(len(of))
    seen[of, at // 64] = np.uint64(1) << (at % 64).astype(np.uint64)
    turn = 0
    while True:
        wave = seen | np.bitwise_or.reduceat(seen[near], start[:-1], axis=0)
        if (wave == seen).all():
            return turn
        seen, turn = wave, turn + 1


def longest_wave(pdf: pd.DataFrame, room: int = 4_000_000) -> int:
    """The diameter of one component (src, dst): waves from as many sources at once as `room` words for all arcs allow."""
    ids, a, b = numbered(pdf.src.to_numpy(), pdf.dst.to_numpy())
    n = len(ids)
    start, near = adjacency(a, b, n)
    step = 64 * max(1, room // len(near))
    return max(waves(start, near, np.arange(low, min(n, low + step))) for low in range(0, n, step))


def distances(start: np.ndarray, near: np.ndarray, source: int) -> np.ndarray:
    dist, turn = np.full(len(start) - 1, -1, np.int32), 0
    dist[source], front = 0, np.array([source])
    while len(front):
        below = near[spread(start, front)[0]]
        below, turn = below[dist[below] < 0], turn + 1
        dist[below] = turn
        front = np.unique(below)
    return dist


def bounded_wave(pdf: pd.DataFrame, room: int = 4_000_000) -> int:
    """The diameter of one component (src, dst), exact: no vertex is farther from any than a source's greatest distance and its own to that source, so only vertices whose bound exceeds the greatest
    distance found stay open. Sources are by turns the vertex of the least lower bound and the open one of the greatest upper bound, now and then many open ones at once, more each time."""
    ids, a, b = numbered(pdf.src.to_numpy(), pdf.dst.to_numpy())
    n = len(ids)
    start, near = adjacency(a, b, n)
    del ids, a, b
    upper, lower, left = np.full(n, n, np.int32), np.zeros(n, np.int32), np.arange(n, dtype=np.int32)
    most, turn, many, source = 0, 0, 64, int(np.argmax(np.diff(start)))
    while True:
        dist = distances(start, near, source)
        far = dist.max()
        most, turn = max(most, int(far)), turn + 1
        np.minimum(upper, dist + far, out=upper)
        np.maximum(lower, np.maximum(dist, far - dist), out=lower)
        upper[source], lower[source] = far, n  # known: never a source again
        left = left[upper[left] > most]
        if len(left) and (turn % 8 == 0 or len(left) <= 64):
            order = np.argsort(-upper[left], kind="stable")
            most, left = max(most, waves(start, near, left[order[:many]])), left[order[many:]]
            left = left[upper[left] > most]
            many = min(2 * many, 64 * max(1, room // len(near)))
        if not len(left):
            return most
        source = int(np.argmin(lower)) if turn % 2 else int(left[np.argmax(upper[left])])


def _neighbours(pdf: pd.DataFrame) -> dict[int, list[int]]:
    near: dict[int, list[int]] = {}
    for a, b in zip(pdf.src.tolist(), pdf.dst.tolist(), strict=True):
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    return near


def diameter(edges: DataFrame, mode: str = "lower") -> DataFrame:
    """(comp, diameter) of every component. exact: waves from all sources, whole components of up to LOCAL_ROWS edges in a task; of up to ARRAY_ROWS edges, from all whose bounds leave them open; larger ones by rounds (vertices squared rows). lower: two sweeps by rounds, a lower bound that is exact on trees."""
    graph = settle(canonical(edges), "diameter")
    if mode == "exact":
        small, large = by_size(graph, LOCAL_ROWS)

        def work(pdf: pd.DataFrame) -> pd.DataFrame:
            rows = [(int(comp), longest_wave(part)) for comp, part in pdf.groupby("comp")]
            return pd.DataFrame(rows, columns=["comp", "diameter"]).astype({"diameter": "int32"})

        found = small.groupBy("pack").applyInPandas(work, "comp long, diameter int")
        if large.isEmpty():
            return found
        size = settle(large.groupBy("comp").agg(F.count(F.lit(1)).alias("n")), "diameter")
        one = lambda pdf: pd.DataFrame({"comp": pdf["comp"].iloc[:1], "diameter": [bounded_wave(pdf)]}).astype({"diameter": "int32"})
        fits = large.join(size.filter(F.col("n") <= ARRAY_ROWS), "comp", "left_semi")
        found = found.unionByName(fits.groupBy("comp").applyInPandas(one, "comp long, diameter int"))
        large = large.join(size.filter(F.col("n") > ARRAY_ROWS), "comp", "left_semi")
        if large.isEmpty():
            return found
        label = settle(connected_components(large, method="local"), "diameter")
        every = eccentricities(large, label.select("v"), 1 << 30)
        return found.unionByName(every.join(label.select(F.col("v").alias("source"), "comp"), "source").groupBy("comp").agg(F.max("ecc").alias("diameter")))
    label = settle(connected_components(graph), "diameter")
    far = _sweep(graph, label.groupBy("comp").agg(F.min("v").alias("v")).select("comp", "v"))
    return _sweep(graph, far.select("comp", "v")).select("comp", F.col("ecc").alias("diameter"))


def _sweep(graph: DataFrame, starts: DataFrame, max_rounds: int = 20_000) -> DataFrame:
    """(comp, v, ecc): a vertex farthest from each component's start, and its distance."""
    arcs = settle(both_ways(graph), "sweep", 0)
    front = settle(starts, "sweep", 0)
    best, before = front.select("comp", "v", F.lit(0).alias("ecc")), front.limit(0)
    for turn in range(1, max_rounds):
        nxt = arcs.join(front, "v").select("comp", F.col("w").alias("v")).distinct()
        nxt = settle(nxt.join(front.unionByName(before).select("v"), "v", "left_anti").select("comp", "v"), "sweep", turn)
        if nxt.isEmpty():
            return best
        here = nxt.groupBy("comp").agg(F.min("v").alias("v")).withColumn("ecc", F.lit(turn))
        best = settle(best.unionByName(here).groupBy("comp").agg(F.max(F.struct("ecc", "v")).alias("z")).select("comp", F.col("z.v").alias("v"), F.col("z.ecc").alias("ecc")), "sweep", turn)
        before, front = front, nxt
    raise Failed("the sweep did not end")


def _least_cycle(near: dict[int, list[int]], s: int, t: int) -> int | None:
    """Length of the shortest simple cycle through s and t: two inner-disjoint paths of least total length, by two rounds of shortest augmenting paths over split vertices."""
    if s == t:
        return 0
    flow: dict[tuple, int] = {}
    cost_total = 0

    def arcs():
        for v in near:
            yield ((v, 0), (v, 1)), (2 if v in (s, t) else 1), 0
            for w in near[v]:
                yield ((v, 1), (w, 0)), 1, 1

    capacity = {}
    out: dict[tuple, list[tuple]] = {}
    for (a, b), cap, cost in arcs():
        capacity[a, b] = (cap, cost)
        out.setdefault(a, []).append(b)
        out.setdefault(b, []).append(a)
    for _ in range(2):
        dist, prev, todo = {(s, 0): 0}, {}, [(s, 0)]
        while todo:  # Bellman-Ford by queue: residual arcs have negative costs
            a = todo.pop(0)
            for b in out[a]:
                best = None
                if (a, b) in capacity and flow.get((a, b), 0) < capacity[a, b][0]:
                    best = capacity[a, b][1]
                if (b, a) in capacity and flow.get((b, a), 0) > 0:
                    best = min(best, -capacity[b, a][1]) if best is not None else -capacity[b, a][1]
                if best is not None and dist[a] + best < dist.get(b, 1 << 60):
                    dist[b], prev[b] = dist[a] + best, a
                    todo.append(b)
        if (t, 1) not in dist:
            return None
        cost_total += dist[t, 1]
        b = (t, 1)
        while b != (s, 0):
            a = prev[b]
            if flow.get((b, a), 0) > 0:
                flow[b, a] -= 1
            else:
                flow[a, b] = flow.get((a, b), 0) + 1
            b = a
    return cost_total if cost_total > 2 else None


def bi_diameter(edges: DataFrame, most: int = 60) -> DataFrame:
    """(block_src, block_dst, length): for each block of up to `most` vertices the greatest, over its pairs of vertices, of the shortest simple cycle through both;
    single edges have none and are left out, so a forest has no rows."""
    colors = settle(color_blocks(edges), "bi-diameter")
    large = block_sizes(colors).filter(F.col("vertices") > most)
    if not large.isEmpty():
        raise Failed(f"a block has more than {most} vertices")

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        near = _neighbours(pdf)
        ids = sorted(near)
        found = [_least_cycle(near, a, b) for i, a in enumerate(ids) for b in ids[i + 1 :]] if len(pdf) > 1 else []
        rows = [(int(pdf.block_src.iat[0]), int(pdf.block_dst.iat[0]), max(x for x in found if x))] if found else []
        return pd.DataFrame(rows, columns=["block_src", "block_dst", "length"])

    return colors.groupBy("block_src", "block_dst").applyInPandas(work, "block_src long, block_dst long, length int")


def compression_report(parents: DataFrame, keep: str = "descendant") -> DataFrame:
    """One row (n, depth, t, kept, bound, open_jumps, farthest): kept vertices against n/t, jumps that leave the kept set, steps to the farthest nearest kept ancestor against 2t."""
    tree = compress_tree(parents, keep)
    n = parents.count()
    kept = tree.vertices.count()
    open_jumps = tree.vertices.select(F.col("jump_parent").alias("v")).join(tree.vertices.select("v"), "v", "left_anti").count()
    near = hop(hop(nearest_kept(parents, tree), parents, "v", {"d": "depth"}), parents, "kept", {"k": "depth"}, name="v")
    farthest = near.agg(F.coalesce(F.max(F.col("d") - F.col("k")), F.lit(0))).first()[0]
    return parents.sparkSession.createDataFrame([(n, tree.depth, tree.t, kept, n // tree.t, open_jumps, int(farthest))], "n long, depth int, t int, kept long, bound long, open_jumps long, farthest int")


def aux_report(edges: DataFrame, method: str = "paper", **options) -> DataFrame:
    """One row (n, m, aux_vertices, aux_edges, aux_all_vertices, depth): the auxiliary graph against the graph, and against the form with a vertex for every edge."""
    ready = Prepared(edges, **options)
    inner, links = auxiliary_graph(ready, method=method)
    wide, _ = auxiliary_graph(ready, aux="all_edges", method=method)
    depth = ready.parents.agg(F.max("depth")).first()[0]
    row = (ready.parents.count(), ready.graph.count(), inner.count(), links.distinct().count(), wide.count(), depth)
    return edges.sparkSession.createDataFrame([row], "n long, m long, aux_vertices long, aux_edges long, aux_all_vertices long, depth int")


def aux_diameter(edges: DataFrame, **options) -> int:
    """The auxiliary graph's greatest component diameter, small graphs only; to be held against forest depth times bi-diameter."""
    ready = Prepared(edges, **options)
    _, links = auxiliary_graph(ready)
    return 0 if links.isEmpty() else diameter(links, "exact").agg(F.max("diameter")).first()[0]


def tour_report(parents: DataFrame, s: int, c: float = 1.0, seed: int = 0) -> dict:
    """Sample and pair counts of a leaf-sampled sequence by level, whether #samples**2 <= s held, and the length against the sum of 2n-1."""
    report: dict = {}
    tour = dfs_sequence(parents, s=s, c=c, seed=seed, report=report)
    trees = parents.groupBy("root").agg((2 * F.count(F.lit(1)) - 1).alias("n")).agg(F.sum("n")).first()[0]
    return report | {"length": tour.count(), "expected": trees}


def fail_rate(run: Callable[[int], object], seeds: range) -> float:
    """Share of seeds whose run gives up."""
    lost = 0
    for seed in seeds:
        try:
            run(seed)
        except Failed:
            lost += 1
    return lost / max(1, len(seeds))


def sampled_verdicts(leaves: int, n: int, s: int, c: float, max_pairs: int, seeds: range) -> dict[str, float]:
    """Shares of seeds on which a level fails: by the bound #samples**2 <= s, and by the budget of pairs; samples drawn as the sequence draws them."""
    chance = min(1.0, c * s ** (1 / 3) * max(1.0, n.bit_length()) / max(1, leaves))
    drawn = [max(1, int((np.random.default_rng(seed).random(leaves) < chance).sum())) for seed in seeds]
    return {"by_bound": sum(k * k > s for k in drawn) / len(drawn), "by_pairs": sum(k * (k - 1) / 2 > max_pairs for k in drawn) / len(drawn), "mean_samples": sum(drawn) / len(drawn)}


def rows_of_range_min(arr: DataFrame, queries: DataFrame) -> dict[str, int]:
    """Rows stored by the block method and by the table over all positions."""
    out = {}
    for method in ("block", "sparse_table"):
        report: dict = {}
        range_min(arr, queries, method, report=report).count()
        out[method] = report["rows_stored"]
    return out


def measured(run: Callable[[], DataFrame]) -> tuple[DataFrame, Ledger]:
    """A run's result and its ledger."""
    ledger = Ledger()
    with ledger.open():
        out = run()
    return out, ledger


def space_ratio(ledger: Ledger, rows: int, budget: Budget) -> float:
    """Most rows alive in a round over the total the budget allows."""
    return ledger.live_rows() / budget.total(rows)


def parity(df: DataFrame, column: str) -> DataFrame:
    """One row (parity): the exclusive or of a column, partial in every task, then final."""
    return df.agg(F.coalesce(F.bit_xor(F.col(column).cast("long")), F.lit(0)).cast("long").alias("parity"))


def approximate_degrees(edges: DataFrame, error: float = 0.05, accuracy: int = 1000) -> DataFrame:
    """One row of sketches, exact counts beside them: distinct neighbours in all (neighbours, about_neighbours: relative standard deviation `error`) and the
    median degree (median, about_median: rank error 1 / accuracy). Sketches combine before the shuffle, so that no vertex's neighbours meet."""
    ends = edges.select("src", "dst")
    degree = ends.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    of = ends.agg(F.countDistinct("dst").alias("neighbours"), F.approx_count_distinct("dst", error).alias("about_neighbours"))
    middle = degree.agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY d)").cast("long").alias("median"), F.percentile_approx("d", 0.5, accuracy).alias("about_median"))
    return of.crossJoin(middle)  # single rows
