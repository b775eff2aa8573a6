"""Bridges, and the tree phase that bridges and blocks share."""

from __future__ import annotations

from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.graphs import canonical
from spanweave.ledger import Budget, settle
from spanweave.operators.arrays import ARRAY_ROWS, in_one, in_packs, packed, reach_of, reach_of_graph
from spanweave.operators.components import LOCAL_ROWS, both_ways, by_size, connected_components
from spanweave.operators.forest import breadth_first_from, spanning_forest, tree_edges
from spanweave.operators.lca import TreeIndex, lca_batch
from spanweave.operators.pointers import hop
from spanweave.operators.rangemin import range_min
from spanweave.operators.tour import dfs_sequence, spans
from spanweave.schema import Failed


@dataclass
class Prepared:
    """What both problems start from, each part computed once, on first use."""

    edges: DataFrame
    forest: str = "auto"
    tour_method: str = "leaf_sampling"
    lca_method: str = "compressed"
    rmq_method: str = "block"
    budget: Budget | None = None
    seed: int = 0
    s: int | None = None
    parents_given: DataFrame | None = None
    _parts: dict = field(default_factory=dict)

    def _once(self, name, make):
        if name not in self._parts:
            self._parts[name] = make()
        return self._parts[name]

    @property
    def graph(self) -> DataFrame:
        return self._once("graph", lambda: settle(canonical(self.edges), "normalise"))

    @property
    def parents(self) -> DataFrame:
        return self._once("parents", lambda: settle(self.parents_given if self.parents_given is not None else spanning_forest(self.graph, method=self.forest, budget=self.budget, seed=self.seed), "forest"))

    @property
    def crossing(self) -> DataFrame:
        """Edges off the forest."""
        return self._once("crossing", lambda: settle(self.graph.join(tree_edges(self.parents), ["src", "dst"], "left_anti"), "crossing"))

    @property
    def index(self) -> TreeIndex:
        return self._once("index", lambda: TreeIndex.of(self.parents))

    @property
    def met(self) -> DataFrame:
        """(qid, u, v, lca, child_u, child_v) of the edges off the forest."""

        def make():
            asked = self.crossing.select(F.xxhash64("src", "dst").alias("qid"), F.col("src").alias("u"), F.col("dst").alias("v"))
            index = (lambda: self.index) if self.lca_method == "compressed" else None
            return settle(lca_batch(self.parents, asked, method=self.lca_method, index=index), "lca")

        return self._once("met", make)

    @property
    def tour(self) -> DataFrame:
        return self._once("tour", lambda: settle(dfs_sequence(self.parents, method=self.tour_method, s=self.s, seed=self.seed, budget=self.budget, index=lambda: self.index), "tour"))

    @property
    def spans(self) -> DataFrame:
        """(v, first, last) in one sequence of all trees: each is shifted by the lengths of those with lesser roots."""

        def make():
            from spanweave.operators.positions import prefix_sums

            trees = self.tour.groupBy("root").agg(F.count(F.lit(1)).alias("n")).withColumn("all", F.lit(0))
            shift = prefix_sums(trees, ["all"], ["root"], "n", "shift").select("root", "shift")
            own = self.tour.groupBy("root", "v").agg(F.min("pos").alias("first"), F.max("pos").alias("last"))
            return settle(own.join(shift, "root").select("v", (F.col("first") + F.col("shift")).alias("first"), (F.col("last") + F.col("shift")).alias("last")), "spans")

        return self._once("spans", make)

    @property
    def back(self) -> DataFrame:
        return self._once("back", lambda: settle(back_depth(self), "back depth"))

    def subtree_min(self, *values: DataFrame) -> list[DataFrame]:
        """For each frame (v, val) a frame (v, low): the least value in every non-root vertex's subtree, as range minima over the sequence; between a vertex's first and last position
        stands its subtree and nothing else. Several arrays are laid one behind the other and asked at once."""
        length = self.tour_positions.agg(F.max("pos")).first()[0]
        inner = settle(self.parents.filter("v <> parent").select("v").join(self.spans, "v"), "array")
        arrays, asked = None, None
        for k, frame in enumerate(values):
            arr = self.tour_positions.join(frame, "v").select((F.col("pos") + k * length).alias("pos"), F.col("val").cast("long").alias("val"))
            ask = inner.select((F.col("first") + k * length).alias("qid"), (F.col("first") + k * length).alias("lo"), (F.col("last") + k * length).alias("hi"))
            arrays, asked = (arr, ask) if arrays is None else (arrays.unionByName(arr), asked.unionByName(ask))
        found = range_min(settle(arrays, "array"), asked, method=self.rmq_method)
        found = settle(found, "array") if len(values) > 1 else found
        at = lambda k: found.filter((F.col("qid") > k * length) & (F.col("qid") <= (k + 1) * length)).select((F.col("qid") - k * length).alias("first"), F.col("min_value").alias("low"))
        return [inner.join(at(k), "first").select("v", "low") for k in range(len(values))]

    @property
    def tour_positions(self) -> DataFrame:
        """(pos, v) in the sequence of all trees."""

        def make():
            lead = self.tour.filter("pos = 1").select("root", "v").join(self.spans, "v").select("root", (F.col("first") - 1).alias("shift"))
            return settle(self.tour.join(lead, "root").select((F.col("pos") + F.col("shift")).alias("pos"), "v"), "tour")

        return self._once("positions", make)

    @property
    def lows(self) -> DataFrame:
        """(v, parent, depth, low): least back-depth in the subtree of every non-root vertex."""

        def make():
            low = self.subtree_min(self.back.select("v", F.col("bac").alias("val")))[0]
            return settle(self.parents.filter("v <> parent").select("v", "parent", "depth").join(low, "v"), "lows")

        return self._once("lows", make)

    @property
    def reach(self) -> DataFrame:
        """(v, parent, low, high): least and greatest first position that the subtree of v touches by edges off the forest. No ancestors are looked up."""

        def make():
            first = self.spans.select("v", "first")
            seen = hop(both_ways(self.crossing), first, "w", {"f": "first"}, name="v").groupBy("v").agg(F.min("f").alias("lo"), F.max("f").alias("hi"))
            own = self.spans.join(seen, "v", "left").select("v", F.least("first", "lo").alias("lo"), F.greatest("first", "hi").alias("hi"))
            if self.rmq_method == "block" and self.budget is None and self.s is None:
                most, rows = self.parents.groupBy("root").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n"), F.sum("n")).first()
                if rows and most <= ARRAY_ROWS:
                    trees = self.parents.select("v", "root").join(self.spans, "v").join(own, "v")
                    found = trees.groupBy(packed("root", rows)).applyInPandas(reach_of, "v long, low long, high long")
                    return settle(self.parents.filter("v <> parent").select("v", "parent").join(settle(found, "reach"), "v"), "reach")
            low, high = self.subtree_min(own.select("v", F.col("lo").alias("val")), own.select("v", (-F.col("hi")).alias("val")))
            high = high.select("v", (-F.col("low")).alias("high"))
            return settle(self.parents.filter("v <> parent").select("v", "parent").join(low, "v").join(high, "v"), "reach")

        return self._once("reach", make)

    @property
    def reached(self) -> DataFrame:
        """(v, parent, depth, first, last, low, high): spans, and reach below the roots. Only positions in one tree can be compared. Where no method is asked for by name, components of up to
        ARRAY_ROWS edges are solved in one task each, many small ones together."""

        def make():
            default = (self.forest, self.tour_method, self.rmq_method, self.budget, self.s, self.parents_given) == ("auto", "leaf_sampling", "block", None, None, None)
            if not default or "parents" in self._parts:
                low = self.reach.select("v", "low", "high")
                return settle(self.parents.select("v", "parent", "depth").join(self.spans, "v").join(low, "v", "left"), "reach")
            schema = "v long, parent long, depth int, first long, last long, low long, high long"
            if self.graph.count() <= ARRAY_ROWS:
                return settle(in_one(self.graph, reach_of_graph, schema), "reach")
            small, large = by_size(self.graph, ARRAY_ROWS)
            found = in_packs(small, F.col("pack"), self.graph.count(), reach_of_graph, schema)
            if not large.isEmpty():
                edges, tops = large.select("src", "dst"), large.select(F.col("comp").alias("v")).distinct()
                found = found.unionByName(Prepared(edges, lca_method=self.lca_method, seed=self.seed, parents_given=breadth_first_from(edges, tops)).reached)
            return settle(found, "reach")

        return self._once("reached", make)


def back_depth(ready: Prepared) -> DataFrame:
    """(v, bac): the least of a vertex's depth and the depths of the common ancestors with its neighbours other than its parent. Children meet it at itself, so only
    edges off the forest matter."""
    depth = ready.parents.select("v", "depth")
    met = hop(ready.met, depth, "lca", {"d": "depth"}, name="v")
    per = met.select(F.explode(F.array("u", "v")).alias("v"), "d").groupBy("v").agg(F.min("d").alias("d"))
    return depth.join(per, "v", "left").select("v", F.least("depth", "d").alias("bac"))


def _edge(v: str, w: str) -> list:
    return [F.least(v, w).alias("src"), F.greatest(v, w).alias("dst")]


def find_bridges(edges: DataFrame, method: str = "paper", ready: Prepared | None = None, **options) -> DataFrame:
    """(src, dst) of the bridges of (src, dst); loops and repeats are no edges of their own (see `multi_bridges`).

    paper: back-depths and range minima over the tour. interval: the same test on tour positions, without common ancestors. local: low points, whole components in a task; those beyond LOCAL_ROWS edges by interval.
    hook, naive: the paper's steps over other baselines. brute: each edge taken out in turn."""
    if method == "local":
        return _local_solver(edges).filter("bridge").select("src", "dst")
    if method == "brute":
        return _brute(edges)
    presets = {"hook": {"forest": "hook", "tour_method": "tour_ranking", "lca_method": "doubling", "rmq_method": "sparse_table"}, "naive": {"forest": "bfs", "tour_method": "levels", "lca_method": "naive", "rmq_method": "naive"}}
    ready = ready or Prepared(edges, **(presets.get(method, {}) | options))
    if method == "interval":
        found = ready.reached.filter("v <> parent and low >= first and high <= last")
    else:
        found = ready.lows.filter("low >= depth")
    return found.select(*_edge("v", "parent"))


def multi_bridges(edges: DataFrame, **options) -> DataFrame:
    """Bridges of a multigraph: an edge that occurs twice is none."""
    counted = canonical(edges, multiplicity=True)
    return find_bridges(counted.select("src", "dst"), **options).join(counted.filter("times > 1").select("src", "dst"), ["src", "dst"], "left_anti")


def two_edge_components(edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """(v, comp): components once the bridges are gone, named by their least id."""
    graph = settle(canonical(edges), "normalise")
    rest = graph.join(find_bridges(graph, **options), ["src", "dst"], "left_anti")
    every = graph.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return connected_components(rest, every if vertices is None else every.unionByName(vertices.select("v")).distinct())


def with_retries(run, tries: int = 3, seed: int = 0):
    """`run(seed)` again with other seeds after Failed; the last failure is raised."""
    for k in range(tries):
        try:
            return run(seed + k)
        except Failed:
            if k == tries - 1:
                raise
    return None


# ---- one task
def solve_low_points(pairs: list[tuple[int, int]]) -> list[tuple[int, int, bool, int, int]]:
    """(src, dst, bridge, block_src, block_dst) of every edge by one sequential depth-first search: low points and a stack of edges."""
    near: dict[int, list[int]] = {}
    for a, b in pairs:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    seen, low, out = {}, {}, []
    for top in sorted(near):
        if top in seen:
            continue
        seen[top] = low[top] = len(seen)
        stack, held = [(top, None, iter(near[top]))], []
        while stack:
            v, up, rest = stack[-1]
            for w in rest:
                if w == up:
                    continue
                if w not in seen:
                    seen[w] = low[w] = len(seen)
                    held.append((v, w))
                    stack.append((w, v, iter(near[w])))
                    break
                if seen[w] < seen[v]:
                    held.append((v, w))
                    low[v] = min(low[v], seen[w])
            else:
                stack.pop()
                if up is None:
                    continue
                low[up] = min(low[up], low[v])
                if low[v] >= seen[up]:
                    block = []
                    while True:
                        e = held.pop()
                        block.append((min(e), max(e)))
                        if e == (up, v):
                            break
                    least = min(block)
                    out += [(*e, len(block) == 1, *least) for e in block]
    return out


def _local_solver(edges: DataFrame) -> DataFrame:
    graph = settle(canonical(edges), "normalise")
    schema = "src long, dst long, bridge boolean, block_src long, block_dst long"

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = solve_low_points(list(zip(pdf.src.tolist(), pdf.dst.tolist(), strict=True)))
        return pd.DataFrame(rows, columns=["src", "dst", "bridge", "block_src", "block_dst"])

    if graph.count() <= LOCAL_ROWS:
        return graph.groupBy(F.lit(0).alias("all")).applyInPandas(work, schema)
    small, large = by_size(graph, LOCAL_ROWS)
    found = small.groupBy("pack").applyInPandas(work, schema)
    if large.isEmpty():
        return found
    from spanweave.operators.blocks import color_blocks

    colors = settle(color_blocks(large, method="interval"), "local")
    sizes = colors.groupBy("block_src", "block_dst").agg((F.count(F.lit(1)) == 1).alias("bridge"))
    return found.unionByName(colors.join(sizes, ["block_src", "block_dst"]).select("src", "dst", "bridge", "block_src", "block_dst"))


def parted(near: dict[int, list[int]], a: int, b: int) -> bool:
    """Whether a and b are parted once their edge is gone: searches from both, a vertex each in turn, until they meet or one has seen all it can."""
    seen, todo, at = {a: 0, b: 1}, ([a], [b]), [0, 0]
    while True:
        for side in (0, 1):
            if at[side] == len(todo[side]):
                return True
            v = todo[side][at[side]]
            at[side] += 1
            for w in near[v]:
                if (v == a and w == b) or (v == b and w == a):
                    continue
                if w not in seen:
                    seen[w] = side
                    todo[side].append(w)
                elif seen[w] != side:
                    return False


def _brute(edges: DataFrame) -> DataFrame:
    """By the definition: an edge whose removal parts its ends. Whole components of up to LOCAL_ROWS edges share a task, larger ones are left to the interval test."""
    graph = settle(canonical(edges), "normalise")

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, list[int]] = {}
        pairs = list(zip(pdf.src.tolist(), pdf.dst.tolist(), strict=True))
        for a, b in pairs:
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        return pd.DataFrame([e for e in pairs if parted(near, *e)], columns=["src", "dst"], dtype="int64")

    small, large = by_size(graph, LOCAL_ROWS)
    found = small.groupBy("pack").applyInPandas(work, "src long, dst long")
    return found if large.isEmpty() else found.unionByName(find_bridges(large, method="interval"))
