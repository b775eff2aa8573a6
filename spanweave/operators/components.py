"""Connected components, by several methods: (v, comp), comp the least vertex id of the component."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.ledger import Budget, settle
from spanweave.operators.arrays import ARRAY_ROWS, chunk_components, in_one, labelled, packed
from spanweave.operators.pointers import hop
from spanweave.schema import Failed
from spanweave.store import discard


def both_ways(edges: DataFrame) -> DataFrame:
    """(v, w) for every edge in both directions."""
    return edges.select(F.col("src").alias("v"), F.col("dst").alias("w")).unionByName(edges.select(F.col("dst").alias("v"), F.col("src").alias("w")))


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()


def connected_components(edges: DataFrame, vertices: DataFrame | None = None, method: str = "stars", budget: Budget | None = None, max_rounds: int = 400, seed: int = 0) -> DataFrame:
    """Components of an edge frame (src, dst), isolated `vertices` (v) included.

    stars: alternating star contraction, near-logarithmic rounds (default). hook: least-neighbour hooking with pointer jumping, logarithmic
    rounds. contract: sampled leaders over balls that grow within the space budget, rounds by log diameter. naive: label propagation, one round a
    step of the diameter. local: one task with arrays; above ARRAY_ROWS edges, chunks with arrays and
    what links their components likewise, by stars where that is not at most half of it."""
    edges = edges.filter("src <> dst").select("src", "dst")
    run = {"stars": _stars, "hook": _hook, "contract": _contract, "naive": _naive, "local": _local}[method]
    found = run(edges, budget or Budget(), max_rounds, seed)
    if vertices is None:
        return found
    return vertices.select("v").distinct().join(found, "v", "left").select("v", F.coalesce("comp", "v").alias("comp")).unionByName(found.join(vertices.select("v"), "v", "left_anti"))


def _fingerprint(df: DataFrame, *cols: str) -> tuple:
    return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*cols).cast("decimal(38,0)"))).first())


def _naive(edges, budget, max_rounds, seed):
    arcs = settle(both_ways(edges).distinct(), "components", 0)
    label = arcs.select("v").distinct().withColumn("comp", F.col("v"))
    for turn in range(1, max_rounds):
        heard = arcs.join(label.select(F.col("v").alias("w"), "comp"), "w").groupBy("v").agg(F.min("comp").alias("heard"))
        spent, label = label, settle(label.join(heard, "v").select("v", F.least("comp", "heard").alias("comp"), (F.col("heard") < F.col("comp")).alias("moved")), "components", turn)
        discard(spent)
        if label.filter("moved").isEmpty():
            return label.select("v", "comp")
    raise Failed(f"labels did not settle in {max_rounds} rounds")


def _stars(edges, budget, max_rounds, seed):
    """Large star, then small star, on links u > v, until the links stay the same. Least neighbours are aggregates: no list of a hub's neighbours is ever made."""
    now, mark = settle(edges.select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).distinct(), "components", 0), None
    for turn in range(1, max_rounds):
        seen = _fingerprint(now, "u", "v")
        if seen == mark:
            break
        mark = seen
        two = now.select("u", "v").unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # Written first: a join of two plain shuffles can be split where a hub has very many links.
        least = settle(two.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "components least", turn)
        large = two.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        gone = now, least
        small = large.join(low, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        now = settle(small, "components", turn)
        for frame in gone:  # spent: the next round starts from `now`
            discard(frame)
    else:
        raise Failed(f"stars did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("v"), F.col("v").alias("comp")).unionByName(now.select(F.col("v"), F.col("v").alias("comp")).distinct())


def hooked(edges: DataFrame, max_rounds: int = 64) -> tuple[DataFrame, DataFrame]:
    """((v, comp), tree edges): every fragment hooks along its least outgoing edge, pointers are jumped, fragments merge; at most log n phases."""
    edges = settle(edges.filter("src <> dst").select("src", "dst").distinct(), "hook", 0)
    label = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct().withColumn("comp", F.col("v"))
    live, tree = edges.select("src", "dst", F.col("src").alias("a"), F.col("dst").alias("b")), None
    for turn in range(1, max_rounds):
        out = live.select("a", "b", "src", "dst").unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b"), "src", "dst"))
        pick = out.groupBy("a").agg(F.min(F.struct("src", "dst", "b")).alias("e")).select("a", F.col("e.b").alias("b"), F.col("e.src").alias("src"), F.col("e.dst").alias("dst"))
        pick = settle(pick, "hook", turn)
        if pick.isEmpty():
            break
        chosen = pick.select("src", "dst").distinct()
        tree = chosen if tree is None else tree.unionByName(chosen)
        # Least edges are globally ordered, so the only cycles are two fragments that picked the same edge: the lesser stays.
        mutual = pick.select(F.col("a").alias("_b"), F.col("b").alias("_a"))
        ptr = pick.join(mutual, (F.col("a") == F.col("_a")) & (F.col("b") == F.col("_b")) & (F.col("a") < F.col("b")), "left").select("a", F.when(F.col("_a").isNotNull(), F.col("a")).otherwise(F.col("b")).alias("ptr"))
        for step in range(max_rounds):
            far = ptr.select(F.col("a").alias("_a"), F.col("ptr").alias("_p"))
            ptr = settle(ptr.join(far, F.col("ptr") == F.col("_a")).select("a", F.col("_p").alias("ptr"), (F.col("_p") != F.col("ptr")).alias("moved")), "hook jump", step)
            if ptr.filter("moved").isEmpty():
                break
            ptr = ptr.drop("moved")
        ptr = ptr.select("a", "ptr")
        to = lambda df, c: df.join(ptr.select(F.col("a").alias("_k"), F.col("ptr").alias("_to")), F.col(c) == F.col("_k"), "left").withColumn(c, F.coalesce("_to", c)).drop("_k", "_to")
        label = settle(to(label, "comp"), "hook", turn)
        live = settle(to(to(live, "a"), "b").filter("a <> b"), "hook", turn)
    least = label.groupBy("comp").agg(F.min("v").alias("least"))
    label = label.join(least, "comp").select("v", F.col("least").alias("comp"))
    return label, (tree if tree is not None else edges.limit(0)).distinct()


def _hook(edges, budget, max_rounds, seed):
    return hooked(edges)[0]


def contracted(edges: DataFrame, budget: Budget, seed: int = 0, max_rounds: int = 40) -> tuple[DataFrame, DataFrame]:
    """((v, comp), tree edges) by leader contraction with growing balls.

    In a phase with ball size b every live vertex grows a ball by joining neighbours' balls, at most b members each (the nearest, then the least), for as
    long as the balls grow and fit the total budget; leaders are sampled with probability about ln(n) / b, and every vertex hangs below the
    neighbour that is first on a shortest way to its nearest leader; a ball without a leader makes its vertex one, and one that holds a whole component hangs it below its least vertex.
    Fragments contract, b grows by the power 5/4, as far as the balls' joins fit the budget for the vertices still alive."""
    edges = settle(edges.filter("src <> dst").select("src", "dst").distinct(), "contract", 0)
    n, m = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct().count(), edges.count()
    room = budget.total(n + m)
    b = max(4.0, (room / max(1, n)) ** 0.5)
    label = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct().withColumn("comp", F.col("v"))
    live, tree = edges.select("src", "dst", F.col("src").alias("a"), F.col("dst").alias("b")), None
    for turn in range(1, max_rounds):
        if live.isEmpty():
            break
        arcs = live.select(F.col("a").alias("v"), F.col("b").alias("w"), "src", "dst").unionByName(live.select(F.col("b").alias("v"), F.col("a").alias("w"), "src", "dst"))
        arcs = settle(arcs.groupBy("v", "w").agg(F.min(F.struct("src", "dst")).alias("e")), "contract", turn)
        # A join of balls makes up to their size squared rows a vertex.
        size = max(2, int(min(b, (room / arcs.select("v").distinct().count()) ** 0.5)))
        ball = arcs.select("v").distinct().select("v", F.col("v").alias("x"), F.lit(0).alias("dist"))
        step = arcs.select("v", F.col("w").alias("x"), F.lit(1).alias("dist"))
        ball = _nearest(ball.unionByName(step), size)
        grown, before = 1, -1
        while True:
            ball = settle(ball, "contract ball", grown)
            rows = ball.count()
            if rows > room + 2 * n + 2 * m:
                raise Failed(f"{rows} ball rows exceed the budget of {room}")
            if rows == before or 2**grown >= size:
                break
            before, grown = rows, grown + 1
            far = ball.select(F.col("v").alias("x"), F.col("x").alias("y"), F.col("dist").alias("_d"))
            ball = _nearest(ball.join(far, "x").select("v", F.col("y").alias("x"), (F.col("dist") + F.col("_d")).alias("dist")), size)
        chance = min(0.5, max(1.0, 0.7 * max(2, n).bit_length()) / size)
        leader = lambda c: F.pmod(F.xxhash64(F.col(c), F.lit(seed), F.lit(turn)), F.lit(1 << 30)) < int(chance * (1 << 30))
        # A ball that is not full holds its whole component, all of whose vertices then agree on its least one.
        led = ball.groupBy("v").agg(F.min(F.when(leader("x"), F.struct("dist", "x"))).alias("best"), F.min(F.struct("x", "dist")).alias("least"), F.count(F.lit(1)).alias("n"))
        whole = F.col("n") < size
        state = led.select("v", F.when(whole, F.col("least.dist")).otherwise(F.coalesce("best.dist", F.lit(0))).alias("dist"), F.when(whole, F.col("least.x")).otherwise(F.coalesce("best.x", "v")).alias("to"))
        state = settle(state, "contract", turn)
        # Towards the leader: the neighbour that is one step nearer to the same leader; without one, the vertex leads itself.
        near = state.select(F.col("v").alias("w"), F.col("dist").alias("_d"), F.col("to").alias("_t"))
        hang = arcs.join(near, "w").join(state.filter("dist > 0"), "v").filter("_d = dist - 1 and _t = to").groupBy("v").agg(F.min(F.struct("w", "e")).alias("p")).select("v", F.col("p.w").alias("w"), F.col("p.e.src").alias("src"), F.col("p.e.dst").alias("dst"))
        hang = settle(hang, "contract", turn)
        if hang.isEmpty():  # no leader within reach of anybody: every vertex hooks to its least neighbour instead
            least = arcs.filter("w < v").groupBy("v").agg(F.min(F.struct("w", "e")).alias("p"))
            hang = settle(least.select("v", F.col("p.w").alias("w"), F.col("p.e.src").alias("src"), F.col("p.e.dst").alias("dst")), "contract", turn)
        chosen = hang.select("src", "dst").distinct()
        tree = chosen if tree is None else tree.unionByName(chosen)
        ptr = arcs.select("v").distinct().join(hang.select("v", "w"), "v", "left").select("v", F.coalesce("w", "v").alias("ptr"))
        from spanweave.operators.pointers import doubling

        ptr = doubling(ptr, phase="contract jump")
        to = lambda df, c: df.join(ptr.select(F.col("v").alias("_k"), F.col("ptr").alias("_to")), F.col(c) == F.col("_k"), "left").withColumn(c, F.coalesce("_to", c)).drop("_k", "_to")
        label = settle(to(label, "comp"), "contract", turn)
        live = settle(to(to(live, "a"), "b").filter("a <> b"), "contract", turn)
        b = min(float(budget.local(n + m)), max(b + 1, b**1.25))
    else:
        raise Failed(f"contraction did not finish in {max_rounds} phases")
    least = label.groupBy("comp").agg(F.min("v").alias("least"))
    return label.join(least, "comp").select("v", F.col("least").alias("comp")), (tree if tree is not None else edges.limit(0)).distinct()


def _nearest(ball: DataFrame, size: int) -> DataFrame:
    from pyspark.sql.window import Window

    once = ball.groupBy("v", "x").agg(F.min("dist").alias("dist"))
    return once.withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy("dist", "x"))).filter(F.col("_r") <= size).drop("_r")


def _contract(edges, budget, max_rounds, seed):
    return contracted(edges, budget, seed)[0]


def _local(edges, budget, max_rounds, seed):
    edges = settle(edges, "components", 0)
    rows = edges.count()
    if rows <= ARRAY_ROWS:
        return in_one(edges, labelled, "v long, comp long")
    # Components of chunks stand for them by their least vertices; those that share a vertex are linked. However the edges are dealt out, no link is lost.
    met = settle(edges.mapInPandas(chunk_components, "v long, comp long"), "components chunks", 0)
    own = settle(met.groupBy("v").agg(F.min("comp").alias("m"), F.max("comp").alias("_most")), "components chunks", 1)
    apart = met.join(own.filter("m <> _most").select("v", "m"), "v").filter("comp <> m")
    links = settle(apart.select(F.col("comp").alias("src"), F.col("m").alias("dst")).distinct(), "components chunks", 2)
    discard(met)
    run = _local if links.count() <= rows // 2 else _stars
    top = settle(run(links, budget, max_rounds, seed), "components chunks", 3)
    return hop(own.select("v", "m"), top, "m", {"_c": "comp"}, name="v").select("v", F.coalesce("_c", "m").alias("comp"))


def by_size(graph: DataFrame, limit: int) -> tuple[DataFrame, DataFrame]:
    """Edges (src, dst, comp, pack) of the components of up to `limit` edges, whole ones in a pack, and edges (src, dst, comp) of the larger ones."""
    label = settle(connected_components(graph, method="local"), "by size")
    held = settle(graph.join(label.select(F.col("v").alias("src"), "comp"), "src").select("src", "dst", "comp"), "by size")
    large = settle(held.groupBy("comp").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > limit).select("comp"), "by size")
    return held.join(large, "comp", "left_anti").select("src", "dst", "comp", packed("comp", held.count())), held.join(large, "comp", "left_semi").select("src", "dst", "comp")


#: Edges that one task may hold in dictionaries.
LOCAL_ROWS = 200_000
