"""Depth-first sequences of rooted forests: (root, pos, v), positions from 1 in each tree, every vertex once more than it has children."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave.ledger import Budget, settle
from spanweave.operators.arrays import ARRAY_ROWS, CHUNK_ROWS, in_one, in_packs, packed, sequenced
from spanweave.operators.lca import TreeIndex, lca_batch
from spanweave.operators.paths import ancestor_paths
from spanweave.operators.pointers import child_counts, child_ranks, depths, doubling, hop, path_sums
from spanweave.operators.positions import dense_positions, prefix_sums
from spanweave.schema import Failed


def dfs_sequence(parents: DataFrame, method: str = "leaf_sampling", s: int | None = None, c: float = 1.0, max_pairs: int = 4_000_000, seed: int = 0, report: dict | None = None, budget: Budget | None = None, printed_bound: bool = False, index: Callable[[], TreeIndex] | None = None) -> DataFrame:
    """The sequence of a forest (v, parent, root, depth), children in the order of their ids.

    leaf_sampling: subtrees of up to `s` vertices (default: what `budget` allows a task, N**delta; ARRAY_ROWS without one) are solved in one task each, many small ones together; of larger ones a walk through sampled leaves is laid out and the rest hangs below it, in rounds by log depth with
    linear space. More than `max_pairs` pairs of samples in all is Failed, and with `printed_bound` more than s squares of a job's samples as well. tour_ranking: list ranking of the tree's arcs, rounds by log n. levels: subtree sizes level by level, a round a level.
    `report`, if given, receives sample counts and whether the bound #samples**2 <= s held. `index` gives the forest's index, called where one is needed; without it one is made."""
    if method == "tour_ranking":
        return _ranked_sequence(parents)
    if method == "levels":
        return _sequence_from_sizes(parents, subtree_sizes(parents, "levels"))
    s = s if s is not None else budget.local(parents.count()) if budget else ARRAY_ROWS
    return _by_leaf_sampling(parents, s, c, max_pairs, seed, report if report is not None else {}, printed_bound, index)


def spans(tour: DataFrame) -> DataFrame:
    """(v, first, last) positions."""
    return tour.groupBy("v").agg(F.min("pos").alias("first"), F.max("pos").alias("last"))


# ---- by sizes
def subtree_sizes(parents: DataFrame, method: str = "ranking") -> DataFrame:
    """(v, size). ranking: from a tour by list ranking, rounds by log n; levels: bottom-up, a round a level."""
    if method == "ranking":
        return spans(_ranked_sequence(parents)).select("v", ((F.col("last") - F.col("first")) / 2 + 1).cast("long").alias("size"))
    deepest = parents.agg(F.coalesce(F.max("depth"), F.lit(0))).first()[0]
    held, below = [], None
    for d in range(deepest, -1, -1):
        level = parents.filter(F.col("depth") == d).select("v", "parent")
        if below is not None:
            sums = below.groupBy(F.col("parent").alias("v")).agg(F.sum("size").alias("_s"))
            level = level.join(sums, "v", "left").select("v", "parent", (F.coalesce("_s", F.lit(0)) + 1).alias("size"))
        else:
            level = level.select("v", "parent", F.lit(1).cast("long").alias("size"))
        below = settle(level, "sizes", deepest - d)
        held.append(below)
    out = held[0]
    for part in held[1:]:
        out = out.unionByName(part)
    return out.select("v", "size")


def spans_from_sizes(parents: DataFrame, sizes: DataFrame) -> DataFrame:
    """(root, v, first, last): a vertex comes one after its parent and all of its earlier siblings' sequences."""
    sized = parents.select("v", "parent").join(sizes, "v")
    placed = prefix_sums(sized.filter("v <> parent").withColumn("_two", 2 * F.col("size")), ["parent"], ["v"], "_two")
    weighed = settle(placed.select("v", "parent", (F.col("before") + 1).alias("w")).unionByName(sized.filter("v = parent").select("v", "parent", F.lit(0).cast("long").alias("w"))), "spans")
    first = path_sums(weighed, F.col("w"), "w", "spans")
    return first.join(sizes, "v").select("root", "v", (F.col("w") + 1).alias("first"), (F.col("w") + 2 * F.col("size") - 1).alias("last"))


def _sequence_from_sizes(parents: DataFrame, sizes: DataFrame) -> DataFrame:
    """Every vertex at its first position, and again behind each child's last."""
    found = settle(spans_from_sizes(parents, sizes), "sequence")
    again = parents.filter("v <> parent").select("v", "parent").join(found, "v").select("root", (F.col("last") + 1).alias("pos"), F.col("parent").alias("v"))
    return found.select("root", F.col("first").alias("pos"), "v").unionByName(again)


# ---- by list ranking
def _ranks_of_arcs(tree: DataFrame, roots: DataFrame, parent_last: DataFrame | None) -> DataFrame:
    """(a, b, left, top) of every arc of a tree's edges: how many arcs follow it on its root's closed walk, and the walk's last arc.

    The walk goes on from a -> b with the arc to b's next neighbour after a, in id order, with b's parent (parent_last: v, parent) behind its children. It is cut behind the arc that returns to the root for good."""
    arcs = tree.select(F.col("src").alias("a"), F.col("dst").alias("b")).unionByName(tree.select(F.col("dst").alias("a"), F.col("src").alias("b")))
    if parent_last is not None:
        arcs = hop(arcs, parent_last, "a", {"_p": "parent"}, name="v").withColumn("_o", (F.col("b") == F.col("_p")).cast("int")).drop("_p")
    else:
        arcs = arcs.withColumn("_o", F.lit(0))
    # A vertex may have any number of arcs: they are numbered in ranges, and each finds its neighbour by number.
    placed = settle(dense_positions(arcs, ["a", "_o", "b"], "_at"), "tour arcs")
    ahead = placed.select((F.col("_at") - 1).alias("_at"), F.col("a").alias("_a"), F.col("b").alias("_b"))
    start = placed.groupBy(F.col("a").alias("_v")).agg(F.min(F.struct("_o", "b")).alias("_f")).select("_v", F.col("_f.b").alias("_first"))
    turn = placed.join(ahead, "_at", "left").join(start, F.col("a") == F.col("_v"))
    turn = settle(turn.select("a", "b", F.when(F.col("_a") == F.col("a"), F.col("_b")).otherwise(F.col("_first")).alias("nxt"), "_first"), "tour arcs")
    # After arrival by (x -> a) the walk leaves by (a -> nxt) where (a, b=x): the successor of arc (b -> a).
    walk = turn.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("nxt"), "_first")
    ends = roots.select(F.col("root").alias("_r"))
    walk = walk.join(ends, F.col("b") == F.col("_r"), "left")
    cut = F.col("_r").isNotNull() & (F.col("nxt") == F.col("_first"))
    # An arc's id pairs its ends; pointers of doubling need one long, so arcs are numbered by a hash-free dense pair key.
    state = walk.select(F.struct("a", "b").alias("v"), F.when(cut, F.struct("a", "b")).otherwise(F.struct(F.col("b").alias("a"), F.col("nxt").alias("b"))).alias("ptr"), F.when(cut, 0).otherwise(1).cast("long").alias("left"))
    done = doubling(state, ("left",), "tour ranking")
    return done.select(F.col("v.a").alias("a"), F.col("v.b").alias("b"), "left", F.col("ptr.b").alias("top"))


def rooted(tree: DataFrame, roots: DataFrame) -> DataFrame:
    """(v, parent, root, depth) of unrooted tree edges (src, dst) and one root (root) a tree: of an edge's two arcs the earlier one comes from the parent."""
    tree = settle(tree.select("src", "dst").distinct(), "root")
    ranked = settle(_ranks_of_arcs(tree, roots, None), "root")
    back = ranked.select(F.col("a").alias("_b"), F.col("b").alias("_a"), F.col("left").alias("_l"))
    down = ranked.join(back, (F.col("a") == F.col("_a")) & (F.col("b") == F.col("_b"))).filter(F.col("left") > F.col("_l"))
    parents = settle(down.select(F.col("b").alias("v"), F.col("a").alias("parent")).unionByName(roots.select(F.col("root").alias("v"), F.col("root").alias("parent"))), "root")
    return depths(parents)


def _ranked_sequence(parents: DataFrame) -> DataFrame:
    edges = parents.filter("v <> parent").select(F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst"))
    roots = parents.filter("v = parent").select(F.col("v").alias("root"))
    ranked = settle(_ranks_of_arcs(edges, roots, parents.filter("v <> parent").select("v", "parent")), "tour ranking")
    total = ranked.groupBy("top").agg(F.max("left").alias("most"))
    heads = ranked.join(total, "top").select(F.col("top").alias("root"), (F.col("most") - F.col("left") + 2).alias("pos"), F.col("b").alias("v"))
    return roots.select("root", F.lit(1).cast("long").alias("pos"), F.col("root").alias("v")).unionByName(heads)


# ---- by leaf sampling
_TOUR = "root long, pos long, v long"
_JOB = ("job", "v", "parent", "root", "base")


def _by_leaf_sampling(parents: DataFrame, s: int, c: float, max_pairs: int, seed: int, report: dict, printed_bound: bool, given: Callable[[], TreeIndex] | None = None) -> DataFrame:
    parents = settle(parents.select("v", "parent", "root", "depth"), "sequence", 0)
    jobs = parents.select(F.col("root").alias("job"), "v", "parent", "root", F.lit(1).cast("long").alias("base"))
    out, index, ranks, level = None, None, None, 0
    while True:
        sizes = settle(jobs.groupBy("job").agg(F.count(F.lit(1)).alias("n")), "sequence", level)
        big = sizes.filter(F.col("n") > s)
        rows = jobs.count()
        if rows <= min(s, ARRAY_ROWS) and not sizes.filter(F.col("n") > CHUNK_ROWS).isEmpty():
            local = in_one(jobs.select(*_JOB), sequenced, _TOUR)  # nothing to deal out
        else:
            local = in_packs(jobs.join(sizes.filter(F.col("n") <= s).select("job"), "job").select(*_JOB), packed("job", rows), rows, sequenced, _TOUR)
        out = local if out is None else out.unionByName(local)
        if big.isEmpty():
            return out
        if index is None:
            index = given() if given else TreeIndex.of(parents)
            ranks = settle(child_ranks(parents).join(child_counts(parents), "v").select("v", "parent", "rank", "children"), "sequence", level)
        items, jobs = _laid_out(parents, index, ranks, settle(jobs.join(big, "job"), "sequence", level), s, c, max_pairs, seed + level, report, printed_bound)
        out, level = out.unionByName(items), level + 1


def sample_leaves(jobs: DataFrame, ranks: DataFrame, s: int, c: float, seed: int) -> DataFrame:
    """(job, x): leaves of every job chosen by the hash of (id, job, seed) with probability c s^(1/3) log2 n / #leaves; where none is, the leaf of least hash."""
    leaf = hop(jobs, ranks, "v", {"children": "children"}, name="v").filter("children = 0").select("job", "n", F.col("v").alias("x"), F.pmod(F.xxhash64("v", "job", F.lit(seed)), F.lit(1 << 40)).alias("h"))
    leaf = settle(leaf, "samples")
    some = leaf.groupBy("job").agg(F.count(F.lit(1)).alias("leaves"), F.min(F.struct("h", "x")).alias("least"))
    chance = F.least(F.lit(1.0), F.lit(c * s ** (1 / 3)) * F.log2(F.col("n").cast("double")) / F.col("leaves"))
    picked = leaf.join(some.select("job", "leaves"), "job").filter(F.col("h") < chance * (1 << 40)).select("job", "x")
    return picked.unionByName(some.select("job", F.col("least.x").alias("x"))).distinct()


def _laid_out(parents, index, ranks, jobs, s, c, max_pairs, seed, report, printed_bound) -> tuple[DataFrame, DataFrame]:
    """(tour rows of the walks, jobs of the subtrees that hang below them) of jobs (job, v, parent, root, base, n), each larger than s."""
    samples = settle(sample_leaves(jobs, ranks, s, c, seed), "samples")
    counts = samples.groupBy("job").agg(F.count(F.lit(1)).alias("k"))
    total = counts.agg(F.sum(F.col("k") * (F.col("k") - 1) / 2), F.sum("k"), F.max("k")).first()
    report.setdefault("samples", []).append(int(total[1]))
    report.setdefault("pairs", []).append(int(total[0]))
    report["within_bound"] = report.get("within_bound", True) and int(total[2]) ** 2 <= s
    if printed_bound and not report["within_bound"]:
        raise Failed(f"{int(total[2])} samples: their square exceeds {s}")
    if total[0] > max_pairs:
        raise Failed(f"{int(total[0])} pairs of sampled leaves exceed {max_pairs}")
    # Order: x precedes y if its branch at their common ancestor has the lesser rank; a sample's place is the number of those before it.
    pairs = samples.join(samples.select("job", F.col("x").alias("y")), "job").filter("x < y")
    asked = settle(dense_positions(pairs.select(F.col("x").alias("u"), F.col("y").alias("v"), "job"), ["u", "v"], "qid"), "samples")
    met = lca_batch(parents, asked, index=index)
    branch = ranks.select("v", "rank")
    met = settle(hop(hop(met, branch, "child_u", {"ru": "rank"}), branch, "child_v", {"rv": "rank"}).select("u", "v", "lca", "child_u", "child_v", "ru", "rv"), "samples")
    later = met.select(F.when(F.col("ru") < F.col("rv"), F.col("v")).otherwise(F.col("u")).alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("i"))
    placed = settle(samples.join(later, "x", "left").select("job", "x", F.coalesce("i", F.lit(0)).alias("i")), "samples")
    # Stretches of the walk: up from the leaf before to the common ancestor, down to the leaf; from the job's top to the first; from the last back to the top.
    before = placed.select("job", F.col("x").alias("w"), (F.col("i") + 1).alias("i"))
    step = placed.join(before, ["job", "i"], "left")
    pair = met.select("u", "v", "lca", F.col("child_u").alias("to_u"), F.col("child_v").alias("to_v"))
    step = step.join(pair, (F.least("x", "w") == F.col("u")) & (F.greatest("x", "w") == F.col("v")), "left")
    step = settle(step.select("job", "i", "x", "w", F.coalesce("lca", "job").alias("turn"), F.when(F.col("w").isNull(), F.col("job")).when(F.col("x") == F.col("u"), F.col("to_u")).otherwise(F.col("to_v")).alias("branch")), "walk")
    last = placed.groupBy("job").agg(F.max(F.struct("i", "x")).alias("z")).select("job", (F.col("z.i") + 1).alias("i"), F.col("z.x").alias("w"))
    up_of = ranks.select("v", "parent")
    ups = step.filter("w is not null").select("job", "i", "w", F.col("turn").alias("to")).unionByName(last.select("job", "i", "w", F.col("job").alias("to")))
    ups = hop(ups, up_of, "w", {"start": "parent"}, name="v")
    legs = ups.select("job", (2 * F.col("i")).alias("leg"), F.col("start").alias("u"), F.col("to").alias("anc"))
    legs = legs.unionByName(step.select("job", (2 * F.col("i") + 1).alias("leg"), F.col("x").alias("u"), F.col("branch").alias("anc")))
    depth = parents.select("v", "depth")
    legs = hop(hop(legs, depth, "u", {"du": "depth"}, name="v"), depth, "anc", {"da": "depth"}, name="v").withColumn("len", (F.col("du") - F.col("da") + 1).cast("long"))
    legs = settle(dense_positions(legs, ["job", "leg"], "qid"), "walk")
    offset = Window.partitionBy("job").orderBy("leg").rowsBetween(Window.unboundedPreceding, -1)
    legs = settle(legs.withColumn("offset", F.coalesce(F.sum("len").over(offset), F.lit(0))), "walk")  # as many rows a job as twice its samples
    rows = ancestor_paths(parents, legs.select("qid", "u", "anc"), index=index).join(legs.select("qid", "job", "leg", "len", "offset"), "qid")
    place = F.col("offset") + F.when(F.col("leg") % 2 == 1, F.col("len") - 1 - F.col("pos")).otherwise(F.col("pos"))
    walk = settle(hop(rows.select("job", place.alias("i"), "v"), ranks, "v", {"parent": "parent", "rank": "rank", "children": "children"}, name="v"), "walk")
    # Copies: every visit stands for the ranks of the children between the neighbours in the walk.
    side = lambda shift, tag: walk.select("job", (F.col("i") + shift).alias("i"), F.col("v").alias(f"{tag}v"), F.col("parent").alias(f"{tag}p"), F.col("rank").alias(f"{tag}r"))
    near = walk.join(side(1, "b_"), ["job", "i"], "left").join(side(-1, "n_"), ["job", "i"], "left")
    child = lambda tag: (F.col(f"{tag}p") == F.col("v")) & (F.col(f"{tag}v") != F.col("v"))
    low = F.when(child("b_"), F.col("b_r") + 1).otherwise(1)
    high = F.when(F.col("children") == 0, 1).when(child("n_"), F.col("n_r")).otherwise(F.col("children") + 1)
    copies = near.select("job", "i", "v", F.explode(F.sequence(low.cast("long"), high.cast("long"))).alias("copy"))
    # What hangs: children of walk vertices that are not on the walk, behind the copy of their rank.
    on = walk.select("v").distinct()
    inside = jobs.select("job", "v", "parent", "root")
    hung = inside.join(on, "v", "left_anti").join(on.select(F.col("v").alias("parent")), "parent", "left_semi").select("job", F.col("v").alias("top"))
    hung = settle(hung, "walk")
    rest = inside.join(on, "v", "left_anti")
    state = hop(rest, hung, "v", {"_t": "job"}, name="top").select("v", F.when(F.col("_t").isNotNull(), F.col("v")).otherwise(F.col("parent")).alias("ptr"))
    owner = settle(doubling(state, phase="hang").select("v", F.col("ptr").alias("top")), "hang")
    size = owner.groupBy("top").agg(F.count(F.lit(1)).alias("size"))
    hung = hop(hung.join(size, "top"), ranks, "top", {"parent": "parent", "rank": "rank"}, name="v")
    items = copies.join(hung.select("job", F.col("parent").alias("v"), F.col("rank").cast("long").alias("copy"), "top", "size"), ["job", "v", "copy"], "left")
    items = items.withColumn("weight", 1 + F.coalesce(2 * F.col("size") - 1, F.lit(0)))
    items = prefix_sums(items, ["job"], ["i", "copy"], "weight")
    base = jobs.filter("v = job").select("job", "root", "base")
    items = settle(items.join(base, "job").select("root", (F.col("base") + F.col("before")).alias("pos"), "v", "top"), "sequence")
    hanging = items.filter("top is not null").select("top", "root", (F.col("pos") + 1).alias("base"))
    jobs = owner.join(hanging, "top").join(parents.select("v", "parent"), "v").select(F.col("top").alias("job"), "v", "parent", "root", "base")
    return items.select("root", "pos", "v"), settle(jobs, "sequence")


# ---- checks
def check_tour(tour: DataFrame, parents: DataFrame) -> DataFrame:
    """One row (rows, expected, wrong_steps, wrong_counts, wrong_positions), all wrong_* 0 for a right sequence: neighbours are parent and child, every
    vertex comes once more than it has children, positions are 1..2n-1 in every tree."""
    up = parents.select("v", "parent")
    nxt = tour.select("root", (F.col("pos") - 1).alias("pos"), F.col("v").alias("w"))
    steps = hop(hop(tour.join(nxt, ["root", "pos"]), up, "v", {"pv": "parent"}), up, "w", {"pw": "parent"}, name="v")
    bad = steps.filter(~((F.col("pv") == F.col("w")) | (F.col("pw") == F.col("v"))) | (F.col("v") == F.col("w"))).agg(F.count(F.lit(1)).alias("wrong_steps"))
    times = tour.groupBy("v").agg(F.count(F.lit(1)).alias("n")).join(child_counts(parents), "v", "full").filter("n is null or children is null or n <> children + 1").agg(F.count(F.lit(1)).alias("wrong_counts"))
    trees = parents.groupBy("root").agg((2 * F.count(F.lit(1)) - 1).alias("len"))
    per = tour.groupBy("root").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("pos").alias("d"), F.min("pos").alias("a"), F.max("pos").alias("b"))
    odd = trees.join(per, "root", "full").filter("n is null or len is null or n <> len or d <> len or a <> 1 or b <> len").agg(F.count(F.lit(1)).alias("wrong_positions"))
    size = tour.agg(F.count(F.lit(1)).alias("rows")).crossJoin(trees.agg(F.coalesce(F.sum("len"), F.lit(0)).alias("expected")))
    return size.crossJoin(bad).crossJoin(times).crossJoin(odd)  # single rows
