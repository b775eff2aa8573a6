"""Trees and sequences: compression, common ancestors, paths, sequences, range minima, positions."""

import random

import pytest
from pyspark.sql import functions as F

from spanweave.ledger import Budget, Ledger
from spanweave.operators import measures
from spanweave.operators.compress import compress_tree, jump_tables, nearest_kept, step_of
from spanweave.operators.lca import TreeIndex, lca_batch
from spanweave.operators.paths import ancestor_paths
from spanweave.operators.pointers import ancestor_at, child_ranks, depths, is_ancestor, leaves
from spanweave.operators.positions import dense_positions, prefix_sums
from spanweave.operators.rangemin import block_length, range_min
from spanweave.operators.tour import check_tour, dfs_sequence, sample_leaves, spans, subtree_sizes
from spanweave.schema import Failed


def tree_rows(seed=2):
    """A forest: two deep branches that part near the root, a broom, a bush, a lone vertex."""
    rng, parent = random.Random(seed), {0: 0}
    for k in range(1, 90):
        parent[k] = k - 1
    parent[100] = 2
    for k in range(101, 170):
        parent[k] = k - 1
    for k in range(200, 260):
        parent[k] = 6
    for k in range(300, 360):
        parent[k] = rng.choice([*range(300, k), 40, 150]) if k > 300 else 40
    parent[500] = 500
    parent |= {600: 600, 601: 600, 602: 601}
    return parent


@pytest.fixture(scope="module")
def parent():
    return tree_rows()


@pytest.fixture(scope="module")
def forest(spark, parent):
    from spanweave.ledger import settle

    return settle(depths(spark.createDataFrame(list(parent.items()), "v long, parent long")), "test")


def line(parent, v):
    out = [v]
    while parent[v] != v:
        v = parent[v]
        out.append(v)
    return out


def test_depths_ranks_leaves_ancestors(spark, forest, parent):
    rows = {r.v: r for r in forest.collect()}
    assert all(r.depth == len(line(parent, v)) - 1 and r.root == line(parent, v)[-1] for v, r in rows.items())
    kids = {v: sorted(w for w, p in parent.items() if p == v and w != v) for v in parent}
    for method in ("window", "positions"):
        assert {r.v: r["rank"] for r in child_ranks(forest, method).collect()} == {v: 1 if p == v else kids[p].index(v) + 1 for v, p in parent.items()}
    assert {r.v for r in leaves(forest).collect()} == {v for v in parent if not kids[v]}
    for k in (0, 1, 5, 64):
        assert {r.v: r.anc for r in ancestor_at(forest, k).collect()} == {v: line(parent, v)[min(k, len(line(parent, v)) - 1)] for v in parent}


@pytest.mark.parametrize("keep", ["descendant", "printed"])
def test_compression(spark, forest, parent, keep):
    tree = compress_tree(forest, keep)
    t, kept = tree.t, {r.v: r.jump_parent for r in tree.vertices.collect()}
    assert t == step_of(tree.depth) == 7
    assert all(j == line(parent, v)[min(t, len(line(parent, v)) - 1)] and j in kept for v, j in kept.items())
    near = {r.v: r.kept for r in nearest_kept(forest, tree).collect()}
    assert all(near[v] == next(x for x in line(parent, v) if x in kept) for v in parent)
    bristles = sum(v in kept for v in range(200, 260))
    assert bristles == (0 if keep == "descendant" else 60)
    if keep == "descendant":
        assert all(line(parent, v).index(near[v]) <= 2 * t for v in parent)
        inner = {v for v in kept if len(line(parent, v)) > 1}
        assert len(inner) + 1 <= len(parent) / t + 1
    for r in jump_tables(tree).collect():
        v = r.v
        for _ in range(1 << r.j):
            v = kept[v]
        assert r.anc == v and r.anc_depth == len(line(parent, v)) - 1


def test_steps_at_shallow_depths():
    assert [step_of(d) for d in (0, 1, 2, 3, 4, 5, 8, 9)] == [1, 1, 1, 2, 2, 3, 3, 4]


@pytest.mark.parametrize(("method", "attach"), [("compressed", False), ("doubling", False), ("naive", False), ("compressed", True)])
def test_common_ancestors(spark, forest, parent, method, attach):
    rng = random.Random(1)
    ids = sorted(parent)
    pairs = [(rng.choice(ids), rng.choice(ids)) for _ in range(150)] + [(89, 169), (89, 12), (169, 100), (5, 5), (0, 500), (88, 168), (13, 210), (601, 3)]
    asked = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(pairs)], "qid long, u long, v long")
    want = {}
    for i, (u, v) in enumerate(pairs):
        a, b = line(parent, u), line(parent, v)
        met = next((x for x in a if x in b), None)
        side = lambda way, met=met: way[way.index(met) - 1] if met is not None and way[0] != met else None
        want[i] = (met, side(a), side(b))
    assert {r.qid: (r.lca, r.child_u, r.child_v) for r in lca_batch(forest, asked, method=method, attach_leaves=attach).collect()} == want


@pytest.mark.parametrize("method", ["compressed", "doubling", "naive"])
def test_paths(spark, forest, parent, method):
    rng = random.Random(2)
    asked = [(v, rng.choice(line(parent, v))) for v in rng.sample(sorted(parent), 60)] + [(89, 0), (169, 2), (169, 0), (7, 7), (89, 60)]
    rows = spark.createDataFrame([(i, u, a) for i, (u, a) in enumerate(asked)], "qid long, u long, anc long")
    want = {i: line(parent, u)[: line(parent, u).index(a) + 1] for i, (u, a) in enumerate(asked)}
    assert {r.qid: r.path for r in ancestor_paths(forest, rows, method=method, as_array=True).collect()} == want
    with pytest.raises(ValueError, match="no ancestor"):
        ancestor_paths(forest, spark.createDataFrame([(1, 89, 169)], "qid long, u long, anc long"), method=method)


def sequence(parent, root):
    kids = {v: sorted(w for w, p in parent.items() if p == v and w != v) for v in parent}
    out, stack = [], [(root, False)]
    while stack:
        v, back = stack.pop()
        out.append(v)
        if not back:
            for w in reversed(kids[v]):
                stack += [(v, True), (w, False)]
    return out


@pytest.mark.parametrize("how", [{}, {"s": 40}, {"s": 12, "c": 0.6, "seed": 3}, {"s": 1, "c": 0.2}, {"method": "tour_ranking"}, {"method": "levels"}])
def test_sequences(forest, parent, how):
    tour = dfs_sequence(forest, **how)
    got = {}
    for r in tour.collect():
        got.setdefault(r.root, {})[r.pos] = r.v
    assert {root: [seq[k] for k in sorted(seq)] for root, seq in got.items()} == {root: sequence(parent, root) for root in (0, 500, 600)}
    assert all(sorted(seq) == list(range(1, len(seq) + 1)) for seq in got.values())


def test_invariants_sizes_and_failure(spark, forest, parent):
    tour = dfs_sequence(forest)
    assert tuple(check_tour(tour, forest).first())[2:] == (0, 0, 0)
    broken = tour.filter("v <> 6").unionByName(tour.filter("v = 6").limit(1))
    assert sum(tuple(check_tour(broken, forest).first())[2:]) > 0
    want = {v: sum(v in line(parent, w) for w in parent) for v in parent}
    for method in ("ranking", "levels"):
        assert {r.v: r["size"] for r in subtree_sizes(forest, method).collect()} == want
    one = forest.filter("root = 0")
    pairs = one.select(F.col("parent").alias("u"), "v")
    assert is_ancestor(pairs, spans(dfs_sequence(one))).filter("not ancestor").isEmpty()
    with pytest.raises(Failed):
        dfs_sequence(forest, s=20, c=50.0, max_pairs=10)
    assert 0 <= measures.fail_rate(lambda seed: dfs_sequence(forest, s=20, c=50.0, max_pairs=10, seed=seed), range(2)) == 1.0
    report = {}
    dfs_sequence(forest, s=40, c=1.0, report=report)
    assert report["samples"] and report["within_bound"] in (True, False)


def test_samples_do_not_change_when_computed_again(spark, forest):
    ranks = forest.select("v", "parent").withColumn("children", F.lit(0))
    jobs = forest.select(F.col("root").alias("job"), "v").withColumn("n", F.lit(200))
    once = {tuple(r) for r in sample_leaves(jobs, ranks, 8, 0.3, 1).collect()}
    assert once == {tuple(r) for r in sample_leaves(jobs.repartition(3), ranks, 8, 0.3, 1).collect()}
    assert once != {tuple(r) for r in sample_leaves(jobs, ranks, 8, 0.3, 2).collect()}


@pytest.mark.parametrize("local", [0, 100_000])
def test_range_minima(spark, monkeypatch, local):
    from spanweave.operators import rangemin

    monkeypatch.setattr(rangemin, "LOCAL", local)
    rng = random.Random(5)
    for n in (1, 7, 33):
        vals = [rng.randrange(20) for _ in range(n)]
        arr = spark.createDataFrame([(i + 1, x) for i, x in enumerate(vals)], "pos long, val long")
        asked = [(lo, hi) for lo in range(1, n + 1) for hi in range(lo, n + 1)]
        queries = spark.createDataFrame([(i, lo, hi) for i, (lo, hi) in enumerate(asked)], "qid long, lo long, hi long")
        want = {i: min(vals[lo - 1 : hi]) for i, (lo, hi) in enumerate(asked)}
        for method in ("block", "sparse_table", "naive"):
            assert dict(range_min(arr, queries, method).collect()) == want
        t = block_length(n)
        long = queries.filter(F.col("hi") - F.col("lo") >= t)
        assert dict(range_min(arr, long, route="long").collect()) == {i: m for i, m in want.items() if asked[i][1] - asked[i][0] >= t}
        if n > 1:
            with pytest.raises(ValueError, match="shorter"):
                range_min(arr, queries, route="long")


def test_positions_and_sums(spark):
    rows = [(i % 3, (i * 37) % 101, i) for i in range(101)]
    df = spark.createDataFrame(rows, "g long, k long, w long")
    got = dense_positions(df, ["k"]).collect()
    assert sorted(r.pos for r in got) == list(range(1, 102)) and all(r.pos == r.k + 1 for r in got)
    for r in prefix_sums(df, ["g"], ["k"], "w").collect():
        assert r.before == sum(w for g, k, w in rows if g == r.g and k < r.k)


def test_ledger_and_budget(spark, forest):
    ledger = Ledger()
    with ledger.open():
        depths(forest)
    assert 5 <= ledger.rounds("depths") <= 9 and ledger.live_rows() == forest.count()
    assert ledger.frame(spark).columns == ["phase", "round", "live_rows", "exchange_rows", "max_rows_per_task", "seconds"]
    assert Budget(delta=0.5).local(10_000) == 1600 and Budget(gamma=1.0).total(10) == 1600


def test_linear_space_of_compression(spark, forest):
    report = measures.compression_report(forest).first()
    assert report.kept <= report.bound + 3 and report.open_jumps == 0 and report.farthest <= 2 * report.t
    arr = spark.range(1, 4097).select(F.col("id").alias("pos"), F.col("id").alias("val"))
    asked = spark.createDataFrame([(1, 1, 4000)], "qid long, lo long, hi long")
    rows = measures.rows_of_range_min(arr, asked)
    assert rows["block"] < 4 * 4096 < rows["sparse_table"]
