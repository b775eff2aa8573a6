"""Graphs beyond the bounds that the methods once refused or took too many rounds for."""

import time

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from spanweave import graphs
from spanweave.ledger import Ledger, settle
from spanweave.operators import blocks, bridges, components, forest, hub, measures, pointers
from spanweave.operators.forest import spanning_forest
from spanweave.operators.lca import lca_batch


def _ring(spark, n):
    return spark.range(n).select(F.least("id", (F.col("id") + 1) % n).alias("src"), F.greatest("id", (F.col("id") + 1) % n).alias("dst"))


def test_a_deep_forest_takes_no_round_a_level(spark):
    n = 200_002
    found = spanning_forest(_ring(spark, n)).agg(F.count("*"), F.max("depth"), F.sum(F.abs(F.col("depth") - F.least("v", n - F.col("v"))))).first()
    assert tuple(found) == (n, n // 2, 0)


@pytest.mark.parametrize("rows", [200_002, 40])
def test_local_components_of_any_size(spark, monkeypatch, rows):
    n = 200_002 if rows > 40 else 41  # more edges than a task took; more than an array bound holds
    if rows == 40:
        monkeypatch.setattr(components, "ARRAY_ROWS", rows)
    found = components.connected_components(_ring(spark, n), method="local").agg(F.count("*"), F.max("comp")).first()
    assert tuple(found) == (n, 0)


@pytest.mark.parametrize("rows", [100, 1000])
def test_cycles_with_a_hub_take_no_range_tables(spark, monkeypatch, rows):
    """Rings of 60 with a hub: 120 edges, beyond a task's rows or within them; the range minima of their subtrees went by a round a power of two."""
    for module in (bridges, components, forest):
        monkeypatch.setattr(module, "ARRAY_ROWS", rows, raising=False)
    part = lambda lo, n: spark.range(lo, lo + n).select(F.col("id").alias("src"), (lo + (F.col("id") - lo + 1) % n).alias("dst"))
    ledger = Ledger()
    with ledger.open():
        assert hub.one_or_two_cycles(part(0, 60), method="interval") == 1
        assert hub.one_or_two_cycles(part(0, 30).unionByName(part(30, 30)), method="interval") == 2
    assert ledger.rounds("range table") == 0
    assert ledger.rounds("normalise") <= 6


def test_many_components_beyond_a_tasks_rows_in_all(spark, monkeypatch):
    """300 small components, 3,300 edges where a task may hold 700: they were labelled by rounds of stars, and their subtrees by range tables."""
    for module in (bridges, components, forest):
        monkeypatch.setattr(module, "ARRAY_ROWS", 700, raising=False)
    pairs = [(100 * c + a, 100 * c + b) for c in range(300) for a, b in [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (4, 5), (5, 6), (3, 6), (6, 7), (7, 8), (1, 9)]]
    graph, ledger = spark.createDataFrame(pairs, "src long, dst long").repartition(6), Ledger()
    with ledger.open():
        found = sorted(map(tuple, bridges.find_bridges(graph, method="interval").collect()))
    assert found == sorted(e[:2] for e in bridges.solve_low_points(pairs) if e[2])
    assert ledger.rounds("components least") == ledger.rounds("range table") == 0
    colors = blocks.color_blocks(graph, method="interval")
    assert sorted(map(tuple, colors.collect())) == sorted((a, b, c, d) for a, b, _, c, d in bridges.solve_low_points(pairs))


def test_a_tree_is_compressed_once(spark):
    """Common ancestors and the sampled tour each made an index of the same forest."""
    graph, ledger = _ring(spark, 60), Ledger()
    with ledger.open():
        assert bridges.find_bridges(graph, s=20).isEmpty()
    assert ledger.rounds("compress") == 1


def test_contraction_takes_small_components_whole(spark):
    """Pairs that drew no leader used to wait for a later phase, while balls grew beyond all room."""
    pairs, ledger = spark.range(400).select((2 * F.col("id")).alias("src"), (2 * F.col("id") + 1).alias("dst")), Ledger()
    with ledger.open():
        found = components.connected_components(pairs, method="contract")
    assert found.filter("comp <> v - v % 2").count() == 0 and found.count() == 800
    assert ledger.rounds("contract") == 6  # one phase


@pytest.mark.parametrize("limit", [None, 3])
def test_solvers_of_one_task_refuse_nothing(spark, monkeypatch, limit):
    """A ring of 3,100 with a tail of 3, and a triangle: beyond the 2,000 edges and 3,000 vertices that were once allowed, and, with `limit`, beyond a task's rows."""
    n = 3100 if limit is None else 12
    if limit is not None:
        for module in (bridges, measures):
            monkeypatch.setattr(module, "LOCAL_ROWS", limit)
    tail = [(0, n), (n, n + 1), (n + 1, n + 2)]
    graph = settle(_ring(spark, n).unionByName(spark.createDataFrame([*tail, (9001, 9002), (9002, 9003), (9001, 9003)], "src long, dst long")), "x")
    for method in ("local", "brute"):
        assert sorted(map(tuple, bridges.find_bridges(graph, method=method).collect())) == tail, method
    assert blocks.color_blocks(graph, method="local").select("block_src", "block_dst").distinct().count() == 5
    assert sorted(map(tuple, measures.diameter(graph, "exact").collect())) == [(0, n // 2 + 3), (9001, 1)]


def test_shared_lines_keep_their_digits(spark, tmp_path):
    """A line's own number was taken for the characters to be trimmed."""
    text = "0 is where it begins, 10\n   1 is where it ends, 2011   "
    spark.createDataFrame([(1, text), (2, text)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    found = {r.token for r in graphs.line_pairs(spark, str(tmp_path)).collect()}
    assert found == {"0 is where it begins, 10", "1 is where it ends, 2011"}


def test_verdicts_on_many_leaves_take_no_generator_a_leaf():
    began = time.process_time()
    few, many = (measures.sampled_verdicts(k, 2 * k, 512, 1.0, 20_000, range(20)) for k in (1_000, 200_000))
    assert time.process_time() - began < 5
    expected = 512 ** (1 / 3) * (400_000).bit_length()
    assert abs(many["mean_samples"] / expected - 1) < 0.2 and many["by_bound"] == 1.0 and few["by_bound"] == 1.0


def test_a_component_of_millions_takes_no_round_a_level(spark):
    """A stem of 3,000 with leaves: 3,100,000 edges and deeper than the rounds that such a component was allowed."""
    n, stem = 3_100_001, 3_000
    rows = spark.range(1, n)
    edges = rows.select(F.when(F.col("id") < stem, F.col("id") - 1).otherwise(F.col("id") % stem).alias("src"), F.col("id").alias("dst"))
    ready, ledger = bridges.Prepared(edges), Ledger()
    with ledger.open():
        assert bridges.find_bridges(edges, method="interval", ready=ready).count() == n - 1
    assert len(ledger.rows) <= 3
    assert ready.reached.agg(F.max("depth"), F.max("last")).first()[:] == (stem, 2 * n - 1)


def _stems(spark, n, stem):
    """Vertices 0 to n - 1: a stem of `stem`, on whose vertices the others hang in threes, one below the other."""
    up = F.when(F.col("id") == 0, 0).when(F.col("id") < stem, F.col("id") - 1).when(F.col("id") % 3 == 0, (F.col("id") * 7) % stem).otherwise(F.col("id") - 1)
    below = F.when(F.col("id") % 3 == 0, 1).otherwise(F.col("id") % 3 + 1)
    on = F.when(F.col("id") < stem, F.col("id")).otherwise(((F.col("id") - F.col("id") % 3) * 7) % stem + below)
    return settle(spark.range(n).select(F.col("id").alias("v"), up.alias("parent"), F.lit(0).cast("long").alias("root"), on.cast("int").alias("depth")), "x")


def test_pointers_of_a_deep_forest_are_doubled_in_one_task(spark):
    """As many rounds as the depth has binary digits went over all rows."""
    parents, ledger = _stems(spark, 150_000, 3_000), Ledger()
    with ledger.open():
        found = pointers.depths(parents.select("v", "parent"))
        wrong = found.join(parents.select("v", F.col("depth").alias("d")), "v").filter("d <> depth or root <> 0").count()
    assert (found.count(), wrong, ledger.rounds("depths")) == (150_000, 0, 1)


@pytest.mark.parametrize(("method", "attach"), [("compressed", False), ("doubling", False), ("compressed", True)])
def test_common_ancestors_in_a_deep_forest_take_no_round_a_jump(spark, method, attach):
    parents, ledger = _stems(spark, 150_000, 3_000), Ledger()
    up = {r.v: r.parent for r in parents.collect()}

    def way(v):
        out = [v]
        while up[out[-1]] != out[-1]:
            out.append(up[out[-1]])
        return out[::-1]

    def met(u, v):
        a, b = way(u), way(v)
        k = next((k for k, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
        return a[k - 1], *(None if attach and len(x) == k else x[k] if k < len(x) else None for x in (a, b))

    pairs = [(u, v) for u, v in zip(range(5, 150_000, 2_003), range(149_990, 5, -1_999), strict=False)] + [(7, 7), (10, 2_900), (3_000, 3_001), (3_002, 3_000)]
    asked = spark.createDataFrame([(k, *p) for k, p in enumerate(pairs)], "qid long, u long, v long")
    with ledger.open():
        rows = lca_batch(parents, asked, method=method, attach_leaves=attach).collect()
    assert {r.qid: tuple(r)[1:] for r in rows} == {k: (u, v, *met(u, v)) for k, (u, v) in enumerate(pairs)}
    assert ledger.rounds() <= 3


def test_exact_diameter_of_a_large_component(spark):
    """A stem of 300 with leaves, 249,999 edges in one component: it took vertices squared rows."""
    rows = spark.range(1, 250_000)
    edges = rows.select(F.when(F.col("id") < 300, F.col("id") - 1).otherwise(F.col("id") % 300).alias("src"), F.col("id").alias("dst"))
    assert [tuple(r) for r in measures.diameter(edges, "exact").collect()] == [(0, 301)]


def test_bounds_leave_no_farther_pair():
    rng = np.random.default_rng(3)
    for n in [2, 3, 10, 40, 300] * 4:
        pairs = [(int(rng.integers(0, v)) if rng.random() < 0.5 else v - 1, v) for v in range(1, n)]
        pairs += [tuple(sorted(map(int, rng.choice(n, 2, replace=False)))) for _ in range(n // 8)]
        pdf = pd.DataFrame(sorted(set(pairs)), columns=["src", "dst"])
        assert measures.bounded_wave(pdf) == measures.longest_wave(pdf), pairs
