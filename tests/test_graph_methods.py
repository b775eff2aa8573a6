"""Every method against definitions and against the other methods, on hand-made and random graphs."""

import random
from itertools import pairwise

import pytest

from spanweave.operators import blocks as bl
from spanweave.operators import bridges as br
from spanweave.operators import hub
from spanweave.operators.components import connected_components
from spanweave.operators.forest import spanning_forest
from spanweave.operators.pointers import check_forest
from spanweave.schema import Failed
from spanweave.sources.tables import from_rows

K4 = [(a, b) for a in range(4) for b in range(a)]
HAND = {
    "edge": [(1, 2)],
    "path": [(1, 2), (2, 3), (3, 4)],
    "star": [(0, k) for k in range(1, 6)],
    "triangle with pendants": [(0, 1), (1, 2), (2, 0), (0, 3), (1, 4), (2, 5)],
    "two triangles": [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 2)],
    "two K4 and a bridge": K4 + [(a + 10, b + 10) for a, b in K4] + [(0, 10)],
    "K23": [(a, b) for a in (0, 1) for b in (2, 3, 4)],
    "two parts": [(0, 1), (1, 2), (2, 0), (7, 8)],
    "loops and repeats": [(0, 0), (0, 1), (1, 0), (1, 2), (1, 2)],
    "wheel": [(0, k) for k in range(1, 7)] + [(k, k % 6 + 1) for k in range(1, 7)],
}


def brute_bridges(pairs):
    edges = {(min(e), max(e)) for e in pairs if e[0] != e[1]}

    def reach(start, without):
        near, todo, seen = {}, [start], {start}
        for a, b in edges - {without}:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
        while todo:
            for w in near.get(todo.pop(), ()):
                if w not in seen:
                    seen.add(w)
                    todo.append(w)
        return seen

    return {e for e in edges if e[1] not in reach(e[0], e)}


def same_cycle(pairs):
    """Blocks as sets of edges by the definition: two edges share a block iff a simple cycle holds both (cycles are enumerated)."""
    edges = sorted({(min(e), max(e)) for e in pairs if e[0] != e[1]})
    near = {}
    for a, b in edges:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    up = {e: e for e in edges}

    def find(e):
        while up[e] != e:
            e = up[e]
        return e

    def walk(path, seen):
        for w in near[path[-1]]:
            if w == path[0] and len(path) > 2:
                cycle = [(min(p), max(p)) for p in [*pairwise(path), (path[-1], w)]]
                for e in cycle[1:]:
                    a, b = sorted((find(e), find(cycle[0])))
                    up[b] = a
            elif w > path[0] and w not in seen:
                walk([*path, w], seen | {w})

    for v in near:
        walk([v], {v})
    return {e: min(x for x in edges if find(x) == find(e)) for e in edges}


def many(seed, count=14, n=7):
    """Random small graphs side by side, ids apart: one run tests them all."""
    rng, out = random.Random(seed), []
    for k in range(count):
        m = rng.randint(1, 11)
        out += [(100 * k + rng.randrange(n), 100 * k + rng.randrange(n)) for _ in range(m)]
    return out


CASES = [*HAND.values(), many(1)]


@pytest.fixture(scope="module")
def everything(spark):
    """All cases as one graph of many components."""
    pairs, base = [], 0
    for case in CASES:
        pairs += [(base + a, base + b) for a, b in case]
        base += 2000
    return pairs, from_rows(spark, pairs)


@pytest.mark.parametrize(
    ("method", "options"),
    [("paper", {}), ("interval", {}), ("hook", {}), ("naive", {}), ("local", {}), ("brute", {}), ("interval", {"forest": "contract", "tour_method": "tour_ranking"}), ("interval", {"s": 3}), ("paper", {"forest": "bfs", "rmq_method": "sparse_table", "lca_method": "naive"})],
)
def test_bridges_are_edges_whose_removal_parts_a_component(everything, method, options):
    pairs, edges = everything
    assert {tuple(r) for r in br.find_bridges(edges, method=method, **options).collect()} == brute_bridges(pairs)


@pytest.mark.parametrize(("method", "options"), [("paper", {}), ("interval", {}), ("local", {}), ("paper", {"aux": "all_edges"}), ("interval", {"presparsify": True}), ("interval", {"components": "hook"}), ("interval", {"forest": "hook", "tour_method": "tour_ranking"})])
def test_blocks_are_edges_on_common_cycles(everything, method, options):
    pairs, edges = everything
    assert {(r.src, r.dst): (r.block_src, r.block_dst) for r in bl.color_blocks(edges, method=method, **options).collect()} == same_cycle(pairs)


def test_cut_vertices_and_the_condition_that_only_follows(spark):
    edges = from_rows(spark, HAND["triangle with pendants"])
    colors = bl.color_blocks(edges, method="local")
    assert {r.v for r in bl.cut_vertices(colors).collect()} == {0, 1, 2}
    fit = {tuple(r) for r in bl.bridge_conditions(edges, colors).collect()}
    bridges = {(0, 3), (1, 4), (2, 5)}
    assert bridges < fit  # triangle edges fit too and are no bridges


def test_doubled_tree_edges_are_no_bridges(spark):
    found = br.multi_bridges(from_rows(spark, [(0, 1), (1, 0), (1, 2)]), method="interval")
    assert {tuple(r) for r in found.collect()} == {(1, 2)}


def test_two_edge_components_and_block_cut_tree(spark):
    edges = from_rows(spark, HAND["two K4 and a bridge"])
    parts = {r.v: r.comp for r in br.two_edge_components(edges, method="interval").collect()}
    assert set(parts.values()) == {0, 10}
    assert {tuple(r) for r in bl.block_cut_tree(bl.color_blocks(edges, method="local")).collect()} == {(0, 1, 0)[:1] + (0, 1), (0, 0, 10), (10, 0, 10), (10, 10, 11)}


def test_biconnected(spark):
    assert bl.is_biconnected(from_rows(spark, HAND["wheel"]), method="interval")
    assert not bl.is_biconnected(from_rows(spark, HAND["two triangles"]), method="interval")
    assert not bl.is_biconnected(from_rows(spark, HAND["edge"]), method="interval")
    assert not bl.is_biconnected(from_rows(spark, HAND["K23"]), vertices=spark.createDataFrame([(99,)], "v long"), method="interval")


def test_hub_reduction(spark):
    one, two = [(k, (k + 1) % 6) for k in range(6)], [(k, (k + 1) % 3) for k in range(3)] + [(k + 3, (k + 1) % 3 + 3) for k in range(3)]
    assert hub.one_or_two_cycles(from_rows(spark, one), method="interval") == 1
    assert hub.one_or_two_cycles(from_rows(spark, two), method="interval") == 2
    assert {(r.v, r.comp) for r in hub.components_via_hub(from_rows(spark, two), method="interval").collect()} == {(v, v // 3 * 3) for v in range(6)}


@pytest.mark.parametrize("method", ["stars", "hook", "contract", "naive", "local"])
def test_components(everything, method):
    pairs, edges = everything
    want = {r.v: r.comp for r in connected_components(edges, method="local").collect()}
    up = {}
    for a, b in pairs:
        if a != b:
            group = {x for x, g in up.items() if g in (up.get(a, a), up.get(b, b))} | {a, b}
            for x in group:
                up[x] = min(min(group), *(up.get(y, y) for y in group))
    assert want == up
    lone = edges.sparkSession.createDataFrame([(99_999,)], "v long")
    assert {r.v: r.comp for r in connected_components(edges, lone, method=method).collect()} == want | {99_999: 99_999}


@pytest.mark.parametrize(("method", "options"), [("auto", {}), ("auto", {"local_rows": 2}), ("bfs", {}), ("hook", {}), ("contract", {})])
def test_forests_span_and_end(everything, method, options):
    pairs, edges = everything
    forest = spanning_forest(edges, method=method, **options)
    check_forest(forest)
    rows = forest.collect()
    known = {(min(e), max(e)) for e in pairs}
    depth = {r.v: r.depth for r in rows}
    assert all(r.v == r.parent == r.root and r.depth == 0 or (min(r.v, r.parent), max(r.v, r.parent)) in known and r.depth == depth[r.parent] + 1 for r in rows)
    assert {(r.v, r.root) for r in rows} == {(r.v, r.comp) for r in connected_components(edges, method="local").collect()}
    if method in ("auto", "bfs"):
        assert {tuple(r) for r in rows} == {tuple(r) for r in spanning_forest(edges).collect()}


def test_an_empty_graph_has_nothing(spark):
    none = from_rows(spark, [])
    assert br.find_bridges(none, method="local").collect() == []
    assert connected_components(none).collect() == []
    assert spanning_forest(none, vertices=spark.createDataFrame([(5,)], "v long")).collect() == [(5, 5, 5, 0)]


def test_cycles_of_pointers_are_found(spark):
    with pytest.raises(ValueError, match="cycle"):
        check_forest(spark.createDataFrame([(1, 2), (2, 1)], "v long, parent long"))
    with pytest.raises(ValueError, match="no vertex"):
        check_forest(spark.createDataFrame([(1, 2)], "v long, parent long"))


def test_retries_end_in_failure():
    seen = []

    def run(seed):
        seen.append(seed)
        raise Failed("never")

    with pytest.raises(Failed):
        br.with_retries(run, 3, seed=5)
    assert seen == [5, 6, 7]
    assert br.with_retries(lambda seed: seed, 3, seed=5) == 5


def test_fundamental_cycles_cover_what_is_no_bridge(everything):
    pairs, edges = everything
    rows = bl.fundamental_cycles(edges).collect()
    assert {(r.src, r.dst) for r in rows} == {(min(e), max(e)) for e in pairs if e[0] != e[1]} - brute_bridges(pairs)
    by = {}
    for r in rows:
        by.setdefault((r.cycle_src, r.cycle_dst), []).append((r.src, r.dst))
    for cycle in by.values():  # every vertex of a cycle has two of its edges
        ends = [v for e in cycle for v in e]
        assert all(ends.count(v) == 2 for v in ends)
