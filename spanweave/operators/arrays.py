"""What one task solves with arrays: components, breadth-first forests and depth-first sequences of whole graphs, many at a time, level by level."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows that one task holds as arrays, at some 60 bytes each.
ARRAY_ROWS = 16_000_000
#: Rows that leave a task at once.
SLICE_ROWS = 500_000
#: Rows of a pack on average; a group of up to ARRAY_ROWS rows comes on top of them.
PACK_ROWS = 100_000
#: Edges of a chunk whose components a task finds before any are exchanged.
CHUNK_ROWS = 1_000_000


def packed(key: str, rows: int) -> Column:
    """The pack of a group named `key`, of `rows` rows in all: whole groups, many small ones in one task."""
    return F.pmod(F.xxhash64(key), F.lit(max(1, -(-rows // PACK_ROWS)))).alias("pack")


def places(ids: np.ndarray, of: np.ndarray) -> np.ndarray:
    """The place of every value of `of` among the sorted `ids`: looked up in order, a stretch at a time, so that near values follow each other."""
    out = np.empty(len(of), np.int32)
    for low in range(0, len(of), SLICE_ROWS):
        part = of[low : low + SLICE_ROWS]
        order = np.argsort(part)
        out[low + order] = np.searchsorted(ids, part[order])
    return out


def numbered(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, a, b): the sorted ids, and both ends of every edge as places among them."""
    ids = np.concatenate([src, dst])
    if not len(ids):
        return ids.astype(np.int64), src.astype(np.int32), dst.astype(np.int32)
    ids.sort()  # in place, and places in 32 bits: np.unique would hold three times as much
    ids = ids[np.concatenate([[True], ids[1:] != ids[:-1]])]
    return ids, places(ids, src), places(ids, dst)


def listed(tail: np.ndarray, head: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(start, near): the heads of v's arcs, in order, are near[start[v] : start[v + 1]]. Both ends share a word, so that nothing but it is sorted."""
    word = tail.astype(np.int64)
    word <<= 32
    word |= head
    word.sort()
    near = word.astype(np.int32)  # the lower half
    word >>= 32
    return np.searchsorted(word, np.arange(n + 1)).astype(np.int32), near


def adjacency(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(start, near): the neighbours of v, in order, are near[start[v] : start[v + 1]]."""
    return listed(np.concatenate([a, b]), np.concatenate([b, a]), n)


def spread(start: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places, owners): all places of the lists of the vertices `of`, in their order."""
    n = start[of + 1] - start[of]
    return np.repeat(start[of] - (np.cumsum(n) - n), n) + np.arange(n.sum()), np.repeat(of, n)


def least_labels(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """The least place of every place's component: roots hang below lesser ones, then pointers are jumped; a root that stays has been hung on, so roots halve."""
    label = np.arange(n, dtype=np.int32)
    while True:
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return label
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            far = label[label]
            if (far == label).all():
                break
            label = far


#: What a solver finds: the number of its rows, and those between two places.
Found = tuple[int, Callable[[slice], pd.DataFrame]]


def ends_of(held: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """`numbered` ends of the edges `held`, which are let go."""
    out = numbered(*held)
    held.clear()
    return out


def labelled(held: list[np.ndarray]) -> Found:
    """(v, comp) of edges (src, dst)."""
    ids, a, b = ends_of(held)
    label = least_labels(a, b, len(ids))
    return len(ids), lambda at: pd.DataFrame({"v": ids[at], "comp": ids[label[at]]})


def chunk_labels(held: list[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    rows, found = labelled(gathered(iter(held), ["src", "dst"]))
    yield found(slice(0, rows))


def chunk_components(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """(v, comp) of every chunk of up to CHUNK_ROWS of a task's edges (src, dst), each by itself."""
    held, rows = [], 0
    for pdf in batches:
        held.append(pdf)
        rows += len(pdf)
        if rows >= CHUNK_ROWS:
            yield from chunk_labels(held)
            held, rows = [], 0
    if rows:
        yield from chunk_labels(held)


def breadth_first(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(parent, root, depth) of every place: from the least one of each component, parents the least neighbour one level up."""
    start, near = adjacency(a, b, n)
    root = least_labels(a, b, n)
    front = np.flatnonzero(root == np.arange(n))
    parent, depth = np.full(n, -1, np.int32), np.full(n, -1, np.int32)
    parent[front], depth[front], level = front, 0, 0
    while len(front):
        level += 1
        at, above = spread(start, front)
        below = near[at]
        fresh = depth[below] < 0
        below, above = below[fresh], above[fresh]
        parent[below[::-1]] = above[::-1]  # the front is in order, and of several parents the last one written stays: the least
        depth[below] = level
        front = np.unique(below)
    return parent, root, depth


def rooted_forest(held: list[np.ndarray]) -> Found:
    """(v, parent, root, depth) of whole components (src, dst): breadth-first from the least id of each, parents the least neighbour one level up."""
    ids, a, b = ends_of(held)
    parent, root, depth = breadth_first(a, b, len(ids))
    return len(ids), lambda at: pd.DataFrame({"v": ids[at], "parent": ids[parent[at]], "root": ids[root[at]], "depth": depth[at]})


def laid_out(parent: np.ndarray, top: np.ndarray, base: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first position, subtree size) of every place; a tree's sequence begins at the base of its `top`, children come in their order."""
    n = len(parent)
    inner = np.flatnonzero(~top).astype(np.int32)
    start, kids = listed(parent[inner], inner, n)
    del inner
    levels = [np.flatnonzero(top).astype(np.int32)]
    while len(levels[-1]):
        levels.append(kids[spread(start, levels[-1])[0]])
    size = np.ones(n, np.int32)
    for level in reversed(levels[1:]):
        np.add.at(size, parent[level], size[level])
    total = np.zeros(len(kids) + 1, np.int64)
    np.cumsum(size[kids], out=total[1:])
    before = np.zeros(n, base.dtype)  # what earlier siblings take
    before[kids] = 2 * (total[:-1] - total[start[parent[kids]]])
    del kids, start, total
    first = base.copy()
    for level in levels[1:]:
        first[level] = first[parent[level]] + 1 + before[level]
    return first, size


def stretch_values(values: np.ndarray, length: np.ndarray, pick: np.ufunc) -> np.ndarray:
    """`pick` (np.minimum or np.maximum) over values[i : i + length[i]] for every i, by powers of two, of which one row is held at a time."""
    power = (np.frexp(length)[1] - 1).astype(np.int8)
    by_power = np.argsort(power, kind="stable").astype(np.int32)
    end = np.cumsum(np.bincount(power))
    del power
    out, row = np.empty_like(values), values
    for k, (lo, hi) in enumerate(zip([0, *end[:-1]], end, strict=True)):
        at = by_power[lo:hi]
        out[at] = pick(row[at], row[at + length[at] - (1 << k)])
        row = pick(row[: -(1 << k)], row[1 << k :])
    return out


def subtree_reach(root: np.ndarray, first: np.ndarray, size: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(low, high): the least lo and the greatest hi in every vertex's subtree; in the order of first positions a subtree is a stretch."""
    order = np.lexsort((first, root)).astype(np.int32)
    low, high = np.empty_like(lo), np.empty_like(hi)
    low[order] = stretch_values(lo[order], size[order], np.minimum)
    high[order] = stretch_values(hi[order], size[order], np.maximum)
    return low, high


def reach_of(pdf: pd.DataFrame) -> pd.DataFrame:
    """(v, low, high) of whole trees (v, root, first, last, lo, hi)."""
    root, first, last, lo, hi = (pdf[c].to_numpy(np.int64) for c in ("root", "first", "last", "lo", "hi"))
    low, high = subtree_reach(root, first, (last - first) // 2 + 1, lo, hi)
    return pd.DataFrame({"v": pdf.v, "low": low, "high": high})


def reach_of_graph(held: list[np.ndarray]) -> Found:
    """(v, parent, depth, first, last, low, high) of whole components (src, dst): their breadth-first forest, spans from 1 on in every tree, and the least and greatest first position that a subtree touches by edges off the forest."""
    ids, a, b = ends_of(held)
    n = len(ids)
    parent, root, depth = breadth_first(a, b, n)
    first, size = laid_out(parent, parent == np.arange(n, dtype=np.int32), np.ones(n, np.int32))
    off = (parent[a] != b) & (parent[b] != a)
    a, b = a[off], b[off]
    lo, hi = first.copy(), first.copy()
    for x, y in ((a, b), (b, a)):
        np.minimum.at(lo, x, first[y])
        np.maximum.at(hi, x, first[y])
    del a, b, off
    low, high = subtree_reach(root, first, size, lo, hi)
    del root, lo, hi
    return n, lambda at: pd.DataFrame({"v": ids[at], "parent": ids[parent[at]], "depth": depth[at], "first": first[at].astype(np.int64), "last": first[at].astype(np.int64) + 2 * size[at] - 2, "low": low[at].astype(np.int64), "high": high[at].astype(np.int64)})


def sequenced(held: list[np.ndarray]) -> Found:
    """(root, pos, v): the sequences of the subtrees (job, v, parent, root, base), each from its base on, children in the order of their ids."""
    job, v, up, root, base = held
    held.clear()
    top = v == job
    del job
    order = np.argsort(v)
    v, up, root, base, top = v[order], up[order], root[order], base[order], top[order]
    del order
    up[top] = v[top]
    parent, n = places(v, up), len(v)
    del up
    first, size = laid_out(parent, top, base)
    del base
    inner = np.flatnonzero(~top).astype(np.int32)

    def found(at: slice) -> pd.DataFrame:
        """Every place at its first position, and behind them its parent again, after each child's last."""
        back = inner[max(0, at.start - n) : max(0, at.stop - n)]
        own = slice(min(n, at.start), min(n, at.stop))
        return pd.DataFrame({"root": np.concatenate([root[own], root[back]]), "pos": np.concatenate([first[own], first[back] + 2 * size[back] - 1]), "v": np.concatenate([v[own], v[parent[back]]])})

    return n + len(inner), found


def doubled(held: list[np.ndarray]) -> Found:
    """(v, ptr, sums) of pointers (v, ptr, sums): every pointer to its pointer's pointer, sums along the way added, until all stand at ends. What leads to no vertex is left out."""
    v, to, *sums = held
    held.clear()
    order = np.argsort(v)
    n, ids, to, sums = len(v), v[order], to[order], [np.append(x[order], 0) for x in sums]
    del v, order
    ptr = np.append(places(ids, to), n).astype(np.int32)
    ptr[:n][ids[np.minimum(ptr[:n], n - 1)] != to] = n
    del to
    end = ptr == np.arange(n + 1, dtype=np.int32)
    for _ in range(64):
        if end[ptr].all():
            break
        for k, x in enumerate(sums):
            sums[k] = x + x[ptr]
        ptr = ptr[ptr]
    else:
        raise ValueError("pointers do not end: they hold a cycle")
    if (ptr[:n] == n).any():
        kept = np.flatnonzero(ptr[:n] != n)
        return len(kept), lambda at: pd.DataFrame({"v": ids[kept[at]], "ptr": ids[ptr[kept[at]]]} | {f"s{k}": x[kept[at]] for k, x in enumerate(sums)})
    return n, lambda at: pd.DataFrame({"v": ids[at], "ptr": ids[ptr[:n][at]]} | {f"s{k}": x[:n][at] for k, x in enumerate(sums)})


class Meeting:
    """Pairs on their way up one forest of places: a the deeper end, b the other, pa and pb where they stood a step before, `lca` where they met (-1: not yet)."""

    def __init__(self, parent: np.ndarray, depth: np.ndarray, a: np.ndarray, b: np.ndarray):
        self.parent, self.depth, self.a, self.b = parent, depth, a, b
        self.pa, self.pb, self.lca = (np.full(len(a), -1, np.int32) for _ in range(3))

    def climb(self, live: np.ndarray, steps: int) -> np.ndarray:
        """Up to `steps` single steps of the pairs `live`: the deeper end, or both where they are level, go to their parents. Those that have not met are returned."""
        for _ in range(steps):
            if not len(live):
                break
            a, b = self.a[live], self.b[live]
            level = self.depth[a] == self.depth[b]
            self.pa[live], self.a[live] = a, self.parent[a]
            self.pb[live[level]], self.b[live[level]] = b[level], self.parent[b[level]]
            met = self.a[live] == self.b[live]
            self.lca[live[met]] = self.a[live[met]]
            live = live[~met]
        return live

    def by_jumps(self, live: np.ndarray, t: int) -> None:
        """Over the compressed tree: far ends are lifted, 4t single steps, then the last kept ancestors that differ, then 2t steps at most."""
        parent, depth = self.parent, self.depth
        anc = np.flatnonzero((depth % t == 0) & (depth >= t)).astype(np.int32)
        for _ in range(t):
            anc = parent[anc]
        chosen = parent == np.arange(len(parent), dtype=np.int32)
        chosen[anc] = True
        kept = np.flatnonzero(chosen).astype(np.int32)
        jump = kept
        for _ in range(t):
            jump = parent[jump]
        tables = [np.searchsorted(kept, jump).astype(np.int32)]
        for _ in range((int(depth[kept].max(initial=0)) // t).bit_length()):
            tables.append(tables[-1][tables[-1]])
        tall = depth[kept]

        def nearest(of: np.ndarray) -> np.ndarray:
            while not chosen[of].all():
                of = np.where(chosen[of], of, parent[of])
            return np.searchsorted(kept, of).astype(np.int32)

        far = live[depth[self.a[live]] > depth[self.b[live]] + 2 * t]
        at, bound = nearest(self.a[far]), depth[self.b[far]]
        for up in reversed(tables):
            at = np.where(tall[up[at]] > bound, up[at], at)
        self.a[far] = kept[at]
        a0, b0 = self.a.copy(), self.b.copy()
        live = self.climb(live, 4 * t)
        # The common ancestor is over 2t above both ends where the near search began, but may be just above where it stopped.
        a, b = nearest(a0[live]), nearest(b0[live])
        for up in reversed(tables):  # level them
            a = np.where((tall[up[a]] >= tall[b]) & (tall[up[a]] < tall[a]), up[a], a)
            b = np.where((tall[up[b]] >= tall[a]) & (tall[up[b]] < tall[b]), up[b], b)
        for up in reversed(tables):
            go = up[a] != up[b]
            a, b = np.where(go, up[a], a), np.where(go, up[b], b)
        self.a[live], self.b[live] = kept[a], kept[b]
        if len(self.climb(live, 2 * t)):
            raise AssertionError("a query was not settled by its last climb")

    def by_tables(self, live: np.ndarray, deepest: int) -> None:
        """Over every 2**j-th ancestor of every vertex: the tables lie in a file, one is held at a time."""
        powers, n = max(1, deepest.bit_length()), len(self.parent)
        with tempfile.TemporaryFile() as rows:
            level = self.parent
            for j in range(powers):
                level.tofile(rows)
                level = level[level] if j + 1 < powers else level
            del level

            def table(j: int) -> np.ndarray:
                rows.seek(4 * n * j)
                return np.fromfile(rows, np.int32, n)

            a, b = self.a[live], self.b[live]
            da, db = self.depth[a], self.depth[b]
            for j in range(powers - 1, -1, -1):  # the deeper end to one step above level, so that its last step is known
                go = da - (1 << j) > db
                a, da = np.where(go, table(j)[a], a), np.where(go, da - (1 << j), da)
            up = da > db
            self.pa[live[up]], a = a[up], np.where(up, self.parent[a], a)
            met = a == b
            self.lca[live[met]] = a[met]
            live, a, b = live[~met], a[~met], b[~met]
            for j in range(powers - 1, -1, -1):
                far = table(j)
                go = far[a] != far[b]
                a, b = np.where(go, far[a], a), np.where(go, far[b], b)
            self.pa[live], self.pb[live], self.lca[live] = a, b, self.parent[a]


def meetings(method: str, step_of: Callable[[int], int]) -> Callable[[list[np.ndarray]], Found]:
    """(qid, u, v, lca, child_u, child_v) of rows (kind, x, y, z): 0 a vertex, its parent, its depth; 1 a query's qid, u, v."""

    def solve(held: list[np.ndarray]) -> Found:
        kind, x, y, z = held
        held.clear()
        asked = kind == 1
        qid, u, v = x[asked], y[asked], z[asked]
        np.logical_not(asked, out=asked)
        ids, up, depth = x[asked], y[asked], z[asked].astype(np.int32)
        del kind, x, y, z, asked
        order = np.argsort(ids)
        ids, up, depth = ids[order], up[order], depth[order]
        del order
        parent, n = places(ids, up), len(ids)
        del up
        root = parent
        while True:
            far = root[root]
            if (far == root).all():
                break
            root = far
        del far
        pu, pv = (np.minimum(places(ids, e), n - 1) for e in (u, v))
        apart = (ids[pu] != u) | (ids[pv] != v) | (root[pu] != root[pv])
        del root
        swapped = depth[pu] < depth[pv]
        pairs = Meeting(parent, depth, np.where(swapped, pv, pu), np.where(swapped, pu, pv))
        same = (u == v) & ~apart
        pairs.lca[same] = pu[same]
        live, deepest = np.flatnonzero(~apart & ~same), int(depth.max(initial=0))
        if method == "doubling":
            pairs.by_tables(live, deepest)
        else:
            pairs.by_jumps(live, step_of(deepest))
        lca, one, two = pairs.lca, np.where(swapped, pairs.pb, pairs.pa), np.where(swapped, pairs.pa, pairs.pb)

        def found(at: slice) -> pd.DataFrame:
            column = lambda of, none: pd.arrays.IntegerArray(ids[of[at]], none)
            none = apart[at]
            return pd.DataFrame({"qid": qid[at], "u": u[at], "v": v[at], "lca": column(lca, none), "child_u": column(one, none | (lca[at] == pu[at])), "child_v": column(two, none | (lca[at] == pv[at]))})

        return len(qid), found

    return solve


def gathered(batches: Iterator[pd.DataFrame], columns: list[str]) -> list[np.ndarray]:
    """Each column of a task's rows as one array."""
    parts: list[list[np.ndarray]] = [[] for _ in columns]
    for pdf in batches:
        for part, c in zip(parts, columns, strict=True):
            part.append(pdf[c].to_numpy(copy=True))
    out = []
    for part in parts:
        out.append(np.concatenate(part) if part else np.empty(0, np.int64))
        part.clear()
    return out


def _task(solve: Callable[[list[np.ndarray]], Found], columns: list[str]) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows, found = solve(gathered(batches, columns))
        for low in range(0, rows, SLICE_ROWS):
            yield found(slice(low, min(rows, low + SLICE_ROWS)))

    return work


def in_one(frame: DataFrame, solve: Callable[[list[np.ndarray]], Found], schema: str) -> DataFrame:
    """`solve` over the columns of all rows in one task, whose rows leave it slice by slice."""
    return frame.coalesce(1).mapInPandas(_task(solve, frame.columns), schema)


def in_packs(frame: DataFrame, pack: Column, rows: int, solve: Callable[[list[np.ndarray]], Found], schema: str) -> DataFrame:
    """`solve` over the columns of whole packs, of `rows` rows in all, a task for some PACK_ROWS of them."""
    columns = [c for c in frame.columns if c not in ("pack", "comp")]
    return frame.withColumn("pack", pack).repartition(max(1, -(-rows // PACK_ROWS)), "pack").select(*columns).mapInPandas(_task(solve, columns), schema)
