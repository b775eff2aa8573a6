"""Removal of byte strings that occur twice: a sparse suffix sort with hash-compared suffixes.

A suffix matters here by its first `width` bytes alone. Two suffixes that share them also share the place, relative to their start, of the least-hashed
gram among them: their anchor. So suffixes stand in runs with one anchor each, and only suffixes whose anchors are equal can share `width` bytes.

1. Packs tell which anchors occur more than once; runs with a lone anchor end there.
2. The other runs go out with their bytes, copies combined before the shuffle by comparing these bytes.
3. The runs of an anchor are sorted twice, by what follows the anchor and by what stands before it, read backwards: a merge sort whose comparisons find
   common extensions by binary search over prefix polynomial hashes. The bytes of neighbours are compared afterwards; neighbours in order prove the whole order, and what a collision put
   wrong is sorted again byte by byte. Two suffixes share `width` bytes if and only if they share enough on both sides of the anchor, which the extensions of neighbours tell.
4. Each run learns which of its suffixes occur again.

An anchor with more than `CROWD` different runs (a line that many texts have in different surroundings) is split before it is sorted: by halves of the places that
the anchor may have in a suffix, each half with as many bytes more as all its suffixes share; again and again, until in the end a half is one suffix, whose copies are one row.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.llm import packs as pk
from spanweave.llm.shared import stash

#: Bytes of the grams that anchors are chosen by.
GRAM = 64
#: Windows whose anchors are found at a time.
_STEP = 1 << 20
#: Different runs of an anchor beyond which it is split, and runs that are sorted at a time.
CROWD, BUCKET = 4096, 8192


# ---- sorting
class Side:
    """Strings that start at `at` in a buffer and run `size` bytes on (`step` 1) or back (`step` -1), compared by hashes."""

    def __init__(self, data: np.ndarray, prefixes: pk.Prefixes, at: np.ndarray, size: np.ndarray, step: int):
        self.data, self.prefixes, self.at, self.size, self.step = data, prefixes, at, size, step

    def hashes(self, i: np.ndarray, n: np.ndarray) -> np.ndarray:
        return self.prefixes.of(self.at[i], self.at[i] + n) if self.step > 0 else self.prefixes.of(self.at[i] - n, self.at[i])

    def extension(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the common beginning of strings i and j, by binary search over hashes."""
        low, high = np.zeros(len(i), np.int64), np.minimum(self.size[i], self.size[j])
        open_ = np.flatnonzero(low < high)
        while len(open_):
            mid = (low[open_] + high[open_] + 1) // 2
            same = self.hashes(i[open_], mid) == self.hashes(j[open_], mid)
            low[open_[same]], high[open_[~same]] = mid[same], mid[~same] - 1
            open_ = open_[low[open_] < high[open_]]
        return low

    def byte(self, i: np.ndarray, n: np.ndarray) -> np.ndarray:
        """The byte after the first n of each string i, -1 at its end."""
        place = self.at[i] + n if self.step > 0 else self.at[i] - n - 1
        return np.where(n < self.size[i], self.data[np.clip(place, 0, len(self.data) - 1)].astype(np.int64), -1)

    def before(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether string i comes before string j, which stands in another place; equal ones by number."""
        n = self.extension(i, j)
        x, y = self.byte(i, n), self.byte(j, n)
        return (x < y) | ((x == y) & (i < j))

    def content(self, raw: bytes, i: int) -> bytes:
        a, n = int(self.at[i]), int(self.size[i])
        return raw[a : a + n] if self.step > 0 else raw[a - n : a][::-1]


def sorted_strings(side: Side, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, common extension of each with the one before it; -1 at a group's start). `group` is ascending; strings are sorted within theirs.

    A bottom-up merge sort: an element's place in the sibling run is found by binary search, all elements side by side. The result is then checked by the bytes."""
    n = len(group)
    order, size = np.arange(n), 1
    first_of, last_of = np.searchsorted(group, group, "left"), np.searchsorted(group, group, "right")
    widest = int((last_of - first_of).max()) if n else 0
    at = np.arange(n)
    while size < n and widest > 1:
        run = at // size
        lo = np.minimum((run ^ 1) * size, n)
        hi = np.minimum(lo + size, n)
        # Groups stand in order already: only the sibling's part of the same group is searched.
        first, last = np.clip(first_of, lo, hi), np.clip(last_of, lo, hi)
        open_ = np.flatnonzero(first < last)
        while len(open_):
            mid = (first[open_] + last[open_]) // 2
            less = side.before(order[mid], order[open_])
            first[open_[less]], last[open_[~less]] = mid[less] + 1, mid[~less]
            open_ = open_[first[open_] < last[open_]]
        merged = np.full(n, -1)
        merged[np.minimum(run, run ^ 1) * size + (at - run * size) + (first - lo)] = order
        if (merged < 0).any():  # comparisons that contradict each other: collisions
            return _verified(side, group, np.arange(n), np.full(n, -1, np.int64), at[:0], {*group.tolist()})
        order, size = merged, size * 2
    shared = np.full(n, -1, np.int64)
    inner = np.flatnonzero(first_of < at)
    shared[inner] = side.extension(order[inner - 1], order[inner])
    return _verified(side, group, order, shared, inner, set())


def _verified(side: Side, group: np.ndarray, order: np.ndarray, shared: np.ndarray, inner: np.ndarray, wrong: set[int]) -> tuple[np.ndarray, np.ndarray]:
    """Neighbours' bytes compared; a group with a pair that hashes misled is sorted anew byte by byte, as are those known to be wrong."""
    raw = side.data.tobytes()
    a, b, n = order[inner - 1], order[inner], shared[inner]
    x, y = side.byte(a, n), side.byte(b, n)
    wrong.update(group[inner[(x > y) | ((x == y) & (x >= 0))]].tolist())
    for k, (p, q, m) in enumerate(zip(side.at[a].tolist(), side.at[b].tolist(), n.tolist(), strict=True)):
        if (raw[p : p + m] != raw[q : q + m]) if side.step > 0 else (raw[p - m : p] != raw[q - m : q]):
            wrong.add(int(group[inner[k]]))
    for g in wrong:
        lo, hi = np.searchsorted(group, g, "left"), np.searchsorted(group, g, "right")
        kept = sorted(((side.content(raw, i), i) for i in order[lo:hi].tolist()))
        order[lo:hi] = [i for _, i in kept]
        for k in range(1, len(kept)):
            u, v = kept[k - 1][0], kept[k][0]
            shared[lo + k] = next((i for i, (s, t) in enumerate(zip(u, v, strict=False)) if s != t), min(len(u), len(v)))
    return order, shared


def suffix_order(data: bytes, starts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(suffix starts in lexicographic order, common extension of each with the one before it, 0 for the first) of one buffer."""
    buffer = np.frombuffer(data, np.uint8)
    at = np.arange(len(buffer)) if starts is None else np.asarray(starts, np.int64)
    side = Side(buffer, pk.Prefixes(pk.byte_values(buffer)), at, len(buffer) - at, 1)
    order, shared = sorted_strings(side, np.zeros(len(at), np.int64))
    return at[order], np.maximum(shared, 0)


def again(node: np.ndarray, bodies: list[bytes], at: np.ndarray, times: np.ndarray, width: int) -> list[np.ndarray]:
    """For every run, which of its windows occur more than once among the runs of its node. A run is the bytes that its windows cover, the place
    of the anchor in them and how often it occurs; nodes are any numbers, runs of a node are different."""
    order = np.argsort(node, kind="stable")
    group, at, times = np.unique(node[order], return_inverse=True)[1], at[order], times[order]
    data = np.frombuffer(b"".join(bodies[i] for i in order.tolist()), np.uint8)
    size = np.array([len(bodies[i]) for i in order.tolist()], np.int64)
    start = np.cumsum(size) - size
    prefixes, m = pk.Prefixes(pk.byte_values(data)), len(order)
    sides = []
    for step, length in ((1, size - at), (-1, at)):
        side = Side(data, prefixes, start + at, length, step)
        sides.append(sorted_strings(side, group))
    most, least = at, at - (size - width)  # bytes from a window's start to the anchor
    marks = [np.zeros(int(a - b) + 1, bool) for a, b in zip(most, least, strict=True)]
    weight = np.minimum(times, 2)
    for o in range(int(least.min()), int(most.max()) + 1) if m else ():
        some = np.flatnonzero((least <= o) & (o <= most))
        if not len(some):
            continue
        code = np.zeros(m, np.int64)
        for (by, shared), depth in zip(sides, (width - o, o), strict=True):
            kind = np.empty(m, np.int64)
            kind[by] = np.cumsum(shared < depth)  # strings that share `depth` bytes stand together
            code = code * (m + 1) + kind
        _, where = np.unique(code[some], return_inverse=True)
        found = some[(np.bincount(where, weights=weight[some]) > 1)[where]]
        for i in found.tolist():
            marks[i][most[i] - o] = True
    out: list[np.ndarray] = [np.zeros(0, bool)] * m
    for k, i in enumerate(order.tolist()):
        out[i] = marks[k]
    return out


# ---- packs
class Runs:
    """Runs of windows of `width` bytes with one anchor, in the order of the texts: first and last window start, place of the anchor."""

    def __init__(self, pack: pk.Pack, width: int):
        self.width, self.gram = width, min(GRAM, width)
        if pack.extra:
            self.first, long, ahead = self._unpacked(pack.extra)
            self.last, self.anchor = self.first + long, self.first + ahead
        else:
            self._find(pack)

    def _find(self, pack: pk.Pack) -> None:
        width, gram = self.width, self.gram
        span = width - gram + 1
        count = np.maximum(pack.sizes - width + 1, 0)  # windows of each text
        ends = pack.starts + count
        parts = []
        total = len(pack.data) - width + 1 if count.sum() else 0
        for lo in range(0, total, _STEP):
            hi = min(lo + _STEP, total)
            part = pk.Prefixes(pk.byte_values(pack.data[lo : hi + width - 1])).of_all(gram)
            value = (part & np.uint64(~((1 << 22) - 1) & 0xFFFFFFFFFFFFFFFF)) | np.arange(len(part), dtype=np.uint64)
            reach = 1
            while reach * 2 <= span:
                value = np.minimum(value[:-reach], value[reach:])
                reach *= 2
            if reach < span:
                value = np.minimum(value[: hi - lo], value[span - reach : span - reach + hi - lo])
            anchor = (value[: hi - lo] & np.uint64((1 << 22) - 1)).astype(np.int64) + lo
            edge = np.concatenate([[True], anchor[1:] != anchor[:-1]])
            for cut in (pack.starts, ends):
                cut = cut[(cut >= lo) & (cut < hi)]
                edge[cut - lo] = True
            first = np.flatnonzero(edge) + lo
            parts.append((first, np.append(first[1:], hi) - 1, anchor[first - lo]))
        first, last, anchor = (np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, np.int64) for i in range(3))
        text = np.minimum(np.searchsorted(pack.ends, first, side="right"), max(0, len(pack.ends) - 1))
        inside = last + width <= pack.ends[text] if len(first) else np.zeros(0, bool)
        self.first, self.last, self.anchor = first[inside], last[inside], anchor[inside]

    def packed(self) -> bytes:
        parts = np.diff(self.first, prepend=0).astype(np.uint32), (self.last - self.first).astype(np.uint16), (self.anchor - self.first).astype(np.uint16)
        return pk.squeeze(b"".join(p.tobytes() for p in parts))

    @staticmethod
    def _unpacked(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        raw = pk.expand(data)
        n = len(raw) // 8
        ahead = (np.frombuffer(raw, np.uint16, n, o).astype(np.int64) for o in (4 * n, 6 * n))
        return np.cumsum(np.frombuffer(raw, np.uint32, n).astype(np.int64)), *ahead

    def _steps(self, pick: np.ndarray):
        """As many of the picked runs at a time as fit into _STEP bytes: their numbers, where their bytes start, and where they end."""
        lo = 0
        while lo < len(pick):
            hi = max(lo + 1, int(np.searchsorted(self.last[pick], self.first[pick[lo]] + _STEP)))
            yield pick[lo:hi], lo, hi, int(self.first[pick[lo]]), int(self.last[pick[hi - 1]]) + self.width
            lo = hi

    def keys(self, pack: pk.Pack) -> np.ndarray:
        """The hash of every run's anchor, which brings runs together."""
        out = np.empty(len(self.first), np.uint64)
        for some, lo, hi, start, end in self._steps(np.arange(len(self.first))):
            at = self.anchor[some] - start
            out[lo:hi] = pk.mix(pk.Prefixes(pk.byte_values(pack.data[start:end])).of(at, at + self.gram) ^ np.uint64(0xA24BAED4963EE407))
        return out

    def names(self, pack: pk.Pack, seed: int, pick: np.ndarray) -> np.ndarray:
        """A hash of the bytes of the picked runs and of the anchor's place in them, which names each among those of its anchor."""
        out = np.empty(len(pick), np.uint64)
        for some, lo, hi, start, end in self._steps(pick):
            first, last = self.first[some], self.last[some]
            place = pk.mix((self.anchor[some] - first + 1 + (seed << 32)).astype(np.uint64))
            out[lo:hi] = pk.mix(pk.Prefixes(pk.byte_values(pack.data[start:end], 1)).of(first - start, last + self.width - start) ^ place)
        return out


def _shared_anchors(packs: DataFrame, width: int) -> DataFrame:
    """Answers to the packs' questions which anchors occur in other packs: shortened hashes, each once a pack."""
    bits = pk.bucket_bits(pk.total_bytes(packs) // 50)

    def question(_, pack):
        short = _short(Runs(pack, width).keys(pack), bits)
        for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bits), bits):
            yield b, pk.squeeze(np.diff(short[lo:hi].astype(np.uint32), prepend=np.uint32(0)))

    def answer(bodies):
        parts = [np.cumsum(pk.expand(b, np.uint32), dtype=np.uint32) for b in bodies]
        value, where, count = np.unique(np.concatenate(parts), return_inverse=True, return_counts=True)
        return [np.packbits(x).tobytes() for x in np.split(count[where] > 1, np.cumsum([len(p) for p in parts])[:-1])]

    return pk.answered(pk.ask(packs, question, bits), answer)


def _short(hashes: np.ndarray, bits: int) -> np.ndarray:
    return np.unique(hashes >> np.uint64(32 - bits))


def _met(found: dict[tuple[int, int], bytes], keys: np.ndarray) -> np.ndarray:
    """Which anchors occur more than once, in this pack or another. The questions' `kind` is the number of bucket bits."""
    value, where, times = np.unique(keys, return_inverse=True, return_counts=True)
    if not len(keys):
        return np.zeros(0, bool)
    bits = next(iter(found))[0]
    short = _short(keys, bits)
    flags = np.zeros(len(short), bool)
    for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bits), bits):
        flags[lo:hi] = np.unpackbits(np.frombuffer(found[bits, b], np.uint8), count=hi - lo).astype(bool)
    return (times > 1)[where] | flags[np.searchsorted(short, keys >> np.uint64(32 - bits))]


# ---- frames
_RUN = "pack long, node long, name long, at int, times long, body binary"


def _halves(runs: DataFrame, width: int, seed: int) -> DataFrame:
    """Runs (node, low, high, name, at, body, times), whose anchors stand `low` to `high` bytes behind their windows' starts, cut into two at the middle: parent node and name, half (1: the windows
    that start earlier), and the run that is left in the half."""
    middle = F.floor((F.col("low") + F.col("high")) / 2).cast("int")
    least = F.col("at") - (F.length("body") - width)

    def half(k: int, a: Column, b: Column) -> Column:
        most, rest = F.least(F.col("at"), b), F.greatest(least, a)
        body = F.substring("body", F.col("at") - most + 1, most + width - rest)
        common = F.substring("body", F.col("at") - a + 1, width - (b - a))
        node = F.xxhash64(F.lit(seed), "node", F.lit(k), common)
        run = F.struct(F.lit(k).alias("half"), node.alias("node"), a.alias("low"), b.alias("high"), F.xxhash64(F.lit(seed), most, body).alias("name"), most.alias("at"), "times", body.alias("body"))
        return F.when(most >= rest, run)

    both = F.explode(F.array(half(0, F.col("low"), middle), half(1, middle + 1, F.col("high")))).alias("r")
    return runs.select(F.col("node").alias("parent"), F.col("name").alias("parent_name"), both).filter("r is not null").select("parent", "parent_name", "r.*")


def _distinct(runs: DataFrame) -> DataFrame:
    """Copies of a run as one, by their bytes."""
    found = stash(runs.groupBy("node", "low", "high", "name", "at", "body").agg(F.sum("times").alias("times")), codec="zstd")
    if not found.groupBy("node", "name").count().filter("count > 1").isEmpty():
        raise NamesCollide
    return found


class NamesCollide(Exception):
    """Two different runs of an anchor have one name: names are drawn anew."""


def _marks(runs: DataFrame, width: int, seed: int) -> DataFrame:
    """(node, name, marks): a byte for each window of each run, 1 if it occurs again; runs without any are left out.

    Nodes with few runs are sorted, the others cut into halves, level by level; then what the halves have learnt is put together again, from the last level up."""

    def work(table: pa.Table) -> pa.Table:
        found = again(table.column("node").to_numpy(), table.column("body").to_pylist(), table.column("at").to_numpy().astype(np.int64), table.column("times").to_numpy(), width)
        some = pa.array([bool(m.any()) for m in found], pa.bool_())
        marks = pa.array([m.astype(np.uint8).tobytes() for m in found], pa.binary())
        return pa.table([table.column("node"), table.column("name"), marks], ["node", "name", "marks"]).filter(some)

    told, cuts, now = [], [], _distinct(runs)
    while True:
        crowded = stash(now.filter("low < high").groupBy("node").agg(F.count(F.lit(1)).alias("_n")).filter(f"_n > {CROWD}").select("node"))
        some = not crowded.isEmpty()
        calm = now.join(crowded, "node", "left_anti") if some else now
        buckets = now.count() // BUCKET + 1
        told.append(stash(calm.withColumn("_bucket", F.pmod(F.xxhash64("node"), F.lit(buckets))).groupBy("_bucket").applyInArrow(work, "node long, name long, marks binary")))
        if not some:
            break
        cuts.append(stash(_halves(now.join(crowded, "node", "left_semi"), width, seed), codec="zstd"))
        now = _distinct(cuts[-1])
    marks = told.pop()
    while cuts:
        half = cuts.pop().select("parent", "parent_name", "half", "node", "name", (F.length("body") - width + 1).alias("_windows"))
        half = half.join(marks.hint("merge"), ["node", "name"], "left").withColumn("marks", F.coalesce("marks", F.expr("cast(repeat('\0', _windows) as binary)")))
        part = lambda k: F.coalesce(F.max(F.when(F.col("half") == k, F.col("marks"))), F.lit(b""))
        whole = half.groupBy(F.col("parent").alias("node"), F.col("parent_name").alias("name")).agg(F.concat(part(1), part(0)).alias("marks"))
        marks = told.pop().unionByName(whole)
    return marks


def repeats(docs: DataFrame, width: int = 200, doc_id: str = "doc_id", text: str = "text", spans: bool = False) -> DataFrame:
    """One row per row of `docs`: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with `spans` also `kept` (the remaining bytes) and
    `removed`, the maximal removed runs as (from, to).

    A byte goes if any `width` bytes that cover it also start elsewhere, in this text or another; matches never cross texts and are judged on the input.
    Null and empty texts, and those shorter than `width`, lose nothing; an empty table gives no rows. Rows that repeat an id, null ids included, are texts of their own. Other columns are
    ignored. A text longer than a pack is a pack of its own, read in steps of a megabyte: its bytes and some bytes for each of its runs are held at once."""
    packs = pk.packed(docs, doc_id, text, extra=lambda pack: Runs(pack, width).packed())
    known = stash(_shared_anchors(packs, width))
    for seed in range(8):
        try:
            return _judged(packs, known, width, seed, spans)
        except NamesCollide:
            continue
    raise RuntimeError("names of runs collide under every seed")


def _judged(packs: DataFrame, known: DataFrame, width: int, seed: int, spans: bool) -> DataFrame:
    def sent(name, pack, found):
        runs = Runs(pack, width)
        key = runs.keys(pack)
        pick = np.flatnonzero(_met(found, key))
        key, check = key[pick], runs.names(pack, seed, pick)
        order = np.lexsort((check, key))  # stable: the first of equal runs stands first
        fresh = np.ones(len(order), bool)
        fresh[1:] = (key[order][1:] != key[order][:-1]) | (check[order][1:] != check[order][:-1])
        at, times = order[fresh], np.diff(np.flatnonzero(fresh), append=len(order))
        by = np.argsort(at)  # in the order of the text, where neighbours overlap and compress well
        at, times = at[by], times[by]
        first, last, ahead = (x[pick[at]] for x in (runs.first, runs.last, runs.anchor - runs.first))
        bodies = [pack.raw[a : b + width] for a, b in zip(first.tolist(), last.tolist(), strict=True)]
        columns = np.full(len(at), name), key[at].view(np.int64), check[at].view(np.int64), ahead.astype(np.int32), times
        return pa.table([*map(pa.array, columns), pa.array(bodies, pa.binary())], ["pack", "node", "name", "at", "times", "body"])

    runs = stash(pk.told(packs, known, sent, _RUN), codec="zstd")
    places = F.lit(0).alias("low"), F.lit(width - min(GRAM, width)).alias("high")
    marks = stash(_marks(runs.select("*", *places), width, seed))
    answers = runs.select("pack", "node", "name").join(marks.hint("merge"), ["node", "name"])

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        row = left.slice(0, 1).to_pylist()[0]
        pack = pk.Pack(row["ids"], row["sizes"], row["body"], row["extra"])
        runs = Runs(pack, width)
        key = runs.keys(pack).view(np.int64)
        nodes = right.column("node").to_numpy()
        pick = np.flatnonzero(np.isin(key, nodes))
        found = dict(zip(zip(nodes.tolist(), right.column("name").to_pylist(), strict=True), right.column("marks").to_pylist(), strict=True))
        marks = [found.get(x) for x in zip(key[pick].tolist(), runs.names(pack, seed, pick).view(np.int64).tolist(), strict=True)]
        pick = pick[[m is not None for m in marks]]
        # All marks in a row, a zero after each run: stretches of ones are stretches of windows.
        flat = np.frombuffer(b"".join(m + b"\0" for m in marks if m is not None), np.uint8)
        begin = np.cumsum(runs.last[pick] - runs.first[pick] + 2) - (runs.last[pick] - runs.first[pick] + 2)
        edges = np.flatnonzero(np.diff(flat, prepend=np.uint8(0)))
        of = np.searchsorted(begin, edges[::2], "right") - 1
        shift = runs.first[pick][of] - begin[of]
        return _report(pack, edges[::2] + shift, edges[1::2] - 1 + width + shift, spans)

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary, removed array<struct<start:long,end:long>>" if spans else "")
    return packs.groupBy("pack").cogroup(answers.groupBy("pack")).applyInArrow(finish, schema)


def _report(pack: pk.Pack, start: np.ndarray, end: np.ndarray, spans: bool) -> pa.Table:
    """Rows of a pack's texts, from stretches in ascending order that lie within texts and may overlap."""
    text = np.searchsorted(pack.ends, start, side="right")
    fresh = np.ones(len(start), bool)
    fresh[1:] = (start[1:] > end[:-1]) | (text[1:] != text[:-1])  # ends ascend with the starts
    start, text, end = start[fresh], text[fresh], end[np.append(fresh[1:], True)] if len(end) else end
    bounds = np.searchsorted(text, np.arange(len(pack.sizes) + 1))
    rows = []
    for i, (key, a, b) in enumerate(zip(pack.names(), pack.starts.tolist(), pack.ends.tolist(), strict=True)):
        gone = list(zip(start[bounds[i] : bounds[i + 1]].tolist(), end[bounds[i] : bounds[i + 1]].tolist(), strict=True))
        edges = [a, *(x for pair in gone for x in pair), b]
        kept = b"".join(pack.raw[x:y] for x, y in zip(edges[::2], edges[1::2], strict=True))
        row = [key, b - a, b - a - len(kept), len(gone), hashlib.sha256(kept).hexdigest()]
        rows.append(row + ([kept, [{"start": x - a, "end": y - a} for x, y in gone]] if spans else []))
    names, kinds = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"], [pa.int64()] * 4 + [pa.string()]
    if spans:
        names, kinds = [*names, "kept", "removed"], [*kinds, pa.binary(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))]
    return pa.table([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)
