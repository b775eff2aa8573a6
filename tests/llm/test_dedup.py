import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanweave.llm import byte_windows, exact_dedup, packs, simhash, word_windows
from spanweave.llm.linking import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_exact_groups_with_and_without_collisions(odd, nothing):
    rows = odd.select("doc_id", "text").collect()
    body = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    want = sorted((r.doc_id, min(x.doc_id for x in rows if body(x.text) == body(r.text)), sum(body(x.text) == body(r.text) for x in rows), hashlib.sha256(body(r.text).encode()).hexdigest()) for r in rows)
    for digest in (exact_dedup.content_digest, lambda b: F.substring(F.md5(b), 1, 1).cast("binary"), lambda b: F.lit(b"x")):
        got = exact_dedup.exact_groups(odd, digest=digest).collect()
        assert sorted((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in got) == want
        assert all(r.kept == (r.doc_id == r.keep_id) for r in got)
    assert exact_dedup.exact_groups(nothing).collect() == []
    assert {r.doc_id for r in exact_dedup.drop_exact(odd).collect()} == {1, 3, 4, 5, 7, 8, 9, 10}


def test_exact_drops_rows_and_not_ids(spark, nothing):
    rows = [(3, "A", 1), (5, "A ", 2), (5, "B", 3), (None, "C", 5), (None, "C", 4), (7, None, 0), (8, "", 0), (9, "D", 2), (9, "D", 1), (10, " ", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, sha int").repartition(3)
    got = {tuple(r) for r in exact_dedup.drop_exact(df).collect()}
    assert got == {(3, "A", 1), (5, "A ", 2), (5, "B", 3), (None, "C", 4), (7, None, 0), (9, "D", 1), (10, " ", 0)}
    assert exact_dedup.drop_exact(nothing).columns == nothing.columns and exact_dedup.drop_exact(nothing).collect() == []


@pytest.mark.parametrize("size", [1024, 4096])
def test_words_whose_polynomials_agree_are_told_apart(spark, size):
    """The Thue-Morse word and its complement have one polynomial hash modulo 2**64, whatever the base."""
    word = "".join("ab"[bin(i).count("1") % 2] for i in range(size))
    same = " ".join(f"w{i}" for i in range(12))
    df = spark.createDataFrame([(1, f"{same} {word}"), (2, f"{same} {word.translate(str.maketrans('ab', 'ba'))}")], "doc_id long, text string")
    assert [(r.doc_id, r.n_removed) for r in word_windows.removals(df).orderBy("doc_id").collect()] == [(1, 0), (2, 0)]


def test_null_and_largest_ids_are_told_apart(spark):
    text = " ".join(f"w{i}" for i in range(60))
    df = spark.createDataFrame([(2**63 - 1, text), (None, text)], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.n_removed) for r in word_windows.removals(df).collect()) == [(0, 0), (2**63 - 1, 0)]
    assert {r.doc_id for r in byte_windows.repeats(df).collect()} == {None, 2**63 - 1}


def brute_words(rows, k=13):
    least, out = {}, []
    split = [(d, WORD.findall(t or "")) for d, t in rows]
    for d, w in split:
        for i in range(len(w) - k + 1):
            key = tuple(w[i : i + k])
            least[key] = min(d, least.get(key, d))
    for d, w in split:
        gone = [False] * len(w)
        for i in range(len(w) - k + 1):
            if least[tuple(w[i : i + k])] < d:
                gone[i : i + k] = [True] * k
        out.append((d, len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone, strict=True) if not g).encode()).hexdigest()))
    return sorted(out)


def brute_bytes(rows, k=200):
    times, out = {}, []
    raw = [(d, (t or "").encode()) for d, t in rows]
    for _, b in raw:
        for i in range(len(b) - k + 1):
            times[b[i : i + k]] = times.get(b[i : i + k], 0) + 1
    for d, b in raw:
        gone = bytearray(len(b))
        for i in range(len(b) - k + 1):
            if times[b[i : i + k]] > 1:
                gone[i : i + k] = b"\1" * k
        out.append((d, len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    return sorted(out)


@pytest.fixture(scope="module")
def passages(spark, small, odd):
    """Documents with planted overlaps of all kinds, few enough for brute force."""
    rng = random.Random(4)
    base = [(r.doc_id + 100, r.text) for r in small.limit(60).collect()]
    rows = base + [(r.doc_id, r.text) for r in odd.filter("doc_id <> 9").collect()]
    for k in range(25):
        a, b = rng.choice(base)[1], rng.choice(base)[1]
        i, j = rng.randrange(max(1, len(a))), rng.randrange(max(1, len(b)))
        rows.append((rng.randrange(1, 400), a[i : i + rng.randint(150, 420)] + rng.choice(["", " ", "é"]) + b[j : j + rng.randint(150, 420)]))
    rows += [(500, "y" * 200), (501, "z" * 201), (502, "ab" * 150), (7, "a b c d e f g h i j k l m " * 5), (503, "a b c d e f g h i j k l m")]
    return rows, spark.createDataFrame(rows, "doc_id long, text string").repartition(4)


@pytest.mark.parametrize("size", [2_000, 1_000_000])
def test_windows_against_brute_force(passages, monkeypatch, size):
    rows, df = passages
    monkeypatch.setattr(packs, "PACK_BYTES", size)
    assert sorted(tuple(r) for r in word_windows.removals(df).collect()) == brute_words(rows)
    assert sorted(tuple(r) for r in byte_windows.repeats(df).collect()) == brute_bytes(rows)


def test_spans_and_kept_texts(spark, nothing):
    text = " ".join(f"w{i}" for i in range(30))
    df = spark.createDataFrame([(1, text), (2, "x " + text + " y")], "doc_id long, text string")
    got = {r.doc_id: r for r in word_windows.removals(df, spans=True).collect()}
    assert got[1].kept_text == text and got[2].kept_text == "x y" and [tuple(s) for s in got[2].removed] == [(1, 31)]
    got = {r.doc_id: r for r in byte_windows.repeats(df, width=40, spans=True).collect()}
    assert got[1].kept == b"" and got[2].kept == b"x  y"[:2] + b" y" and [tuple(s) for s in got[2].removed] == [(2, 2 + len(text))]
    assert word_windows.removals(nothing).collect() == [] and byte_windows.repeats(nothing).collect() == []


def test_anchor_runs_in_small_steps(monkeypatch):
    rng = random.Random(1)
    texts = [bytes(rng.choice(b"ab") for _ in range(rng.randrange(900))) for _ in range(6)]
    body = np.arange(6).tobytes(), np.array([len(t) for t in texts]).tobytes(), packs.squeeze(b"".join(texts))
    pack = packs.Pack(*body)
    runs = byte_windows.Runs(pack, 200)
    covered = [s for a, b in zip(runs.first, runs.last, strict=True) for s in range(a, b + 1)]
    assert covered == [s for a, e in zip(pack.starts, pack.ends, strict=True) for s in range(a, e - 199)]
    every = np.arange(len(runs.first))
    before = runs.keys(pack).tolist(), runs.names(pack, 3, every).tolist()
    stored = byte_windows.Runs(packs.Pack(*body, runs.packed()), 200)
    assert all((getattr(stored, x) == getattr(runs, x)).all() for x in ("first", "last", "anchor"))
    monkeypatch.setattr(byte_windows, "_STEP", 397)
    again = byte_windows.Runs(pack, 200)
    assert [s for a, b in zip(again.first, again.last, strict=True) for s in range(a, b + 1)] == covered
    assert (runs.keys(pack).tolist(), runs.names(pack, 3, every).tolist()) == before


def test_runs_of_an_anchor_are_sorted_and_verified(monkeypatch):
    """Windows that occur again among runs, against brute force; with hashes that collide as well."""
    rng = random.Random(9)
    for good in (True, False):
        if not good:
            monkeypatch.setattr(packs, "mix", lambda x: x & np.uint64(3))
        node, bodies, at, times = [], [], [], []
        for k in range(12):
            seen = set()
            for _ in range(rng.randrange(1, 30)):
                left = rng.randrange(0, 7)
                body = bytes(rng.choices(b"ab", k=left)) + b"ANCH" + bytes(rng.choices(b"ab", k=6 - rng.randrange(left + 1)))
                if (body, left) not in seen:
                    seen.add((body, left))
                    node, bodies, at, times = [*node, k * 7 % 5], [*bodies, body], [*at, left], [*times, rng.choice([1, 1, 1, 2])]
        keep = {(n, b, a): i for i, (n, b, a) in enumerate(zip(node, bodies, at, strict=True))}.values()
        node, bodies, at, times = ([x[i] for i in keep] for x in (node, bodies, at, times))
        count = {}
        for n, b, t in zip(node, bodies, times, strict=True):
            for i in range(len(b) - 9):
                count[n, b[i : i + 10]] = count.get((n, b[i : i + 10]), 0) + t
        want = [[count[n, b[i : i + 10]] > 1 for i in range(len(b) - 9)] for n, b in zip(node, bodies, strict=True)]
        got = byte_windows.again(np.array(node), bodies, np.array(at), np.array(times), 10)
        assert [g.tolist() for g in got] == want


@pytest.mark.parametrize("crowd", [1, 6])
def test_crowded_anchors_are_split_without_loss(spark, monkeypatch, crowd):
    """A line in many surroundings, some of which are copies of each other in part."""
    monkeypatch.setattr(byte_windows, "CROWD", crowd)
    monkeypatch.setattr(byte_windows, "BUCKET", 20)
    monkeypatch.setattr(packs, "PACK_BYTES", 3_000)
    rng = random.Random(11)
    line = "".join(rng.choices("abcdefgh ", k=150))
    noise = lambda n: "".join(rng.choices("ijklmnop", k=n))
    lefts, rights = [noise(120) for _ in range(4)], [noise(120) for _ in range(4)]
    rows = []
    for k in range(40):
        left, right = rng.choice(lefts), rng.choice(rights)
        rows.append((k, noise(30) + left[rng.randrange(100) :] + line + right[: rng.randrange(10, 120)] + noise(40)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(tuple(r) for r in byte_windows.repeats(df).collect()) == brute_bytes(rows)


def test_suffixes_are_sorted():
    for text in (b"", b"a", b"banana" * 4, b"abracadabra mississippi" * 3, bytes(random.Random(2).choices(b"ab", k=300))):
        order, ext = byte_windows.suffix_order(text)
        want = sorted(range(len(text)), key=lambda i: text[i:])
        assert order.tolist() == want
        for k in range(1, len(want)):
            a, b = text[want[k - 1] :], text[want[k] :]
            assert ext[k] == next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))


def brute_fingerprint(text):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints_and_classes(odd, nothing, small, spark):
    df = odd.select("doc_id", "text").union(small.selectExpr("doc_id + 100", "text"))
    rows = [(r.doc_id, brute_fingerprint(r.text)) for r in df.collect()]
    group = {f: f for _, f in rows}
    for f in group:
        for g in list(group):
            if (f ^ g).bit_count() <= 2 and group[f] != group[g]:
                a, b = group[f], group[g]
                group = {k: (min(a, b) if v in (a, b) else v) for k, v in group.items()}
    want = sorted((d, f"{f:016x}", min(e for e, g in rows if group[g] == group[f])) for d, f in rows)
    assert sorted(tuple(r) for r in simhash.near_classes(df).collect()) == want
    assert simhash.near_classes(nothing).collect() == []


@pytest.mark.parametrize("crowd", [4096, 20])
@pytest.mark.parametrize("segments", [4, 8, 16])
def test_every_close_pair_is_linked(spark, crowd, segments):
    rng = random.Random(segments)
    prints = [rng.getrandbits(64) for _ in range(60)]
    prints += [prints[0] ^ rng.getrandbits(12) for _ in range(90)]  # a crowd that agrees on most bits
    prints += [p ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for p in prints[:40]] + [p ^ (1 << rng.randrange(64)) for p in prints[:9]]
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    found = simhash.links(spark.createDataFrame([(p,) for p in signed], "bits long"), segments=segments, crowd=crowd)
    want = {(min(a, b), max(a, b)) for a in signed for b in signed if a != b and ((a ^ b) & ((1 << 64) - 1)).bit_count() <= 2}
    got = {tuple(r) for r in found.collect()}
    assert got == want


def test_similar_documents_are_found(spark, small, nothing, odd):
    rng = random.Random(5)
    rows = [(r.doc_id * 10, r.text) for r in small.collect()]
    for d, t in rows[:80]:
        words = t.split(" ")
        for _ in range(max(1, len(words) // 60)):
            words[rng.randrange(len(words))] = "changed"
        rows.append((d + 1, " ".join(words)))
    near = {(a, b) for a, t in rows for b, u in rows if a < b and a // 10 == b // 10 and simhash.similarity(t, u) >= 0.8}
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in simhash.similar_classes(df).collect()}
    assert sum(got.get(a, a) == got.get(b, -1) for a, b in near) >= 0.9 * len(near) > 30
    assert simhash.similar_classes(nothing).collect() == []
    assert {r.doc_id for r in simhash.similar_classes(odd).collect()} >= {1, 2, 3, 5, 6}


@pytest.mark.parametrize(("few", "block"), [(16, 256), (2, 4)])
def test_families_of_merely_alike_texts_hide_no_pairs(spark, monkeypatch, few, block):
    """300 texts that differ in one slot are 0.7 alike; among the later ones stand pairs whose slots are half equal."""
    monkeypatch.setattr(simhash, "SMALL", few)
    monkeypatch.setattr(simhash, "BLOCK", block)
    rng = np.random.default_rng(3)
    draw = lambda n: rng.integers(0, 10**6, n).astype(str).tolist()
    frame, rows = draw(494), []
    for d in range(300):
        rows.append((d, frame[:200] + draw(106) + frame[200:]))
    for d in range(300, 340, 2):
        slot = draw(106)
        rows += [(d, frame[:200] + slot + frame[200:]), (d + 1, frame[:200] + slot[:60] + draw(46) + frame[200:])]
    rows = [(d, " ".join(w)) for d, w in rows]
    assert 0.6 < simhash.similarity(rows[0][1], rows[301][1]) < 0.78 and all(simhash.similarity(rows[d][1], rows[d + 1][1]) > 0.82 for d in range(300, 340, 2))
    got = {r.doc_id: r.component_id for r in simhash.similar_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert set(got.items()) <= {(d, d // 2 * 2) for d in range(300, 340)}
    assert len(got) >= 36


def test_near_rows_are_told_by_id_and_text(spark, nothing):
    words = [f"w{k}" for k in range(60)]
    a, b, c = " ".join(words), " ".join([*words[:59], "x"]), " ".join(reversed(words))
    rows = [(5, a), (5, c), (3, b), (None, a + " y"), (None, "lone words of no other row at all"), (7, None)]
    got = simhash.drop_near(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(got.collect(), key=str) == sorted([(5, c), (3, b), (None, "lone words of no other row at all"), (7, None)], key=str)
    assert simhash.drop_near(nothing).collect() == [] and simhash.drop_near(nothing).columns == nothing.columns


def test_blocks_join_classes_and_only_those():
    """Links found in a block leave the classes that all pairs would give."""
    rng = np.random.default_rng(8)
    texts = [rng.integers(0, 99, 40).astype(str).tolist() for _ in range(6)]
    texts = [" ".join(t[:39] + [f"end{k}"]) for t in texts for k in range(3)]
    ids = list(range(len(texts)))
    bits = np.array([simhash.wide_fingerprint(t) for t in texts], np.uint64)
    shingles = lambda i: {*simhash.shingle_hashes(texts[i], 5)}
    for sides, want in ((np.zeros(18, int), 12), (np.arange(18) % 2, 12)):
        links = simhash._linked_in_block(ids, ids, sides, bits, shingles, 64 * simhash.LEAST_WIDE, 0.8)
        assert len(links) == want and all(u // 3 == v // 3 and (not sides.any() or sides[u] != sides[v]) for u, v in links)
    assert simhash._linked_in_block(ids, [0] * 18, np.zeros(18, int), bits, shingles, 64 * simhash.LEAST_WIDE, 0.8) == []


@pytest.mark.parametrize("n", [1000, 200_000, 12_000_000])
@pytest.mark.parametrize("kind", ["appended", "replaced", "scattered"])
def test_every_kind_of_edit_at_the_edge_is_found_at_every_size(n, kind):
    """Texts at 0.8 to each other share a segment in nine of ten cases, wherever their differences stand."""
    width, wide = simhash.ring(n)
    rng, found = np.random.default_rng(n), []

    def ring_bits(words):
        bits = np.unpackbits(np.array(simhash.wide_fingerprint(" ".join(words), wide), "<u8").view(np.uint8), bitorder="little")
        return np.concatenate([bits, bits[:width]])

    for _ in range(120):
        words = rng.integers(0, 10**6, 604).astype(str)
        other = words.copy()
        if kind == "appended":
            other = np.concatenate([words, rng.integers(0, 10**6, 148).astype(str)])
        elif kind == "replaced":
            other[300:361] = rng.integers(0, 10**6, 61).astype(str)
        else:
            other[rng.choice(120, 13, replace=False) * 5 + 2] = "changed"
        assert 0.795 < simhash.similarity(" ".join(words), " ".join(other)) < 0.825
        run = np.cumsum(np.pad((ring_bits(words) == ring_bits(other)).astype(int), (1, 0)))
        found.append(((run[width:] - run[:-width])[: 64 * wide : simhash.STRIDE] == width).any())
    assert np.mean(found) >= 0.9


@pytest.mark.parametrize("times", [10, 50])
def test_a_repeated_line_counts_once(spark, times):
    """Repeats of a line change no set of shingles, so they change few bits and lose no pair."""
    rng = np.random.default_rng(times)
    words, line = rng.integers(0, 10**6, 500).astype(str).tolist(), rng.integers(0, 10**6, 10).astype(str).tolist()
    a, b = " ".join(words + line), " ".join(words + line * times)
    assert simhash.similarity(a, b) > 0.95
    x, y = (np.array(simhash.wide_fingerprint(t), np.uint64) for t in (a, b))
    assert np.bitwise_count(x ^ y).sum() / (64 * simhash.LEAST_WIDE) < 0.1
    got = simhash.similar_classes(spark.createDataFrame([(1, a), (2, b)], "doc_id long, text string")).collect()
    assert {(r.doc_id, r.component_id) for r in got} == {(1, 1), (2, 1)}


def test_components_of_links(spark):
    rng = random.Random(6)
    pairs = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(k, k + 1) for k in range(300, 380)] + [(1000, k) for k in range(1001, 1100)]
    up = {v: v for p in pairs for v in p if p[0] != p[1]}
    for a, b in pairs:
        if a != b and up[a] != up[b]:
            x, y = sorted((up[a], up[b]))
            up = {k: (x if v == y else v) for k, v in up.items()}
    assert dict(components(spark.createDataFrame(pairs, "u long, v long")).collect()) == up


@pytest.mark.parametrize("n", [100, 200_000, 8_000_000, 20_000_000_000])
def test_the_ring_finds_pairs_at_the_edge_alike_at_every_size(n):
    """Pairs that differ in EDGE_BITS of their bits share a segment in nine of ten cases at least."""
    width, wide = simhash.ring(n)
    trials, size = 400, 64 * wide
    equal = np.random.default_rng(n).random((trials, size)) >= simhash.EDGE_BITS
    turned = np.concatenate([equal, equal[:, :width]], axis=1)
    run = np.cumsum(np.pad(turned, ((0, 0), (1, 0))), axis=1, dtype=np.int64)
    whole = (run[:, width : width + size] - run[:, :size])[:, :: simhash.STRIDE] == width
    assert whole.any(axis=1).mean() >= 0.9


def test_bits_that_differ_at_the_edge_of_similarity():
    """Texts at a similarity of 0.8 over five words differ in some EDGE_BITS of their wide fingerprints."""
    rng, shares = np.random.default_rng(5), []
    for _ in range(40):
        words = rng.integers(0, 10**6, 600).astype(str)
        other = words.copy()
        other[rng.choice(600, 13, replace=False)] = "changed"
        a, b = " ".join(words), " ".join(other)
        if 0.78 < simhash.similarity(a, b) < 0.84:
            x, y = (np.array(simhash.wide_fingerprint(t), np.uint64) for t in (a, b))
            shares.append(np.bitwise_count(x ^ y).sum() / (64 * simhash.LEAST_WIDE))
    assert len(shares) > 10 and abs(np.mean(shares) - simhash.EDGE_BITS) < 0.03
