import hashlib
import math
import random
import time

import pytest
from pyspark.sql import functions as F

from spanweave.llm import bpe, url_filter
from spanweave.llm.queries import TARGETS, vocabulary

SAMPLES = ["", " ", "Hello  World's <|endoftext|> it''s ΑΣ İx 123 <|startoftext|>é", "a" * 5000, "abcabd" * 2000, "é ́xḍ̇", "''s'll-'re don't", "\x85\xa0\u2003x\u2028y\x1cz", "ẞßſ ﬁ", "日本語テキスト\u0590Ꟁꟁ"]


def texts():
    rng = random.Random(1)
    some = ["".join(rng.choice("abcdeth 'sréÉΣ1!\n\t<|>́") for _ in range(rng.randint(0, 200))) for _ in range(400)]
    some += ["".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(0, 900))) for _ in range(60)]
    blocks = ["".join(chr(c) for c in range(i, i + 64) if not 0xD800 <= c < 0xE000) for i in range(0, 0x12000, 64)]
    return SAMPLES + some + blocks


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary())


def test_ids_counts_and_decoded_texts_are_the_librarys(library):
    own = bpe.tokenizer_of(vocabulary())
    for chunk in (7, 50, 16_384):
        machine = bpe.CountTransducer(own, chunk)
        for t in texts():
            ids = library.encode(t, add_special_tokens=False).ids
            if chunk == 7:
                assert own.encode(t) == ids, ascii(t[:60])
                decoded = library.decode(ids, skip_special_tokens=False)
                assert own.decode(ids) == decoded
                assert own.digest(t) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest())
            assert machine.count(t) == len(ids), ascii(t[:60])


def test_machine_survives_its_bounds(library):
    machine = bpe.CountTransducer(bpe.tokenizer_of(vocabulary()))
    machine.most_states, machine.most_pieces = 50, 20
    for t in texts()[:80]:
        assert machine.count(t) == len(library.encode(t, add_special_tokens=False).ids)


def test_chunk_maps_compose_associatively():
    machine = bpe.CountTransducer(bpe.tokenizer_of(vocabulary()))
    rng = random.Random(2)
    for _ in range(60):
        parts = ["".join(rng.choice("ab's \n1") for _ in range(rng.randrange(9))) for _ in range(3)]
        a, b, c = map(machine.chunk_map, parts)
        assert machine.compose(machine.compose(a, b), c) == machine.compose(a, machine.compose(b, c))


@pytest.mark.parametrize("piece", ["a" * 1_000_000, "." * 200_000, "_" * 50_000, "ab" * 60_000, "haha" * 3000 + "x" + "haha" * 777])
def test_long_rows_of_few_characters_end_soon(library, piece):
    own, began = bpe.Tokenizer(vocabulary()), time.time()
    want = library.encode(piece, add_special_tokens=False).ids
    assert own.encode(piece) == want and bpe.CountTransducer(own).count(piece) == len(want)
    assert time.time() - began < 60


def test_merging_long_pieces_is_merging_short_ones(library):
    own, rng = bpe.tokenizer_of(vocabulary()), random.Random(6)
    for _ in range(200):
        piece = "".join(rng.choices("abetaoinsh", k=rng.randint(1, 500)))
        want = library.encode(piece, add_special_tokens=False).ids
        assert own.merge_long(own.base(piece)) == own.tree(own.base(piece)) == want


def test_state_maps_compose_associatively():
    machine, rng = bpe.CountTransducer(bpe.tokenizer_of(vocabulary())), random.Random(8)
    symbols = [machine.tokenizer.inner[ord(c)] for c in rng.choices("abetin", k=90)]
    a, b, c = (bpe.StateMap(machine, symbols[i : i + 30]) for i in (0, 30, 60))
    left, right, whole = bpe.Composed(bpe.Composed(a, b), c), bpe.Composed(a, bpe.Composed(b, c)), bpe.StateMap(machine, symbols)
    for entry in machine.states[:200]:
        assert left(entry) == right(entry) == whole(entry)


def test_token_frames(odd, nothing, library):
    text = {r.doc_id: r.text or "" for r in odd.collect()}
    counts = bpe.token_counts(odd, vocabulary(), limit=300).collect()
    assert len(counts) == 11
    for r in counts:
        n = len(library.encode(text[r.doc_id], add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(text[r.doc_id].encode()), n, n > 300)
    for r in bpe.encode_texts(odd, vocabulary()).collect():
        assert r.ids == library.encode(text[r.doc_id], add_special_tokens=False).ids
    for r in bpe.encoding_digests(odd, vocabulary()).collect():
        ids = library.encode(text[r.doc_id], add_special_tokens=False).ids
        decoded = library.decode(ids, skip_special_tokens=False)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest())
    assert bpe.encoding_digests(nothing, vocabulary()).collect() == [] and bpe.token_counts(nothing, vocabulary()).collect() == []


URLS = [
    ("http://www.x.org/a", "www.x.org", "/a", "org/", "allow"),
    ("https://Sub.EXAMPLE.org/es/1?q#f", "sub.example.org", "/es/1", "example.org/es/", "block"),
    ("https://example.org/en/19", "example.org", "/en/19", "example.org/en/1", "block"),
    ("https://badexample.org/es/1", "badexample.org", "/es/1", "org/", "allow"),
    ("http://a.com/de/", "a.com", "/de/", "com/de/", "block"),
    ("http://a.com/fr/x", "a.com", "/fr/x", "com/fr/", "allow"),
    ("http://a.com/en/x", "a.com", "/en/x", None, None),
    ("http://x.org?y=/", "x.org", "", None, None),
    ("http://notcom/fr/", "notcom", "/fr/", None, None),
    ("a://b://c", "b:", "//c", None, None),
    ("no scheme", "", "", None, None),
    ("", "", "", None, None),
    (None, "", "", None, None),
    ("http://ÄÖ.net/ü", "ÄÖ.net", "/ü", None, None),
]


def test_rules_and_model(spark):
    rows = [(i, *u, 1) for i, u in enumerate(URLS + URLS[:2])]
    df = spark.createDataFrame([(r[0], r[1], 5) for r in rows], "page_id long, url string, line int")
    got = {r.page_id: r for r in url_filter.judge_urls(df).collect()}
    assert len(got) == len(rows)
    for i, _, host, path, rule, verdict, _ in rows:
        assert (got[i].host, got[i].path, got[i].rule) == (host, path, rule)
        assert got[i].verdict == verdict if verdict else got[i].verdict in ("allow", "block")
    assert url_filter.judge_urls(df.limit(0)).collect() == []
    assert url_filter.judge_urls(df.filter("page_id = 10")).count() == 1


def test_the_ratio_tells_the_classes_apart(spark):
    rng = random.Random(3)
    good = [f"http://a{rng.randrange(99)}.org/news/{rng.randrange(999)}" for _ in range(150)]
    bad = [f"http://b{rng.randrange(99)}.com/de/xxx/{rng.randrange(999)}" for _ in range(150)]
    other = [f"http://c.net/news/{k}" for k in range(20)] + [f"http://c.net/de/xxx/{k}" for k in range(20)]
    df = spark.createDataFrame(list(enumerate(good + bad + other)), "page_id long, url string")
    got = {r.page_id: r.verdict for r in url_filter.judge_urls(df).collect()}
    assert [got[300 + k] for k in range(40)] == ["allow"] * 20 + ["block"] * 20


def weights_by_hand(lines, order, smoothing):
    """millionths of the log ratio for every string, from counts in dictionaries. `lines`: line to (allow, block)."""
    count, of, seen, signs = {}, {}, {}, set()
    for line, both in lines.items():
        for at in range(order, len(line)):
            signs.add(line[at])
            gram = line[at - order : at + 1]
            seen[gram] = seen.get(gram, 0) + 1
            for j in range(order + 1):
                for side in (0, 1):
                    for table, key in ((count, line[at - j : at + 1]), (of, line[at - j : at])):
                        table[j, key, side] = table.get((j, key, side), 0) + both[side]

    def chance(gram, side):
        p = 1 / len(signs)
        for j in range(order + 1):
            key = gram[order - j :]
            p = (count[j, key, side] + smoothing * p) / (of[j, key[:-1], side] + smoothing)
        return p

    return {g: (n, round((math.log(chance(g, 0)) - math.log(chance(g, 1))) * 1_000_000)) for g, n in seen.items()}


def test_log_ratios_by_hand(spark):
    rng, order = random.Random(5), 3
    bodies = ["", "/%C3%A4", "ü.net/ü😀😀/x", "a" * 300] + ["".join(rng.choices("abc./😀", k=rng.randint(1, 30))) for _ in range(80)]
    lines = {chr(url_filter.START) * order + b + chr(url_filter.END): (rng.randrange(3), rng.randrange(3)) for b in bodies}
    df = spark.createDataFrame([(i, k, *v) for i, (k, v) in enumerate(lines.items())], "line_id long, line string, allow long, block long")
    model = url_filter.log_ratios(df, order)
    got = {r.gram: (r.seen, r.weight) for r in model.collect()}
    want = weights_by_hand(lines, order, url_filter.SMOOTHING)
    assert got.keys() == want.keys()
    assert all(got[g][0] == want[g][0] and abs(got[g][1] - want[g][1]) <= 1 for g in want)
    scores = {r.line_id: r.score for r in url_filter.mean_ratios(df, model, order).collect()}
    for i, line in enumerate(lines):
        parts = [got[line[at - order : at + 1]][1] for at in range(order, len(line))]
        assert scores[i] == sum(parts) // len(parts)


def test_what_the_models_gather_grows(spark):
    rng = random.Random(9)
    urls = [f"http://{rng.randrange(10**9):x}.net/{rng.randrange(10**9):x}" for _ in range(2000)]
    sizes = []
    for n in (200, 2000):
        line = url_filter.framed(url_filter.host_of(F.col("url")), url_filter.path_of(F.col("url")))
        df = spark.createDataFrame([(u,) for u in urls[:n]], "url string").select(line.alias("line"), F.lit(1).alias("allow"), F.lit(0).alias("block"))
        sizes.append(url_filter.log_ratios(df).count())
    assert sizes[1] > 5 * sizes[0]


def test_a_very_long_url(spark):
    df = spark.createDataFrame([(1, "http://a.net/" + "xyz%" * 250_000), (2, "http://b.org/x"), (3, "http://b.com/de/")], "page_id long, url string")
    began = time.time()
    got = {r.page_id: (len(r.path), r.rule) for r in url_filter.judge_urls(df).collect()}
    assert got == {1: (1_000_001, None), 2: (2, "org/"), 3: (4, "com/de/")} and time.time() - began < 60


def test_native_operators_run_no_python(spark, sf):
    from spanweave.llm.queries import QUERIES

    for name in ("op5_exact_dedup", "op10_urls"):
        plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_pipeline_against_its_parts(spark, library):
    import corpus_pipeline
    from spanweave.llm import exact_dedup, mixing, quality, simhash

    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    good = quality.quality_scores(docs, labels).filter("predicted = 1").select("doc_id")
    left = docs.join(good, "doc_id", "left_semi")
    seen, rows = set(), []
    for r in sorted(left.select("doc_id", "text", "source").collect()):
        body = " ".join(r.text.replace("\x1c", "\x1c").split(" "))
        key = __import__("re").sub(r"[\x20\x09-\x0D]+", " ", body)
        if key not in seen:
            seen.add(key)
            rows.append(r)
    assert exact_dedup.drop_exact(left).count() == len(rows)
    up = {r.doc_id: r.doc_id for r in rows}
    sets = {r.doc_id: {*simhash.shingle_hashes(r.text, 5)} for r in rows}
    where: dict[int, list[int]] = {}
    for i, s in sets.items():
        for h in sorted(s)[: len(s) // 5 + 1]:
            where.setdefault(h, []).append(i)
    pairs = {(a, b) for group in where.values() for a in group for b in group if a < b}
    for a, b in pairs:
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) and up[a] != up[b]:
            x, y = sorted((up[a], up[b]))
            up = {k: (x if v == y else v) for k, v in up.items()}
    want = {k for k, v in up.items() if k == v}
    got = corpus_pipeline.run(spark, d).collect()
    text = {r.doc_id: r.text for r in rows}
    assert len({r.doc_id for r in got}) == len(got) and len({r.doc_id for r in got} ^ want) <= 0.01 * len(want)
    for r in got[:60]:
        assert r.n_tokens == len(library.encode(text[r.doc_id], add_special_tokens=False).ids)
    assert len(corpus_pipeline.STAGES) == 5
    kept = docs.join(spark.createDataFrame([(r.doc_id,) for r in got], "doc_id long"), "doc_id", "left_semi")
    places = {r.doc_id: r.position for r in mixing.schedule(kept, TARGETS).collect()}
    assert {r.doc_id: r.mix_position for r in got} == places and sorted(places.values()) == sorted({*places.values()})


def test_pipeline_of_odd_and_empty_tables(spark, odd, tmp_path):
    import corpus_pipeline

    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    extra = odd.unionByName(odd.limit(4)).unionByName(odd.withColumn("doc_id", F.lit(None).cast("long"))).withColumn("mix_position", F.lit(1)).withColumn("_key_", F.lit(2))
    for name, docs in (("odd", extra), ("none", extra.limit(0))):
        docs.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        labels.write.parquet(f"{tmp_path}/{name}/labels.parquet")
    got = corpus_pipeline.run(spark, f"{tmp_path}/odd").collect()
    assert {r.doc_id for r in got} == {1, 3, 4, 5, 7, 8, 9, 10} - {3} and len(got) == 7
    assert corpus_pipeline.run(spark, f"{tmp_path}/none").collect() == []
