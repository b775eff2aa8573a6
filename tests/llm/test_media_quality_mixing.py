import hashlib
import io
import math
import struct
import zlib
from collections import Counter
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanweave.llm import media, mixing, quality


@pytest.mark.parametrize("shape", [(1, 64), (5, 7), (13, 3), (3, 1)])
def test_images_come_back_and_areas_are_means(shape):
    x = np.random.default_rng(1).integers(0, 256, shape, dtype=np.uint8)
    assert (media.decode(media.pgm(x)) == x).all()
    assert (media.decode(media.bmp(x)) == x).all()
    for h, w in ((8, 9), (2, 3), (32, 32)):
        wide = np.kron(x.astype(float), np.ones((h, w))).reshape(h, x.shape[0], w, x.shape[1])
        assert np.allclose(wide.mean(axis=(1, 3)), media.area_resize(x, h, w))


def test_netpbm_kinds():
    assert media.decode(b"P1\n# note\n3 2\n1 0 1\n010\n").tolist() == [[0, 255, 0], [255, 0, 255]]
    assert media.decode(b"P2 2 1 255 7 9").tolist() == [[7, 9]]
    assert media.decode(b"P3 1 1 255 1 2 3").tolist() == [[[1, 2, 3]]]
    assert media.decode(b"P4\n9 1\n\x80\x80").tolist() == [[0, *[255] * 7, 0]]
    assert media.decode(b"P5 1 2 65535\n\x01\x02\x03\x04").tolist() == [[258], [772]]
    assert media.decode(b"P6 1 1 255\n\x01\x02\x03").tolist() == [[[1, 2, 3]]]
    assert media.decode(b"P2 3 1 15 0 7 15").tolist() == [[0, 119, 255]]
    assert media.decode(b"P2 2 1 1023 0 1023").tolist() == [[0, 65535]]
    for bad in (b"", b"P5 2 2 255\n\x01", b"P5", b"BMxx", b"P9 1 1", b"P2 2 1 9 -1 3", b"P2 2 1 9 1 10", b"P5 99999999999 99999999999 255\n", b"P1 2 1 0 7"):
        with pytest.raises(ValueError):
            media.decode(bad)


def bitmap(bits, how, body, extra=b"", width=1, height=1, colours=0):
    start = 54 + len(extra)
    return struct.pack("<2sIHHIIiiHHIIiiII", b"BM", start + len(body), 0, 0, start, 40, width, height, 1, bits, how, len(body), 0, 0, colours, 0) + extra + body


def test_bmp_kinds():
    masks = struct.pack("<III", 0xFF, 0xFF00, 0xFF0000)
    assert media.decode(bitmap(32, 3, bytes([10, 20, 30, 0]), masks)).tolist() == [[[10, 20, 30]]]
    assert media.decode(bitmap(32, 0, bytes([10, 20, 30, 0]))).tolist() == [[[30, 20, 10]]]
    assert media.decode(bitmap(16, 0, struct.pack("<HH", 31 << 10, 0))).tolist() == [[[255, 0, 0]]]
    assert media.decode(bitmap(24, 0, bytes([1, 2, 3, 0]))).tolist() == [[[3, 2, 1]]]
    assert media.decode(bitmap(1, 0, b"\x40\0\0\0", bytes([0, 0, 0, 0, 9, 9, 9, 0]), width=2)).tolist() == [[0, 9]]
    for bad in (bitmap(8, 0, b"\5\0\0\0", b"\0" * 4, colours=1), bitmap(8, 0, b"\5"), bitmap(32, 3, b"\0" * 4, b"\0" * 12), bitmap(24, 0, b"", width=1 << 30, height=1 << 30)):
        with pytest.raises(ValueError):
            media.decode(bad)


def test_a_broken_image_never_fails_the_job(spark):
    rows = [(str(k), bytearray(b)) for k, b in enumerate((bitmap(8, 0, b"\5\0\0\0", b"\0" * 4, colours=1), b"P5 99999999999 99999999999 255\n", b"BM" + b"\0" * 60, b""))]
    got = media.media_tiles(spark.createDataFrame(rows, "key string, data binary")).collect()
    assert len(got) == 4 and all(r.tile is None and r.height is None for r in got)


def test_tiles_of_a_column(spark, tmp_path):
    x = np.arange(64 * 48, dtype=np.uint8).reshape(48, 64)
    rows = spark.createDataFrame([("a", bytearray(media.pgm(x))), ("b", None), ("c", bytearray(b"no image"))], "key string, data binary")
    media.write_tiles(rows, str(tmp_path / "tiles"))
    got = {r.key: r for r in spark.read.parquet(str(tmp_path / "tiles")).collect()}
    assert np.load(io.BytesIO(got["a"].tile)).shape == (32, 32) and got["a"].height == 48
    assert got["b"].tile is None and got["c"].dhash is None
    assert len(media.difference_hash(x)) == 16


def test_payloads(odd, nothing):
    rows = media.payload_report(odd).collect()
    for r, text in ((r, dict(odd.select("doc_id", "text").collect())[r.doc_id]) for r in rows):
        raw = (text or "").encode()
        padded = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]))
    assert len(rows) == 11 and media.payload_report(nothing).collect() == []


def test_quality_of_held_out_rows(spark, odd, nothing):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    rows = quality.quality_scores(docs, labels).join(labels, "doc_id").collect()
    out = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == (r.score >= 0.3) for r in rows)
    assert sum(r.predicted == r.quality for r in out) >= 0.95 * len(out)
    assert quality.quality_scores(nothing, labels).collect() == []
    assert quality.quality_scores(odd, labels.limit(0)).count() == 11
    kept = quality.keep_good(docs.limit(100), labels)
    assert kept.columns == docs.columns


def test_attention_learns_from_one_passage_of_many():
    rng = np.random.default_rng(0)
    bags, labels = [], []
    for k in range(300):
        x = rng.normal(0, 0.1, (rng.integers(1, 8), quality.FEATURES)).astype(np.float32)
        x[rng.integers(len(x)), 0] += 3 * (k % 2)
        bags.append(x)
        labels.append(k % 2)
    model = quality.Attention.fit(bags[:200], np.array(labels[:200], np.float32), epochs=200, batch=32)
    assert ((model.score(bags[200:]) > 0.5) == np.array(labels[200:])).mean() > 0.95


def test_scores_are_those_of_a_plain_forward_pass():
    rng = np.random.default_rng(5)
    bags = [rng.normal(size=(n, quality.FEATURES)).astype(np.float32) for n in (2, 1, 4, 3)]
    model = quality.Attention.fit(bags, np.array([0, 1, 1, 0], np.float32), epochs=3)
    p = {k: v.astype(float).tolist() for k, v in model.parts.items()}
    for bag, got in zip(bags, model.score(bags), strict=True):
        encoded, weights = [], []
        for x in bag:
            x = [(float(a) - float(m)) / float(s) for a, m, s in zip(x, model.mean, model.scale, strict=True)]
            h = [math.tanh(sum(x[i] * p["E"][i][j] for i in range(len(x))) + p["e"][j]) for j in range(len(p["e"]))]
            gate = [math.tanh(sum(h[i] * p["V"][i][j] for i in range(len(h)))) / (1 + math.exp(-sum(h[i] * p["U"][i][j] for i in range(len(h))))) for j in range(len(p["w"]))]
            encoded.append(h)
            weights.append(math.exp(sum(g * w for g, w in zip(gate, p["w"], strict=True))))
        z = [sum(w * h[j] for w, h in zip(weights, encoded, strict=True)) / sum(weights) for j in range(len(p["c"]))]
        want = 1 / (1 + math.exp(-(sum(a * b for a, b in zip(z, p["c"], strict=True)) + p["b"][0])))
        assert abs(want - got) < 1e-4


def test_a_gradient_is_that_of_the_loss():
    rng = np.random.default_rng(3)
    bags = [rng.normal(size=(n, quality.FEATURES)).astype(np.float64) for n in (1, 3, 2)]
    y = np.array([0, 1, 1.0])
    model = quality.Attention.fit([b.astype(np.float32) for b in bags], y.astype(np.float32), epochs=1)
    model.parts = {k: v.astype(np.float64) + 0.05 for k, v in model.parts.items()}
    lengths = np.array([1, 3, 2])

    def loss():
        p = model._forward(np.concatenate(bags), np.cumsum(lengths) - lengths, lengths)[-1]
        return -np.mean(y * np.log(p) + (1 - y) * np.log(1 - p))

    grad = model._gradient(bags, y)
    for name in ("E", "V", "U", "w", "c", "b"):
        at = (0,) * model.parts[name].ndim
        old = model.parts[name][at]
        model.parts[name][at] = old + 1e-5
        up = loss()
        model.parts[name][at] = old - 1e-5
        down = loss()
        model.parts[name][at] = old
        assert abs((up - down) / 2e-5 - np.ravel(grad[name])[0]) < 1e-4, name


@pytest.mark.parametrize("shares", [{"a": 1}, {"a": 3, "b": 2, "c": 5}, {"a": 7, "b": 1, "c": 1, "d": 2}, {f"s{k}": k + 1 for k in range(12)}])
def test_a_round_keeps_every_source_within_a_block(shares):
    q, seen = sum(shares.values()), Counter()
    for slot, (source, release, due) in enumerate(mixing.one_round(shares)):
        assert release <= slot < due
        seen[source] += 1
        assert all(abs(seen[s] - a * (slot + 1) / q) < 1 for s, a in shares.items())
    assert seen == shares


def brute_mix(blocks, targets):
    """Slot by slot from the definition: of the blocks that are released, the one due first; blocks that do not exist leave their slot to the next."""
    total = sum(targets.values())
    share = {s: t / total for s, t in targets.items()}
    next_block, clock, out = dict.fromkeys(blocks, 1), 0, []
    while any(next_block[s] <= n for s, n in blocks.items()):
        due = {s: (math.ceil(i / share[s]), s) for s, i in next_block.items() if math.floor((i - 1) / share[s]) <= clock}
        if due:
            source = min(due.values())[1]
            if next_block[source] <= blocks[source]:
                out.append((source, next_block[source] - 1, clock, math.floor((next_block[source] - 1) / share[source]), due[source][0]))
            next_block[source] += 1
        clock += 1
    return [(slot, *x) for slot, x in enumerate(out)]


@pytest.mark.parametrize("named", [None, {"src0": 0.5, "src1": 0.2}, {"src0": 0.9996, "src1": 0.0004, "src2": 0}])
def test_every_document_has_its_place(spark, small, named):
    few = small.filter("source in ('src0', 'src1', 'src2', 'src3')")
    rows = mixing.schedule(few, named, block=4).collect()
    assert sorted(r.position for r in rows) == sorted({r.position for r in rows}) and len(rows) == few.count()
    counts = Counter(r.source for r in rows)
    targets = {s: Fraction(str((named or {}).get(s, Fraction(1, 4)))) if s in (named or {}) else Fraction(1, 4) for s in counts}
    targets = {s: t or Fraction("0.0004") for s, t in targets.items()}
    want = brute_mix({s: math.ceil(n / 4) for s, n in counts.items()}, targets)
    assert sorted({(r.slot, r.source, r.block, r.clock, r.release, r.deadline) for r in rows}) == want
    assert all(r.release <= r.clock < r.deadline and r.slot == r.position // 4 for r in rows)


def test_mixes_of_odd_and_empty_tables(spark, odd, nothing, small):
    assert mixing.schedule(odd).count() == 11 and mixing.schedule(nothing).collect() == []
    mixed = mixing.mixed(small.withColumn("mix_position", F.lit("x")), {"src0": 0.5}, position="place")
    places = {r.doc_id: r.position for r in mixing.schedule(small, {"src0": 0.5}).collect()}
    got = mixed.collect()
    assert [r.doc_id for r in got] == sorted(places, key=places.get) and [r.place for r in got] == sorted(places.values())
    assert mixed.columns == [*small.columns, "mix_position", "place"]
    assert mixing.mixed(odd.unionByName(odd.withColumn("doc_id", F.lit(None).cast("long")))).count() == 22 and mixing.mixed(nothing).collect() == []


def test_a_plan_is_linear_in_its_sources():
    weights = mixing.whole_weights([f"s{k}" for k in range(3000)], None)
    assert sum(weights.values()) == 3000 == len(mixing.one_round(weights))
    assert mixing.whole_weights(["a", "b"], {"a": 0.9996, "b": 0.0004}) == {"a": 2499, "b": 1}


def test_training_reads_every_passage_of_the_rows_it_takes(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(quality.Attention, "fit", staticmethod(lambda bags, labels, **_: seen.append([len(b) for b in bags])))
    docs = spark.createDataFrame([(d, "word " * (102 * 60)) for d in range(20)], "doc_id long, text string")
    labels = spark.createDataFrame([(d, d % 2) for d in range(20)], "doc_id long, quality int")
    whole = len(quality.passages("word " * (102 * 60)))
    quality.train(docs, labels)
    quality.train(docs, labels, most_passages=3 * whole)
    assert whole > 48 and {*seen[0]} == {whole} and len(seen[0]) > 3 and seen[1] == [whole] * 3
