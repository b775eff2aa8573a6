"""SimHash near-duplicates: fingerprints of word shingles, linked by Hamming distance with a pigeonring filter.

A fingerprint is read as a ring of `segments` equal parts. If two fingerprints differ in at most `radius` bits, some start on the ring
exists from which every run of l parts differs in at most l * radius / segments bits. So the first parts of such a chain are equal: they are
the key candidates meet on, for each start, and the longer runs are tested before the full distance. Crowded keys are made longer by the same rule, applied to the other bits.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.llm import packs as pk
from spanweave.llm.linking import components
from spanweave.llm.packs import mix
from spanweave.llm.shared import stash, texts

SEED = 42


def shingle_hashes(text: str, words: int) -> list[int]:
    """XXH64 of every shingle, repeats included; fewer words than a shingle make one, none give none."""
    found = text.encode().lower().split()  # of bytes: A-Z and ASCII white space only
    if not found:
        return []
    joined = b" ".join(found)
    ends = np.cumsum([len(w) + 1 for w in found]) - 1
    starts = [0, *(ends[:-1] + 1).tolist()]
    ends = ends.tolist()
    digest, k = xxhash.xxh64_intdigest, min(words, len(found))
    return [digest(joined[a:b], SEED) for a, b in zip(starts, ends[k - 1 :], strict=False)]


def majority(hashes: np.ndarray) -> int:
    """64 bits, each set if it is set in over half of the hashes; 0 of none."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 65_536):
        part = np.ascontiguousarray(hashes[at : at + 65_536], "<u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprint(text: str, words: int = 3) -> int:
    return majority(np.array(shingle_hashes(text, words), np.uint64))


def fingerprints(docs: DataFrame, words: int = 3, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, bits (the fingerprint as a signed long), of whole texts; null texts are empty."""

    def work(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                bits = np.array([fingerprint(t, words) for t in part.column(1).to_pylist()], np.uint64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(bits.view(np.int64))], ["doc_id", "bits"])

    return texts(docs, doc_id, text).mapInArrow(work, "doc_id long, bits long")


def _chains(places: list[int], parts: int, radius: int) -> list[list[int]]:
    """The bits at `places` are a ring, cut into `parts`. If at most `radius` of them differ, some start exists from which every run of l parts differs in at most l * radius / parts
    bits. For each start: masks of its longest runs that may differ in 0, 1, ... radius - 1 bits."""
    edges = [k * len(places) // parts for k in range(parts + 1)]
    pieces = [sum(1 << p for p in places[x:y]) for x, y in zip(edges[:-1], edges[1:], strict=True)]
    longest = [-(-(b + 1) * parts // radius) - 1 for b in range(radius)]
    return [[sum(pieces[(start + k) % parts] for k in range(run)) for run in longest] for start in range(parts)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(prints: DataFrame, radius: int = 2, segments: int = 8, crowd: int = 256) -> DataFrame:
    """(u, v), u < v: all pairs of different fingerprints (column `bits`) within `radius` bits.

    Fingerprints meet on the equal parts that a chain begins with (`_chains` of the whole ring); the chain's longer runs are tested, then the whole distance. Where more than
    `crowd` of them meet, they all agree on those parts, so that the ring of the other bits holds whatever difference there is: it is cut into parts
    in turn, and they meet on a longer key. At most 2**(bits left) fingerprints can agree, so this ends."""
    if not 0 < radius < segments or 64 % segments:
        raise ValueError("segments must divide 64 and exceed radius")
    spark, runs = prints.sparkSession, [f"c{b}" for b in range(1, radius)]
    now, found = prints.select("bits", F.lit(0).cast("long").alias("mask")).distinct(), []
    cuts = {0: _chains([*range(64)], segments, radius)}
    while True:
        # One row a chain: at most `segments` times the few starts that each further cut has.
        table = [(_signed(m), _signed(m | chain[0]), *map(_signed, chain[1:])) for m, chains in cuts.items() for chain in chains]
        chains = spark.createDataFrame(table, ", ".join(f"{c} long" for c in ("of", "mask", *runs)))
        keyed = now.withColumnRenamed("mask", "of").join(F.broadcast(chains), "of").select("bits", "mask", F.col("bits").bitwiseAND(F.col("mask")).alias("lead"), *runs)
        left = {m: [p for p in range(64) if not m >> p & 1] for m in {m | chain[0] for m, chains in cuts.items() for chain in chains}}
        cuts = {_signed(m): _chains(p, max(radius + 1, min(segments, len(p) // 8)), radius) for m, p in left.items() if 2 ** len(p) > crowd}
        some = False
        if cuts:
            crowded = stash(keyed.groupBy("mask", "lead").count().filter(F.col("count") > crowd).join(F.broadcast(spark.createDataFrame([(m,) for m in cuts], "mask long")), "mask", "left_semi").select("mask", "lead"))
            cuts = {r["mask"] % (1 << 64): cuts[r["mask"]] for r in crowded.select("mask").distinct().collect()}  # masks, not fingerprints: as many as the chains have
            some = bool(cuts)
        calm = keyed.join(crowded, ["mask", "lead"], "left_anti") if some else keyed
        u = calm.select(F.col("mask").alias("mask_u"), F.col("lead").alias("lead_u"), F.col("bits").alias("u"), *runs)
        v = calm.select("mask", "lead", F.col("bits").alias("v"))
        apart = F.col("u").bitwiseXOR(F.col("v"))
        close = F.bit_count(apart) <= radius
        for b, run in enumerate(runs, 1):
            close = (F.bit_count(apart.bitwiseAND(F.col(run))) <= b) & close
        met = (F.col("mask_u") == F.col("mask")) & (F.col("lead_u") == F.col("lead")) & (F.col("u") < F.col("v"))
        near = u.join(v, met & close).select("u", "v")
        found.append(stash(near) if some or found else near)
        if not some:
            return reduce(DataFrame.unionByName, found).distinct()
        now = stash(keyed.join(crowded, ["mask", "lead"], "left_semi").select("bits", "mask").distinct())


def near_classes(docs: DataFrame, words: int = 3, radius: int = 2, segments: int = 8, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits), component_id: the least doc_id that a chain of links reaches.

    Texts without words, null ones included, have fingerprint 0 and are linked like any other. Equal fingerprints are one
    vertex, so copies are never paired. Repeated rows come out repeated; other columns are ignored; an empty table gives no rows."""
    prints = stash(fingerprints(docs, words, doc_id, text))
    vertices = prints.groupBy("bits").agg(F.min("doc_id").alias("least"))
    joined = components(links(prints, radius, segments))
    placed = vertices.join(joined, F.col("bits") == F.col("key"), "left").select("bits", "least", F.coalesce("component", "bits").alias("component"))
    named = placed.groupBy("component").agg(F.min("least").alias("component_id"))
    names = stash(placed.join(named, "component").select("bits", "component_id"))
    return prints.join(names, "bits").select("doc_id", F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), "component_id")


# ---- classes by similarity
#: Least 64-bit words of a wide fingerprint; bits from one segment's start to the next one's.
LEAST_WIDE, STRIDE = 12, 8
#: Groups of up to SMALL documents are compared in pairs by a join, larger ones in blocks of BLOCK documents.
SMALL, BLOCK = 16, 256
#: Documents whose fingerprints stand in one row.
CRATE = 2048


def edge_bits(least: float) -> float:
    """Share of bits in which two sets at a similarity of `least` differ, at most: what they share is 2 least / (1 + least) of their mean size or more,
    and so is their cosine, whatever kind of edit lies between them (a geometric mean is never above the arithmetic one)."""
    return float(np.arccos(2 * least / (1 + least)) / np.pi)


EDGE_BITS = edge_bits(0.8)


def ring(n: int, edge: float = EDGE_BITS) -> tuple[int, int]:
    """(bits of a segment, 64-bit words of the ring) for `n` documents. Segments of log2(n) + 3 bits are seldom shared by chance. The ring grows with
    them, as n to the power 0.24, so that three separate stretches of equal segments are to be expected where `edge` of the bits differ: a pair there is found
    with a chance of some 1 - exp(-3) = 0.95 at every size, closer ones nearly always."""
    width = min(56, max(16, int(np.ceil(np.log2(max(2, n)))) + 3))
    stretches = 64 / STRIDE * (1 - (1 - edge) ** STRIDE) * (1 - edge) ** width  # a word's share
    return width, max(LEAST_WIDE, int(np.ceil(3 / stretches)))


def wide_fingerprint(text: str, wide: int = LEAST_WIDE, words: int = 5) -> list[int]:
    """`wide` fingerprints of the same set of shingles (each counts once, as in `similarity`) under different hashes: their distance tells similarity to about one part in a hundred."""
    hashes = np.unique(np.array(shingle_hashes(text, words), np.uint64))
    steps = np.arange(1, wide + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return [majority(mix(hashes + step)) for step in steps]


def similarity(a: str, b: str, words: int = 5) -> float:
    """Shared part of all different word shingles of two texts; two texts without words are alike."""
    return _alike({*shingle_hashes(a, words)}, {*shingle_hashes(b, words)})


def _alike(x: set[int], y: set[int]) -> float:
    return len(x & y) / len(x | y) if x or y else 1.0


def keyed_rows(docs: DataFrame) -> DataFrame:
    """`docs` and `_key`, a number for every row: its doc_id where no other row has it, and else one from 2**62 on, drawn from id and text; rows that have both in common share it.
    Ids are taken to be below 2**62. Columns of any other name stand."""
    often = stash(docs.groupBy(F.col("doc_id").cast("long").alias("_id")).agg(F.count(F.lit(1)).alias("_n")).filter("_n > 1 or _id is null").select("_id"))
    if often.isEmpty():
        return docs.withColumn("_key", F.col("doc_id").cast("long"))
    drawn = F.shiftrightunsigned(F.xxhash64("doc_id", "text"), 2).bitwiseOR(F.lit(1 << 62))
    marked = docs.join(often.withColumn("_often", F.lit(True)), F.col("doc_id").cast("long").eqNullSafe(F.col("_id")), "left")
    return marked.withColumn("_key", F.when(F.col("_often"), drawn).otherwise(F.col("doc_id").cast("long"))).select(*docs.columns, "_key")


def drop_near(docs: DataFrame, **how) -> DataFrame:
    """The rows of `docs` that stay, all columns: of each class of `similar_classes` the row with the least doc_id; rows whose id is null or carries several texts come last. A row is told by id
    and text, so that no text goes with another one's id. Null texts are empty; an empty table gives no rows."""
    rows = keyed_rows(docs)
    gone = similar_classes(rows, doc_id="_key", **how).filter("doc_id <> component_id").select(F.col("doc_id").alias("_key")).distinct()
    return rows.join(stash(gone).hint("merge"), "_key", "left_anti").select(*docs.columns)


def _linked_in_block(ids: list[int], classes: list[int], sides: np.ndarray, bits: np.ndarray, shingles, limit: int, least: float) -> list[tuple[int, int]]:
    """Links that join different classes, among the documents of one block (all of side 0) or between two (sides 0 and 1). Near pairs come first, and
    a pair whose classes have met by then is passed over: it would join nothing."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.get(x, x) != x:
            x = root[x]
        return x

    near, of = [], np.array(classes)
    for i in range(len(ids)):
        away = np.bitwise_count(bits[i + 1 :] ^ bits[i]).sum(axis=1, dtype=np.int64)
        wanted = (away <= limit) & (of[i + 1 :] != of[i])
        if sides.any():
            wanted &= sides[i + 1 :] != sides[i]
        near += [(int(away[j]), i, i + 1 + int(j)) for j in np.flatnonzero(wanted)]
    sets: dict[int, set[int]] = {}
    out = []
    for _, i, j in sorted(near):
        a, b = find(classes[i]), find(classes[j])
        if a == b:
            continue
        for k in (i, j):
            if k not in sets:
                sets[k] = shingles(k)
        if _alike(sets[i], sets[j]) >= least:
            root[a] = b
            out.append((ids[i], ids[j]))
    return out


def similar_classes(docs: DataFrame, words: int = 5, least: float = 0.8, most_bits: float | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, component_id) of the documents that are linked to others by a similarity of `least` or more over `words`-word shingles; component_id is the least doc_id of the class.

    Candidates share a segment of a ring of wide fingerprints at the same place (`ring` gives the sizes). Segments that only one document has are dropped before any
    row of theirs is made: crates of fingerprints ask for them by shortened hashes. A pair is dropped if over `most_bits` of all bits
    differ (default: a tenth more than at `least`), and the rest are linked if their shingles are as similar as asked. In every segment group each
    document is first held against the least one, one combinable minimum a group. Then the group's documents that are not yet in one class are compared with
    each other, in pairs in groups of up to SMALL documents and block by block in larger ones, until no two classes of the group are left uncompared. Null ids
    are left out; ids must not repeat (`keyed_rows` gives such ids); null texts are empty, and texts without words are alike; an empty table gives no rows, other columns are ignored. Found
    pairs are exact; a pair just above `least` is missed if no segment is equal (tests measure a recall of over 0.9)."""
    rows = texts(docs, doc_id, text).filter("doc_id is not null")
    edge = edge_bits(least)
    width, wide = ring(rows.count(), edge)
    limit = int((edge + 0.1 if most_bits is None else most_bits) * 64 * wide)
    names = [f"b{k}" for k in range(wide)]

    def work(batches):
        from pyspark import TaskContext

        serial = TaskContext.get().partitionId() << 32
        for batch in batches:
            for at in range(0, batch.num_rows, CRATE):
                part = batch.slice(at, CRATE)
                bits = np.array([wide_fingerprint(t, wide, words) for t in part.column(1).to_pylist()], np.uint64).reshape(-1, wide)
                ids = part.column(0).to_numpy().astype(np.int64).tobytes()
                row = [serial], [ids], [b""], [bits.tobytes()], [len(bits)], [b""]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(row, (pa.int64(), *(pa.binary(),) * 3, pa.int64(), pa.binary()), strict=True)], ["pack", "ids", "sizes", "body", "bytes", "extra"])
                serial += 1

    crates = stash(rows.mapInArrow(work, pk._PACK), codec="zstd")

    class Crate:
        """Ids and fingerprints of some documents."""

        def __init__(self, ids: bytes, _sizes: bytes, body: bytes, _extra: bytes):
            self.ids, self.bits = np.frombuffer(ids, np.int64), np.frombuffer(body, np.uint64).reshape(-1, wide)

        def segments(self) -> np.ndarray:
            """Bits k * STRIDE and on of every ring: documents x places."""
            out = np.empty((len(self.ids), 64 * wide // STRIDE), np.uint64)
            for k in range(out.shape[1]):
                word, shift = divmod(k * STRIDE, 64)
                low = self.bits[:, word] >> np.uint64(shift)
                if shift + width > 64:
                    low = low | (self.bits[:, (word + 1) % wide] << np.uint64(64 - shift))
                out[:, k] = low & np.uint64((1 << width) - 1)
            return out

        def slots(self) -> np.ndarray:
            """A segment and its place as one number."""
            found = self.segments()
            return mix(found + (np.arange(1, found.shape[1] + 1, dtype=np.uint64) << np.uint64(width)))

    bucket_bits = pk.bucket_bits(rows.count() * 64 * wide // STRIDE)

    def question(_, crate):
        short = np.unique(crate.slots() >> np.uint64(32 - bucket_bits))
        for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bucket_bits), bucket_bits):
            yield b, pk.squeeze(np.diff(short[lo:hi].astype(np.uint32), prepend=np.uint32(0)))

    def answer(bodies):
        parts = [np.cumsum(pk.expand(b, np.uint32), dtype=np.uint32) for b in bodies]
        _, where, count = np.unique(np.concatenate(parts), return_inverse=True, return_counts=True)
        return [np.packbits(x).tobytes() for x in np.split(count[where] > 1, np.cumsum([len(p) for p in parts])[:-1])]

    def shared(_, crate, found):
        slots = crate.slots()
        value, where, times = np.unique(slots, return_inverse=True, return_counts=True)
        short = np.unique(value >> np.uint64(32 - bucket_bits))
        flags = np.zeros(len(short), bool)
        for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bucket_bits), bucket_bits):
            flags[lo:hi] = np.unpackbits(np.frombuffer(found[0, b], np.uint8), count=hi - lo).astype(bool)
        some = (times > 1) | flags[np.searchsorted(short, value >> np.uint64(32 - bucket_bits))]
        doc, place = np.nonzero(some[where].reshape(slots.shape))
        key = crate.segments()[doc, place] + (place.astype(np.uint64) << np.uint64(width))
        return pa.table([pa.array(crate.ids[doc]), pa.array(key.view(np.int64))], ["doc_id", "key"])

    known = pk.answered(pk.ask(crates, question, 0, load=Crate), answer)
    keyed = stash(pk.told(crates, known, shared, "doc_id long, key long", load=Crate), codec="zstd")

    def spread(batches):
        for batch in batches:
            for row in batch.to_pylist():
                crate = Crate(row["ids"], b"", row["body"], b"")
                yield pa.RecordBatch.from_arrays([pa.array(crate.ids), *(pa.array(np.ascontiguousarray(crate.bits[:, k]).view(np.int64)) for k in range(wide))], ["doc_id", *names])

    met = keyed.select("doc_id").distinct()
    prints = stash(crates.mapInArrow(spread, "doc_id long, " + ", ".join(f"{n} long" for n in names)).join(met, "doc_id", "left_semi"))
    heads = stash(keyed.groupBy("key").agg(F.min("doc_id").alias("head"), F.max("doc_id").alias("_last"), F.count(F.lit(1)).alias("n")).filter("head <> _last").drop("_last"))
    members = stash(keyed.join(heads.hint("merge"), "key").select("key", "n", "head", "doc_id"))
    other = prints.select(F.col("doc_id").alias("head"), *(F.col(f"b{k}").alias(f"c{k}") for k in range(wide)))
    differ = sum((F.bit_count(F.col(f"b{k}").bitwiseXOR(F.col(f"c{k}"))) for k in range(wide)), F.lit(0))

    def judge(batches):
        for batch in batches:
            found = [similarity(a, b, words) >= least for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["u", "v"]).filter(pa.array(found, pa.bool_()))

    def texts_of(ids: DataFrame) -> DataFrame:
        """The texts of the documents in `ids` alone, once; Spark broadcasts the ids if they are few enough for its own threshold."""
        return stash(rows.join(stash(ids.distinct()), "doc_id", "left_semi"), codec="zstd")

    def judged(candidates: DataFrame) -> DataFrame:
        """(u, v) of those pairs (doc_id, head) that are as similar as asked."""
        pairs = stash(candidates.distinct())
        near = pairs.join(prints.hint("merge"), "doc_id").join(other.hint("merge"), "head").filter(differ <= limit)
        near = stash(near.select("doc_id", "head"))
        bodies = texts_of(near.select("doc_id").unionByName(near.select(F.col("head").alias("doc_id"))))
        both = near.join(bodies.hint("merge"), "doc_id").join(bodies.select(F.col("doc_id").alias("head"), F.col("text").alias("other")).hint("merge"), "head")
        return stash(both.select(F.col("head").alias("u"), F.col("doc_id").alias("v"), "text", "other").mapInArrow(judge, "u long, v long"))

    classes = stash(components(judged(members.filter("doc_id <> head").select("doc_id", "head"))).select(F.col("key").alias("doc_id"), F.col("component").alias("class")))

    # What the stars left apart: groups with more than one class.
    placed = stash(members.filter("n > 2").join(classes.hint("merge"), "doc_id", "left").select("key", "n", "head", "doc_id", F.coalesce("class", "doc_id").alias("class")))
    split = stash(placed.groupBy("key").agg(F.min("class").alias("_a"), F.max("class").alias("_b")).filter("_a <> _b").select("key"))
    placed = stash(placed.join(split.hint("merge"), "key"))
    few = placed.filter(f"n <= {SMALL} and doc_id <> head")
    others = few.select(F.col("key").alias("key2"), F.col("doc_id").alias("first"), F.col("class").alias("class2"))
    apart = few.join(others.hint("merge"), F.expr("key = key2 and first < doc_id and class <> class2"))
    more = judged(apart.select("doc_id", F.col("first").alias("head")))

    def block_links(table: pa.Table) -> pa.Table:
        table = table.sort_by("doc_id")
        bits = np.stack([table.column(f"b{k}").to_numpy().view(np.uint64) for k in range(wide)], axis=1)
        body = table.column("text")
        shingles = lambda i: {*shingle_hashes(body[i].as_py(), words)}
        found = _linked_in_block(table.column("doc_id").to_pylist(), table.column("class").to_pylist(), table.column("side").to_numpy(), bits, shingles, limit, least)
        return pa.table([pa.array([x[i] for x in found], pa.int64()) for i in (0, 1)], ["u", "v"])

    # Every block of a group meets itself and every later block; `side` tells the two apart.
    blocks = F.ceil(F.col("n") / BLOCK).cast("int")
    cut = placed.filter(f"n > {SMALL}").withColumn("blocks", blocks).withColumn("own", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    meets = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("met")
    cut = cut.select("key", "doc_id", "class", "own", meets).select("key", "doc_id", "class", F.least("own", "met").alias("i"), F.greatest("own", "met").alias("j"), (F.col("own") > F.col("met")).cast("int").alias("side"))
    full = cut.join(prints.hint("merge"), "doc_id").join(texts_of(cut.select("doc_id")).hint("merge"), "doc_id")
    more = more.unionByName(full.groupBy("key", "i", "j").applyInArrow(block_links, "u long, v long"))

    # The later links join classes; a document without a class is its own.
    for end in ("u", "v"):
        of = classes.select(F.col("doc_id").alias(end), F.col("class").alias(f"of_{end}"))
        more = more.join(of.hint("merge"), end, "left").withColumn(f"of_{end}", F.coalesce(f"of_{end}", end))
    joined = stash(components(stash(more.select(F.col("of_u").alias("u"), F.col("of_v").alias("v")).distinct())))
    moved = classes.join(joined.hint("merge"), F.col("class") == F.col("key"), "left").select("doc_id", F.coalesce("component", "class").alias("component_id"))
    lone = joined.join(classes.hint("merge"), F.col("key") == F.col("doc_id"), "left_anti").select(F.col("key").alias("doc_id"), F.col("component").alias("component_id"))
    return moved.unionByName(lone)
