"""Substring dedup over words: Rabin-Karp hashes of every window of a fixed number of words, counted in Spark.

Every window of every text is hashed from prefix sums. A first round sends shortened hashes, once a pack, and learns which of them occur in more packs
than one: two packs must agree for a window to matter, so most windows end there at some three bytes each. A second round sends the full hashes of the
rest with the least document that has them, and learns the least document of all. Windows that start in a lesser document are removed; windows next to each other
merge into maximal intervals. Two windows count as equal if two independent 64-bit hashes of all their words agree (at 10**13 windows a false pair is to be
expected once in some 10**12 runs); their words are not moved to be compared.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from spanweave.llm import packs as pk
from spanweave.llm.shared import stash

_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True


#: Longer words are hashed by a cryptographic digest: polynomials modulo 2**64 agree on some different words of 1024 bytes and more.
PLAIN = 64


class Windows:
    """All windows of `width` words of a pack: hash, first word, document (index in the pack); with `check` a second hash that is
    independent of the first from the bytes on."""

    def __init__(self, pack: pk.Pack, width: int, check: bool = False):
        space = _SPACE[pack.data]
        word = ~space
        edge = np.zeros(len(word) + 1, bool)
        edge[pack.starts[pack.starts < len(word)]] = True  # a word ends where its text ends
        before = np.concatenate([[False], word[:-1]]) if len(word) else word
        self.start = np.flatnonzero(word & (~before | edge[:-1]))
        after = np.concatenate([word[1:], [False]]) if len(word) else word
        self.end = np.flatnonzero(word & (~after | edge[1:])) + 1
        del space, word, edge, before, after
        self.doc = np.searchsorted(pack.ends, self.start, side="right")
        n = len(self.start) - width + 1
        self.first = np.flatnonzero(self.doc[:n] == self.doc[width - 1 :]) if n > 0 else np.zeros(0, np.int64)
        self.hash = self._windows(pack, width, 0)
        self.check = self._windows(pack, width, 1) if check else None

    def _windows(self, pack: pk.Pack, width: int, lane: int) -> np.ndarray:
        if not len(self.first):
            return np.zeros(0, np.uint64)
        values = pk.Prefixes(pk.byte_values(pack.data, lane)).of(self.start, self.end)
        for i in np.flatnonzero(self.end - self.start > PLAIN).tolist():
            digest = hashlib.blake2b(pack.raw[self.start[i] : self.end[i]], digest_size=16).digest()
            values[i] = int.from_bytes(digest[8 * lane : 8 * lane + 8], "little")
        return pk.Prefixes(pk.mix(values ^ np.uint64(lane))).of_all(width)[self.first]


def _short(hashes: np.ndarray, bits: int) -> np.ndarray:
    return np.unique(hashes >> np.uint64(32 - bits))


def _deltas(values: np.ndarray) -> np.ndarray:
    return np.diff(values, prepend=values.dtype.type(0))


def removals(docs: DataFrame, width: int = 13, doc_id: str = "doc_id", text: str = "text", spans: bool = False) -> DataFrame:
    """One row per row of `docs`: doc_id, n_words, n_removed, kept_sha256 (of the kept words, one blank between); with
    `spans` also kept_text and removed, the maximal intervals of removed words as (from, to).

    Windows never cross texts. Null and empty texts, and texts shorter than a window, lose nothing. A null doc_id counts as the largest.
    Rows that share an id are one document: neither takes words from the other. Other columns are ignored."""
    packs = pk.packed(docs, doc_id, text)
    bits = pk.bucket_bits(pk.total_bytes(packs) // 5)

    def first_question(_, pack):
        short = _short(Windows(pack, width).hash, bits)
        for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bits), bits):
            yield b, pk.squeeze(_deltas(short[lo:hi].astype(np.uint32)))

    def first_answer(bodies):
        parts = [np.cumsum(pk.expand(b, np.uint32), dtype=np.uint32) for b in bodies]
        value, count = np.unique(np.concatenate(parts), return_counts=True)
        shared = value[count > 1]
        return [np.packbits(_among(shared, p)).tobytes() for p in parts]

    known = stash(pk.answered(pk.ask(packs, first_question, 1), first_answer))

    def candidates(found, hashes) -> np.ndarray:
        """Which hashes other packs may have."""
        short = _short(hashes, bits)
        flags = np.zeros(len(short), bool)
        for b, lo, hi in pk.by_bucket(short << np.uint64(32 - bits), bits):
            flags[lo:hi] = np.unpackbits(np.frombuffer(found[1, b], np.uint8), count=hi - lo).astype(bool)
        return _among(short[flags], hashes >> np.uint64(32 - bits))

    def entries(pack, windows) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct windows by (hash, check): the two, the least id of each, and every window's place among them."""
        ids = pack.ids[windows.doc[windows.first]]
        order = np.lexsort((windows.check, windows.hash))
        hashes, checks = windows.hash[order], windows.check[order]
        new = _fresh(hashes) | _fresh(checks)
        place = np.empty(len(order), np.int64)
        place[order] = np.cumsum(new) - 1
        at = np.flatnonzero(new)
        return hashes[at], checks[at], np.minimum.reduceat(ids[order], at) if len(at) else ids, place

    def second_question(name, pack, found):
        hashes, checks, ids, _ = entries(pack, Windows(pack, width, check=True))
        some = candidates(found, hashes)
        hashes, checks, ids = hashes[some], checks[some], ids[some]
        return pk._arrays((2, b, name, pk.squeeze(_deltas(hashes[lo:hi]).tobytes() + _deltas(ids[lo:hi]).tobytes() + checks[lo:hi].tobytes())) for b, lo, hi in pk.by_bucket(hashes, bits))

    def second_answer(bodies):
        parts = []
        for body in bodies:
            three = pk.expand(body, np.uint64).reshape(3, -1)
            parts.append((np.cumsum(three[0], dtype=np.uint64), np.cumsum(three[1].view(np.int64)), three[2]))
        hashes, ids, checks = (np.concatenate([p[i] for p in parts]) for i in range(3))
        order = np.lexsort((checks, hashes))
        new = _fresh(hashes[order]) | _fresh(checks[order])
        least = np.empty(len(order), np.int64)
        least[order] = np.minimum.reduceat(ids[order], np.flatnonzero(new))[np.cumsum(new) - 1]
        cuts = np.cumsum([len(p[0]) for p in parts])[:-1]
        return [pk.squeeze(x) for x in np.split(least - ids, cuts)]

    asked = pk.told(packs, known, second_question, pk.ARRAYS)
    answers = known.unionByName(pk.answered(asked, second_answer))

    def third(_, pack, found):
        windows = Windows(pack, width, check=True)
        # Every window of the pack with the least id here, then the least id of all where other packs have it.
        hashes, _, least, place = entries(pack, windows)
        some = np.flatnonzero(candidates(found, hashes))
        for b, lo, hi in pk.by_bucket(hashes[some], bits):
            least[some[lo:hi]] += pk.expand(found[2, b], np.int64)
        gone = windows.first[least[place] < pack.ids[windows.doc[windows.first]]]
        cover = np.zeros(len(windows.start) + 1, np.int64)
        np.add.at(cover, gone, 1)
        np.add.at(cover, gone + width, -1)
        cover = np.cumsum(cover[:-1]) > 0
        return _report(pack, windows, cover, spans)

    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + (", kept_text string, removed array<struct<start:long,end:long>>" if spans else "")
    return pk.told(packs, answers, third, schema)


def _fresh(ordered: np.ndarray) -> np.ndarray:
    """Where a value differs from the one before it."""
    new = np.ones(len(ordered), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    return new


def _among(ordered: np.ndarray, values: np.ndarray) -> np.ndarray:
    if not len(ordered):
        return np.zeros(len(values), bool)
    at = np.searchsorted(ordered, values)
    return ordered[np.minimum(at, len(ordered) - 1)] == values


def _report(pack: pk.Pack, windows: Windows, gone: np.ndarray, spans: bool) -> pa.Table:
    bounds = np.searchsorted(windows.start, [*pack.starts, len(pack.raw)]) if len(pack.starts) else np.zeros(1, np.int64)
    rows = []
    names_of = pack.names()
    for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
        words, lost = pack.raw[pack.starts[i] : pack.ends[i]].split(), gone[a:b]
        n = int(lost.sum())
        kept = b" ".join(words if not n else [w for w, x in zip(words, lost.tolist(), strict=True) if not x])
        row = [names_of[i], len(words), n, hashlib.sha256(kept).hexdigest()]
        if spans:
            at = np.flatnonzero(np.diff(np.concatenate([[False], lost, [False]]).astype(np.int8)))
            row += [kept.decode(), [{"start": int(s), "end": int(e)} for s, e in at.reshape(-1, 2)]]
        rows.append(row)
    names, kinds = ["doc_id", "n_words", "n_removed", "kept_sha256"], [pa.int64(), pa.int64(), pa.int64(), pa.string()]
    if spans:
        names, kinds = [*names, "kept_text", "removed"], [*kinds, pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))]
    return pa.table([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)
