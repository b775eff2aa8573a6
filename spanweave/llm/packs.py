"""Texts in packs, and counting of very many hashes across packs.

A pack holds some megabytes of whole texts. Hashes are not rows: each pack sends each bucket of the hash space one sorted array with every
hash once, and gets one array back. So a hash that a third of all texts share costs one entry a pack, never a row a text; arrays of a bucket are
bounded by choosing the number of buckets from the number of hashes; and the shuffle moves compressed arrays instead of single rows.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm.shared import stash, texts

#: Bytes of text in a pack; a longer text is a pack of its own.
PACK_BYTES = 1_000_000
#: Hashes that a bucket gets at most, on average.
BUCKET_HASHES = 1_000_000

_MASK = (1 << 64) - 1
_tables: dict[str, np.ndarray] = {}


def squeeze(data) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(data if isinstance(data, bytes) else np.ascontiguousarray(data).tobytes())


def expand(data: bytes, kind=None):
    out = zstandard.ZstdDecompressor().decompress(data)
    return out if kind is None else np.frombuffer(out, kind)


def frugal() -> None:
    """Give large arrays back to the system when they are freed: the C library otherwise comes to keep them, and two workers stand beside each executor's heap."""
    if "frugal" not in _tables:
        _tables["frugal"] = np.zeros(0)
        with contextlib.suppress(OSError, AttributeError):
            ctypes.CDLL(None).mallopt(-3, 1 << 18)  # M_MMAP_THRESHOLD, fixed


# ---- hashing
def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit (the finaliser of SplitMix64)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BASE = 0x9E3779B97F4A7C15 | 1


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The base's powers and those of its inverse modulo 2**64, n of each or more."""
    if "up" not in _tables or len(_tables["up"]) < n:
        size = max(n, PACK_BYTES + 250_000)
        for name, b in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            seq = np.full(size, b & _MASK, np.uint64)
            seq[0] = 1
            _tables[name] = np.multiply.accumulate(seq)
    return _tables["up"][:n], _tables["down"][:n]


class Prefixes:
    """Polynomial hashes of any stretch of a sequence of 64-bit numbers, from prefix sums."""

    def __init__(self, values: np.ndarray):
        up, self.down = powers(len(values) + 1)
        self.sums = np.zeros(len(values) + 1, np.uint64)
        np.cumsum(values * up[:-1], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of [start, end); stretches of equal content and length have equal hashes wherever they stand."""
        return mix((self.sums[end] - self.sums[start]) * self.down[start])

    def of_all(self, length: int) -> np.ndarray:
        """Hash of every stretch of `length`."""
        n = len(self.sums) - length
        return mix((self.sums[length:] - self.sums[:n]) * self.down[:n])


_BYTES = [mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(m)) for m in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def byte_values(data: np.ndarray, lane: int = 0) -> np.ndarray:
    """A fixed random 64-bit number for every byte; two lanes are independent of each other."""
    return _BYTES[lane][data]


# ---- packs
_PACK = "pack long, ids binary, sizes binary, body binary, bytes long, extra binary"


def packed(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", extra: Callable[[Pack], bytes] = lambda _: b"") -> DataFrame:
    """Packs of whole texts, written once to the shared folder: ids, sizes in bytes (NumPy int64) and the compressed bytes.
    A null id is kept as the largest number, and its size as -1 - size, so that it is told from a real one.
    `extra` is what an operator wants to remember of each pack."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        serial, ids, parts, size = TaskContext.get().partitionId() << 32, [], [], 0

        def out():
            sizes = np.array([-1 - len(p) if i is None else len(p) for i, p in zip(ids, parts, strict=True)], np.int64)
            names = np.array([(1 << 63) - 1 if i is None else i for i in ids], np.int64)
            body = squeeze(b"".join(parts))
            row = [serial], [names.tobytes()], [sizes.tobytes()], [body], [size], [extra(Pack(names.tobytes(), sizes.tobytes(), body))]
            kinds = (pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(row, kinds, strict=True)], ["pack", "ids", "sizes", "body", "bytes", "extra"])

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                for key, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    raw = text.encode()
                    if size and size + len(raw) > PACK_BYTES:
                        yield out()
                        serial, ids, parts, size = serial + 1, [], [], 0
                    ids.append(key)
                    parts.append(raw)
                    size += len(raw)
        if ids:
            yield out()

    return stash(texts(docs, doc_id, text).mapInArrow(work, _PACK))


class Pack:
    """One pack in memory: its texts' bytes one after the other."""

    def __init__(self, ids: bytes, sizes: bytes, body: bytes, extra: bytes = b""):
        frugal()
        self.extra = extra
        self.ids, stored = np.frombuffer(ids, np.int64), np.frombuffer(sizes, np.int64)
        self.unnamed = stored < 0
        self.sizes = np.where(self.unnamed, -1 - stored, stored)
        self.raw = expand(body)
        self.data = np.frombuffer(self.raw, np.uint8)
        self.ends = np.cumsum(self.sizes)
        self.starts = self.ends - self.sizes

    def names(self) -> list[int | None]:
        return [None if lost else i for i, lost in zip(self.ids.tolist(), self.unnamed.tolist(), strict=True)]


def bucket_bits(hashes: int) -> int:
    """Buckets as a power of two, so that each gets BUCKET_HASHES hashes at most."""
    return max(6, int(np.ceil(np.log2(max(1, hashes) / BUCKET_HASHES))))


def by_bucket(hashes: np.ndarray, bits: int) -> list[tuple[int, int, int]]:
    """(bucket, from, to) of sorted hashes; a bucket is what the first `bits` bits name."""
    which = (hashes >> np.uint64(64 - bits)).astype(np.int64)
    at = np.flatnonzero(np.diff(which, prepend=-1, append=1 << 62))
    return [(int(which[a]), int(a), int(b)) for a, b in zip(at[:-1], at[1:], strict=True)]


#: Questions go to a bucket, answers back to a pack; `kind` tells rounds apart.
ARRAYS = "kind int, bucket long, pack long, body binary"


def _arrays(rows: Iterable[tuple[int, int, int, bytes]]) -> pa.Table:
    rows = list(rows)
    kinds = (pa.int32(), pa.int64(), pa.int64(), pa.binary())
    return pa.table([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["kind", "bucket", "pack", "body"])


def ask(packs: DataFrame, question: Callable[[int, Pack], Iterable[tuple[int, bytes]]], kind: int, load: type = Pack) -> DataFrame:
    """Questions (bucket, body) of every pack, which `load` makes from its row."""

    def work(batches):
        for batch in batches:
            for row in batch.to_pylist():
                pack = row["pack"]
                found = [(kind, b, pack, body) for b, body in question(pack, load(row["ids"], row["sizes"], row["body"], row["extra"]))]
                yield from _arrays(found).to_batches()

    return packs.mapInArrow(work, ARRAYS)


def answered(questions: DataFrame, answer: Callable[[list[bytes]], list[bytes]]) -> DataFrame:
    """One body back for each body that a bucket got, in its order. A bucket's bodies meet in one task: BUCKET_HASHES entries on average."""

    def work(table: pa.Table) -> pa.Table:
        kinds, buckets, packs = (table.column(c).to_pylist() for c in ("kind", "bucket", "pack"))
        bodies = answer(table.column("body").to_pylist())
        return _arrays(zip(kinds, buckets, packs, bodies, strict=True))

    return questions.groupBy("bucket").applyInArrow(work, ARRAYS)


def told(packs: DataFrame, answers: DataFrame, then: Callable[[int, Pack, dict[tuple[int, int], bytes]], pa.Table], schema: str, load: type = Pack) -> DataFrame:
    """`then(pack, Pack, {(kind, bucket): answer})` for every pack with its answers."""

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        found = {(k, b): body for k, b, body in zip(right.column("kind").to_pylist(), right.column("bucket").to_pylist(), right.column("body").to_pylist(), strict=True)}
        row = left.slice(0, 1).to_pylist()[0]
        return then(row["pack"], load(row["ids"], row["sizes"], row["body"], row["extra"]), found)

    return packs.groupBy("pack").cogroup(answers.groupBy("pack")).applyInArrow(work, schema)


def total_bytes(packs: DataFrame) -> int:
    return packs.agg(F.coalesce(F.sum("bytes"), F.lit(0))).first()[0]
