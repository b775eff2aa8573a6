"""Quality classifier: gated attention over a document's passages (multiple-instance learning).

Every passage of a text is encoded; a gated attention network, learnt from document labels alone, weighs the passages; the weighted
sum of their encodings is scored by a logistic unit. Training is NumPy on the driver over a bounded sample of labelled rows; scoring is one pass
over all whole texts, without a shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm.shared import stash, texts

#: Bytes of a passage.
PASSAGE = 512
#: Byte classes: control and blanks, lower case, upper case, digits, sentence marks, other ASCII marks, UTF-8 bytes.
CLASSES = 7
FEATURES = CLASSES * CLASSES + 9


def _byte_classes() -> np.ndarray:
    kind = np.full(256, 5, np.int64)
    kind[:33], kind[127], kind[128:] = 0, 0, 6
    kind[97:123], kind[65:91], kind[48:58] = 1, 2, 3
    kind[[ord(c) for c in ".,;:!?'\"-()"]] = 4
    return kind


_KIND = _byte_classes()


def passages(text: str) -> np.ndarray:
    """Features of every passage of a whole text, one row each; an empty text has one passage of zeros."""
    data = text.encode()
    if not data:
        return np.zeros((1, FEATURES), np.float32)
    n = (len(data) + PASSAGE - 1) // PASSAGE
    kind = _KIND[np.frombuffer(data, np.uint8)]
    at = np.arange(len(data)) // PASSAGE
    pair = np.bincount((at * CLASSES + kind)[:-1] * CLASSES + kind[1:], minlength=n * CLASSES**2).reshape(n, -1)
    size = np.bincount(at, minlength=n)[:, None]
    out = np.empty((n, FEATURES), np.float32)
    out[:, : CLASSES**2] = np.sqrt(pair / size)
    for i in range(n):
        part = data[i * PASSAGE : (i + 1) * PASSAGE]
        words = part.split()
        count = max(1, len(words))
        lone = len({*words})
        lines = part.split(b"\n")
        long = max(map(len, words), default=0)
        out[i, CLASSES**2 :] = (
            lone / count,
            sum(map(bytes.__eq__, words, words[1:])) / count,
            sum(map(bytes.__eq__, words, words[2:])) / count,
            len({*zip(words, words[1:], strict=False)}) / count,
            len({*lines}) / len(lines),
            min(long, 100) / 20,
            len(part) / count / 10,
            len({*part}) / 64,
            np.log1p(n) / 5,
        )
    return out


@dataclass
class Attention:
    """mean, scale of the features; encoder E, e; gates V, U and attention w; classifier c, b."""

    mean: np.ndarray
    scale: np.ndarray
    parts: dict[str, np.ndarray]

    @staticmethod
    def fit(bags: list[np.ndarray], labels: np.ndarray, hidden: int = 24, gates: int = 12, epochs: int = 40, batch: int = 128, rate: float = 0.01, decay: float = 1e-4, seed: int = 7) -> Attention:
        """Adam on the log loss. Without both labels the score is the constant share of label 1."""
        every = np.concatenate(bags) if bags else np.zeros((1, FEATURES), np.float32)
        mean, scale = every.mean(axis=0), every.std(axis=0) + 1e-3
        rng = np.random.default_rng(seed)
        draw = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        p = {"E": draw(FEATURES, hidden), "e": np.zeros(hidden, np.float32), "V": draw(hidden, gates), "U": draw(hidden, gates), "w": draw(gates, 1)[:, 0], "c": np.zeros(hidden, np.float32), "b": np.zeros(1, np.float32)}
        share = (float(labels.sum()) + 1) / (len(labels) + 2)
        p["b"][0] = np.log(share / (1 - share))
        model = Attention(mean, scale, p)
        if len({*labels.tolist()}) < 2:
            return model
        bags = [((x - mean) / scale).astype(np.float32) for x in bags]
        first, second, step = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}, 0
        for epoch in range(epochs):
            order = rng.permutation(len(bags))
            for at in range(0, len(order), batch):
                pick = order[at : at + batch]
                grad = model._gradient([bags[i] for i in pick], labels[pick])
                step += 1
                for k, g in grad.items():
                    g = g + decay * p[k]
                    first[k] += 0.1 * (g - first[k])
                    second[k] += 0.001 * (g * g - second[k])
                    p[k] -= rate * (0.5 ** (epoch / (epochs / 4))) * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        return model

    def _forward(self, x: np.ndarray, starts: np.ndarray, lengths: np.ndarray):
        p = self.parts
        h = np.tanh(x @ p["E"] + p["e"])
        t, s = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-(h @ p["U"])))
        a = (t * s) @ p["w"]
        a = np.exp(a - np.repeat(np.maximum.reduceat(a, starts), lengths))
        a /= np.repeat(np.add.reduceat(a, starts), lengths)
        z = np.add.reduceat(a[:, None] * h, starts, axis=0)
        return h, t, s, a, z, 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["b"][0], -30, 30)))

    def _gradient(self, bags: list[np.ndarray], labels: np.ndarray) -> dict[str, np.ndarray]:
        p, x = self.parts, np.concatenate(bags)
        lengths = np.array([len(b) for b in bags])
        starts = np.cumsum(lengths) - lengths
        h, t, s, a, z, y = self._forward(x, starts, lengths)
        dy = ((y - labels) / len(bags)).astype(np.float32)
        dz = np.repeat(dy[:, None] * p["c"], lengths, axis=0)
        da = (dz * h).sum(axis=1)
        da = a * (da - np.repeat(np.add.reduceat(a * da, starts), lengths))
        dg = da[:, None] * p["w"]
        dt, ds = dg * s * (1 - t * t), dg * t * s * (1 - s)
        dh = (a[:, None] * dz + dt @ p["V"].T + ds @ p["U"].T) * (1 - h * h)
        return {"E": x.T @ dh, "e": dh.sum(axis=0), "V": h.T @ dt, "U": h.T @ ds, "w": ((t * s) * da[:, None]).sum(axis=0), "c": (dy[:, None] * z).sum(axis=0), "b": np.array([dy.sum()], np.float32)}

    def score(self, bags: list[np.ndarray]) -> np.ndarray:
        lengths = np.array([len(b) for b in bags])
        x = ((np.concatenate(bags) - self.mean) / self.scale).astype(np.float32)
        return self._forward(x, np.cumsum(lengths) - lengths, lengths)[-1].astype(np.float64)


def held_out(doc_id):
    """Rows whose labels are never learnt from."""
    return F.crc32(doc_id.cast("string")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, sample: int = 4000, most_passages: int = 200_000, **options) -> Attention:
    """Fit on at most `sample` labelled rows that are not held out (those with the least hashed ids, all if there are fewer), with every passage of each.
    Rows are taken until they have `most_passages` passages, so very long texts make fewer rows, never thinner ones. Null labels and labels of unknown documents are passed over; of several labels of one
    document the highest counts."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).filter("label is not null and doc_id is not null")
    known = known.filter(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("label").alias("label"))
    some = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)

    def work(batches):
        for batch in batches:
            rows = [passages(text).ravel() for text in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, pa.list_(pa.float32()))], ["doc_id", "label", "features"])

    rows = stash(texts(docs).join(F.broadcast(some), "doc_id").select("doc_id", "label", "text").mapInArrow(work, "doc_id long, label int, features array<float>"))
    sizes = rows.groupBy("doc_id").agg((F.sum(F.size("features")) / FEATURES).alias("n")).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    before = np.cumsum([0, *(r["n"] for r in sizes)])[:-1]
    taken = [r["doc_id"] for r, n in zip(sizes, before, strict=True) if n < most_passages]
    if len(taken) < len(sizes):
        rows = rows.filter(F.col("doc_id").isin(taken))
    got = rows.toArrow().sort_by("doc_id")
    bags = [np.asarray(x.values, np.float32).reshape(-1, FEATURES) for x in got.column("features")]
    return Attention.fit(bags, np.array(got.column("label").to_pylist(), np.float32), **options)


def quality_scores(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, sample: int = 4000, most_passages: int = 200_000) -> DataFrame:
    """One row per row of `docs`: doc_id, held_out, score (0 to 1, higher: label 1 likelier), predicted (1 from `threshold` on).

    Null and empty texts are scored as one empty passage. A null doc_id is not held out. An empty table gives no rows, an empty label table the
    constant score one half; repeated rows are scored alike; other columns are ignored."""
    model = train(docs, labels, sample, most_passages)

    def work(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                score = model.score([passages(t) for t in part.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(score)], ["doc_id", "score"])

    scored = texts(docs).mapInArrow(work, "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, sample: int = 4000, most_passages: int = 200_000) -> DataFrame:
    """The rows of `docs` that score `threshold` or more, all columns as they are, in one pass without a shuffle.

    Null texts are empty and scored as one empty passage; null ids and repeated rows are judged by their texts like any other; an empty table gives no rows, and
    columns of any name stand."""
    model, at = train(docs, labels, sample, most_passages), docs.columns.index("text")

    def work(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                keep = model.score([passages(t or "") for t in part.column(at).to_pylist()]) >= threshold
                yield part.filter(pa.array(keep))

    return docs.mapInArrow(work, docs.schema)
