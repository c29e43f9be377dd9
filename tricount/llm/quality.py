"""Document quality by attention over passages (multiple-instance learning with gated attention)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm import textkit
from tricount.llm.common import fold, labelled_sample
from tricount.llm.nets import Adam, sigmoid

#: Words of a passage.
PASSAGE = 48
#: Labelled documents learned from, at most.
SAMPLE = 4000
#: Documents with at least this score are predicted to be good.
THRESHOLD = 0.3
_ENCODED, _GATE = 16, 8

_CLASSES = np.zeros((10, 256), dtype=bool)
_CLASSES[0, 97:123] = True
_CLASSES[1, 65:91] = True
_CLASSES[2, 48:58] = True
_CLASSES[3, 128:] = True
_CLASSES[4, [ord(c) for c in ".,"]] = True
_CLASSES[5, [ord(c) for c in "!?;:'\"()-"]] = True
_CLASSES[6, [ord(c) for c in "|/\\<>[]{}=_~^`"]] = True
_CLASSES[7, [ord(c) for c in "#$%&*@+"]] = True
_CLASSES[8, [10, 13]] = True
_CLASSES[9, [32, 9, 11, 12]] = True
FEATURES = len(_CLASSES) + 9


def passages(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(features, row) of every passage of PASSAGE words of each text; a text without words is one passage."""
    words = textkit.Words(data, offsets)
    rows = len(offsets) - 1
    count = np.maximum(1, -(-words.count // PASSAGE))
    first = np.cumsum(count) - count
    row = np.repeat(np.arange(rows), count)
    number = np.arange(len(row)) - first[row]
    word_from = np.minimum(words.first[row] + number * PASSAGE, words.first[row + 1])
    word_to = np.minimum(word_from + PASSAGE, words.first[row + 1])
    n_words = word_to - word_from
    at = np.append(words.start, len(data))
    begin = np.where(number == 0, offsets[row], at[np.minimum(word_from, len(words.start))])
    last = number == count[row] - 1
    end = np.where(last, offsets[row + 1], at[np.minimum(word_to, len(words.start))])
    size = np.maximum(end - begin, 1)
    out = np.zeros((len(row), FEATURES), dtype=np.float32)
    for k, members in enumerate(_CLASSES):
        total = np.concatenate([[0], np.cumsum(members[data], dtype=np.int64)])
        out[:, k] = (total[end] - total[begin]) / size
    k = len(_CLASSES)
    out[:, k] = np.log1p(n_words) / 5
    length = np.concatenate([[0], np.cumsum(words.end - words.start)])
    out[:, k + 1] = (length[word_to] - length[word_from]) / np.maximum(n_words, 1) / 10
    h = words.hashes()
    of = np.repeat(np.arange(len(row)), n_words)
    order = np.lexsort((h, of))
    again = np.zeros(len(h))
    again[order[1:]] = (h[order[1:]] == h[order[:-1]]) & (of[order[1:]] == of[order[:-1]])
    next_same = np.zeros(len(h))
    next_same[1:] = (h[1:] == h[:-1]) & (of[1:] == of[:-1])
    size_of = words.end - words.start
    lead = words.data[words.start] if len(words.start) else words.data
    tail = words.data[words.end - 1] if len(words.start) else words.data
    per_word = (again, next_same, size_of <= 3, size_of >= 14, size_of == 1, lead < 48, (tail >= 33) & (tail < 48) & (tail != 44) & (tail != 46))
    for j, x in enumerate(per_word):
        total = np.concatenate([[0.0], np.cumsum(x, dtype=np.float64)])
        out[:, k + 2 + j] = (total[word_to] - total[word_from]) / np.maximum(n_words, 1)
    return out, row


class AttentionScorer:
    """Encodes passages, weighs those of a document by gated attention, scores their weighted mean."""

    def __init__(self, seed: int = 7) -> None:
        rng = np.random.default_rng(seed)
        draw = lambda a, b: (rng.standard_normal((a, b)) / np.sqrt(a)).astype(np.float32)
        self.p = {"w1": draw(FEATURES, _ENCODED), "b1": np.zeros(_ENCODED, np.float32), "v": draw(_ENCODED, _GATE), "u": draw(_ENCODED, _GATE), "a": draw(_GATE, 1)[:, 0], "w2": draw(_ENCODED, 1)[:, 0], "b2": np.zeros(1, np.float32)}
        self.mean, self.scale = np.zeros(FEATURES, np.float32), np.ones(FEATURES, np.float32)

    def forward(self, x: np.ndarray, row: np.ndarray, rows: int) -> tuple:
        """Logits of the documents, and what backward() needs. Every document has a passage, and `row` is in order."""
        p = self.p
        h = np.tanh(x @ p["w1"] + p["b1"])
        t, s = np.tanh(h @ p["v"]), sigmoid(h @ p["u"])
        e = (t * s) @ p["a"]
        starts = np.searchsorted(row, np.arange(rows))
        e = np.exp(e - np.maximum.reduceat(e, starts)[row])
        a = e / np.add.reduceat(e, starts)[row]
        z = np.add.reduceat(h * a[:, None], starts, axis=0)
        return z @ p["w2"] + p["b2"][0], (x, row, starts, h, t, s, a, z)

    def backward(self, d: np.ndarray, kept: tuple) -> dict[str, np.ndarray]:
        p = self.p
        x, row, starts, h, t, s, a, z = kept
        dz = d[:, None] * p["w2"]
        da = (h * dz[row]).sum(axis=1)
        de = a * (da - np.add.reduceat(a * da, starts)[row])
        dts = de[:, None] * p["a"]
        dt, ds = dts * s * (1 - t * t), dts * t * s * (1 - s)
        dh = a[:, None] * dz[row] + dt @ p["v"].T + ds @ p["u"].T
        d1 = dh * (1 - h * h)
        return {"w1": x.T @ d1, "b1": d1.sum(axis=0), "v": h.T @ dt, "u": h.T @ ds, "a": (t * s).T @ de, "w2": z.T @ d, "b2": np.array([d.sum()])}

    def fit(self, x: np.ndarray, row: np.ndarray, y: np.ndarray, epochs: int = 60, batch: int = 64) -> AttentionScorer:
        self.mean, self.scale = x.mean(axis=0), x.std(axis=0) + 1e-3
        x = (x - self.mean) / self.scale
        starts = np.searchsorted(row, np.arange(len(y) + 1))
        rng, adam = np.random.default_rng(11), Adam(self.p, 0.01)
        for epoch in range(epochs):
            adam.rate = 0.01 if epoch < epochs * 2 // 3 else 0.002
            order = rng.permutation(len(y))
            for at in range(0, len(y), batch):
                docs = order[at : at + batch]
                size = starts[docs + 1] - starts[docs]
                take = np.concatenate([np.arange(starts[k], starts[k + 1]) for k in docs])
                logit, kept = self.forward(x[take], np.repeat(np.arange(len(docs)), size), len(docs))
                grads = self.backward((sigmoid(logit) - y[docs]) / len(docs), kept)
                adam.step({k: g + 1e-4 * self.p[k] for k, g in grads.items()})
        return self

    def score(self, x: np.ndarray, row: np.ndarray, rows: int) -> np.ndarray:
        return sigmoid(self.forward((x - self.mean) / self.scale, row, rows)[0])


def train(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> AttentionScorer | None:
    """Learns from at most `bound` labelled documents outside the held-out fold; None without both labels."""
    rows = labelled_sample(docs, labels, "quality", fold("doc_id", 5) != 0, bound)
    y = np.array([r[1] for r in rows], dtype=np.float32)
    if not len(y) or y.min() == y.max():
        return None
    parts = [passages(data, offsets) for _, _, data, offsets in textkit.texts(pa.array([r[0] for r in rows], pa.large_string()))]
    spans = [(a, b) for a, b, _, _ in textkit.texts(pa.array([r[0] for r in rows], pa.large_string()))]
    return AttentionScorer().fit(np.concatenate([x for x, _ in parts]), np.concatenate([r + a for (_, r), (a, _) in zip(parts, spans, strict=True)]), y)


def _scored(model: AttentionScorer | None, column: pa.Array) -> np.ndarray:
    """Scores of the texts of a batch; 0.5 without a model."""
    out = np.full(len(column), 0.5)
    for a, b, data, offsets in textkit.texts(column):
        if model is not None:
            out[a:b] = model.score(*passages(data, offsets), b - a)
    return out


def score_quality(docs: DataFrame, model: AttentionScorer | None) -> DataFrame:
    """doc_id, held_out, score, predicted for every document, from its whole text alone.

    A null text is scored as an empty one, which is one passage without words. Without a model every score is 0.5. Equal texts get equal scores, so repeated rows agree;
    a null id falls into fold 0 and is held out. An empty table gives no rows. Other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = _scored(shared.value, batch.column("text"))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))],
                names=["doc_id", "held_out", "score", "predicted"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 5) == 0).alias("held_out"), "text")
    return rows.mapInArrow(scored, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, model: AttentionScorer | None) -> DataFrame:
    """The documents predicted to be good, with all their columns, in one pass over the table.

    Null and empty texts are scored as texts without words. Rows are judged one by one, so repeated rows share their fate and a null id is no reason to go. An empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(_scored(shared.value, batch.column("text")) >= THRESHOLD))

    return docs.mapInArrow(kept, docs.schema)
