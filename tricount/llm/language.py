"""Language identification: the family first, then one-versus-one linear support vector machines within it."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm import textkit
from tricount.llm.common import fold

# Languages (ISO 639-1) by family. A language that stands in none forms a family of its own.
FAMILIES = {
    "germanic": "en de nl af sv da no nb nn is fo fy lb yi",
    "romance": "fr es it pt ro ca gl oc la",
    "slavic": "ru uk be bg mk sr hr bs sl cs sk pl",
    "celtic": "ga gd cy br",
    "baltic": "lt lv",
    "uralic": "fi et hu",
    "turkic": "tr az kk uz tk ky tt",
    "indic": "hi bn ur pa mr gu ne si",
    "semitic": "ar he mt am",
}
FEATURES = 4096
#: Learned from at most so many documents of each language.
PER_LANGUAGE = 400

_LETTER = np.full(256, 32, dtype=np.uint8)
_LETTER[97:123] = np.arange(97, 123)
_LETTER[65:91] = np.arange(97, 123)
_LETTER[128:] = np.arange(128, 256)


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a row for each text: hashed counts of 1 to 3 neighbouring bytes of letters, square-rooted and of length one; whether it has a letter's byte)."""
    rows = len(offsets) - 1
    b = _LETTER[data].astype(np.int64)
    row = np.repeat(np.arange(rows), np.diff(offsets))
    out = np.zeros(rows * FEATURES)
    letter = np.bincount(row[b != 32], minlength=rows) > 0
    for width in (1, 2, 3):
        if len(b) < width:
            break
        gram = np.full(len(b) - width + 1, width, dtype=np.int64)
        for k in range(width):
            gram = gram * 257 + b[k : len(b) - width + 1 + k]
        inside = (row[: len(gram)] == row[width - 1 :]) & (b[: len(gram)] + b[width - 1 :] != 64)
        cell = (gram * 0x9E3779B1 >> 7) % FEATURES
        out += np.bincount((row[: len(gram)] * FEATURES + cell)[inside], minlength=rows * FEATURES)
    out = np.sqrt(out).reshape(rows, FEATURES)
    return (out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)).astype(np.float32), letter


def linear_svm(x: np.ndarray, y: np.ndarray, steps: int = 100, weight: float = 1e-4) -> np.ndarray:
    """Weights (bias last) of a linear machine for y = 1 or -1, by gradient steps on the squared hinge loss; both classes count alike."""
    x = np.hstack([x, np.ones((len(x), 1), dtype=np.float32)])
    share = np.where(y > 0, 0.5 / max((y > 0).sum(), 1), 0.5 / max((y < 0).sum(), 1))
    share, y = share.astype(np.float32), y.astype(np.float32)
    w = speed = np.zeros(x.shape[1], dtype=np.float32)
    for _ in range(steps):
        short = np.maximum(0, 1 - y * (x @ w))
        speed = np.float32(0.9) * speed - np.float32(2) * (np.float32(weight) * w - (share * y * short) @ x)
        w = w + speed
    return w


def family_of(lang: str) -> str:
    return next((f for f, langs in FAMILIES.items() if lang in langs.split()), lang)


class Hierarchy:
    """One machine for each family against the rest, and one for each two languages of a family."""

    def __init__(self, x: np.ndarray, langs: list[str]) -> None:
        self.langs = sorted(set(langs))
        self.families = sorted({family_of(v) for v in self.langs})
        of = np.array([family_of(v) for v in langs])
        lang = np.array(langs)
        self.top = np.stack([linear_svm(x, np.where(of == f, 1, -1)) for f in self.families]) if len(self.families) > 1 else None
        self.pairs = {}
        for a, b in combinations(self.langs, 2):
            if family_of(a) == family_of(b):
                take = (lang == a) | (lang == b)
                self.pairs[a, b] = linear_svm(x[take], np.where(lang[take] == a, 1, -1))

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(language, score) of each row: the family with the largest margin, then most votes, ties by summed margins."""
        x = np.hstack([x, np.ones((len(x), 1), dtype=np.float32)])
        chance = np.ones((len(x), 1))
        if self.top is not None:
            margin = np.exp(np.clip(4 * (x @ self.top.T), -30, 30))
            chance = margin / margin.sum(axis=1, keepdims=True)
        family = chance.argmax(axis=1)
        names, score = np.empty(len(x), dtype=object), chance.max(axis=1)
        for k, f in enumerate(self.families):
            rows = np.flatnonzero(family == k)
            own = [v for v in self.langs if family_of(v) == f]
            votes, worst = np.zeros((len(rows), len(own))), np.ones((len(rows), len(own)))
            for (a, b), w in self.pairs.items():
                if a in own:
                    p = 1 / (1 + np.exp(-np.clip(4 * (x[rows] @ w), -30, 30)))
                    for v, q in ((own.index(a), p), (own.index(b), 1 - p)):
                        votes[:, v] += (q >= 0.5) + 1e-3 * q
                        worst[:, v] = np.minimum(worst[:, v], q)
            best = votes.argmax(axis=1)
            names[rows] = np.array(own, dtype=object)[best]
            score[rows] *= worst[np.arange(len(rows)), best]
        return names, score


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Hierarchy | None:
    """Learns from at most `per_language` documents of each language outside the held-out fold, those with the smallest hash of their id."""
    known = docs.select("doc_id", "text", "lang").where((fold("doc_id", 4) != 2) & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    # The bound needs only ids and languages; texts are read for the chosen alone.
    shares = known.groupBy("lang").count().collect()
    total = sum(r["count"] for r in shares)
    if not total:
        return None
    rate = F.create_map(*[F.lit(v) for r in shares for v in (r.lang, min(1.0, 1.2 * per_language / r["count"]))])[F.col("lang")]
    drawn = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < rate * (1 << 30))
    rows = sorted(drawn.orderBy("lang", F.xxhash64("doc_id")).limit(2 * per_language * len(shares)).collect(), key=lambda r: (r.lang, r.doc_id, r.text))
    column = pa.array([r.text for r in rows], pa.large_string())
    x = np.concatenate([features(data, offsets)[0] for _, _, data, offsets in textkit.texts(column)])
    return Hierarchy(x, [r.lang for r in rows])


def identify(docs: DataFrame, model: Hierarchy | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document.

    A null text or one without a letter is `und` with score 0, as is every text if no label could be learned from. Rows are independent, so repeated rows get the
    same answer; a null id falls into fold 0. An empty table gives no rows; other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def predicted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = shared.value
        for batch in batches:
            column = batch.column("text")
            for a, b, data, offsets in textkit.texts(column):
                names, score = np.full(b - a, "und", dtype=object), np.zeros(b - a)
                if machine is not None:
                    x, letter = features(data, offsets)
                    ascii_letter = np.bincount(np.repeat(np.arange(b - a), np.diff(offsets))[(_LETTER[data] != 32) & (data < 128)], minlength=b - a) > 0
                    for k in np.flatnonzero(letter & ~ascii_letter):
                        letter[k] = any(c.isalpha() for c in column[a + int(k)].as_py())
                    at = np.flatnonzero(letter)
                    if len(at):
                        names[at], score[at] = machine.predict(x[at])
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(a, b - a), batch.column("held_out").slice(a, b - a), pa.array(names, pa.string()), pa.array(score)],
                    names=["doc_id", "held_out", "lang_pred", "score"],
                )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 4) == 2).alias("held_out"), "text")
    return rows.mapInArrow(predicted, "doc_id long, held_out boolean, lang_pred string, score double")
