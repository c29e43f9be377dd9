"""Toxicity by a bidirectional gated recurrent network over words, with attention pooling, on all overlapping windows of a text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm import textkit
from tricount.llm.common import fold, labelled_sample
from tricount.llm.nets import Adam, gru, gru_grad, gru_params, platt, sigmoid

#: Words of a window, and from one window to the next.
WINDOW, STRIDE = 24, 12
#: Labelled documents learned from, at most.
SAMPLE = 4000
#: Documents with at least this score are predicted to be toxic.
THRESHOLD = 0.3
#: Bytes of a word that its character network reads in each direction: the first so many and the last so many.
SPELLED = 12
#: Word vectors that a task remembers before it starts over.
CACHE_WORDS = 400_000
_BUCKETS, _WORD, _CHAR, _CHAR_STATE, _STATE, _ATTEND = 4096, 6, 6, 6, 8, 8
#: Evidence is kept for whole words and for their first bytes, so many of them.
_BEGINNINGS = (5, 7)
_EVIDENCE = 1 + len(_BEGINNINGS)
_INPUT = _EVIDENCE + _WORD + 2 * _CHAR_STATE
_LETTERS = textkit._LOWER


def _trimmed(words: textkit.Words) -> None:
    """Moves the ends of words inwards over ASCII signs, so that a word is the same before a comma; words of signs alone stay."""
    sign = np.ones(256, dtype=bool)
    sign[[*range(48, 58), *range(97, 123), *range(128, 256)]] = False
    if not len(words.start):
        return
    spot = np.flatnonzero(~sign[words.data])
    if not len(spot):
        return
    lo = np.searchsorted(spot, words.start)
    hi = np.searchsorted(spot, words.end) - 1
    has = hi >= lo
    words.start = np.where(has, spot[np.minimum(lo, len(spot) - 1)], words.start)
    words.end = np.where(has, spot[hi] + 1, words.end)


def _cut(words: textkit.Words) -> None:
    """Puts pieces in place of words too long to be spelled whole: cut at ASCII signs and no-break spaces, then into overlapping pieces, each begun SPELLED bytes
    after the one before and twice as long, so that every byte is among the first or last bytes of a piece. Words of signs alone are only cut by length."""
    whole = 2 * SPELLED
    long = words.end - words.start > whole
    if not long.any():
        return
    data, start, end = words.data, words.start[long], words.end[long]
    part = (data >= 128) | ((data >= 97) & (data <= 122)) | ((data >= 48) & (data <= 57))
    hard = np.flatnonzero((data[:-1] == 0xC2) & (data[1:] == 0xA0))
    part[hard] = part[hard + 1] = False
    total = np.concatenate([[0], np.cumsum(part)])
    inside = lambda a, b: np.cumsum(np.bincount(a, minlength=len(data) + 1) - np.bincount(b, minlength=len(data) + 1))[:-1] > 0
    bare = total[end] == total[start]
    part = (part | inside(start[bare], end[bare])) & inside(start, end)
    turn = np.zeros(len(data) + 1, dtype=bool)
    turn[start] = turn[end] = True
    before, after = np.concatenate([[False], part[:-1]]), np.concatenate([part[1:], [False]])
    a, b = np.flatnonzero(part & (~before | turn[:-1])), np.flatnonzero(part & (~after | turn[1:])) + 1
    n = 1 + np.maximum(0, -(-(b - a - whole) // SPELLED))
    of = np.repeat(np.arange(len(a)), n)
    step = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
    begin = np.where(step == n[of] - 1, np.maximum(b[of] - whole, a[of]), a[of] + step * SPELLED)
    row = words.row[np.searchsorted(words.start, begin, side="right") - 1]
    words.start, words.end, words.row = (np.concatenate(x) for x in ((words.start[~long], begin), (words.end[~long], np.minimum(begin + whole, b[of])), (words.row[~long], row)))
    order = np.argsort(words.start, kind="stable")
    words.start, words.end, words.row = words.start[order], words.end[order], words.row[order]
    words.first = np.searchsorted(words.row, np.arange(len(words.first)))
    words.count = np.diff(words.first)


class Texts:
    """Distinct words of a chunk of texts, pieces standing for long ones, the place of each word among them, and the windows of each text.

    A text's windows start every STRIDE words until one reaches its end; a text without words has none.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray) -> None:
        words = textkit.Words(data, offsets)
        _trimmed(words)
        _cut(words)
        self.hash, first, self.word = np.unique(words.hashes(), return_index=True, return_inverse=True)
        start, size = words.start[first], (words.end - words.start)[first]
        step = np.arange(SPELLED)
        n = np.minimum(size, SPELLED)[:, None]
        ahead, back = start[:, None] + np.minimum(step, n - 1), (start + size)[:, None] - 1 - np.minimum(step, n - 1)
        self.spelled = np.stack([words.data[ahead], words.data[back]]) if len(first) else np.zeros((2, 0, SPELLED), np.uint8)
        self.mask = (step[None, :] < n).astype(np.float32)
        self.keys = [self.hash]
        for n in _BEGINNINGS:
            begins = np.where(self.mask[:, :n] > 0, self.spelled[0][:, :n], 0).astype(np.uint64)
            self.keys.append(textkit.mix((begins << (np.arange(n, dtype=np.uint64) * np.uint64(8))).sum(axis=1, dtype=np.uint64) + np.uint64(n)))
        self.first, self.count = words.first, words.count
        windows = np.where(self.count > 0, 1 + np.maximum(0, -(-(self.count - WINDOW) // STRIDE)), 0)
        self.row = np.repeat(np.arange(len(self.count)), windows)
        number = np.arange(len(self.row)) - np.repeat(np.cumsum(windows) - windows, windows)
        self.begin = self.first[self.row] + number * STRIDE
        self.size = np.minimum(WINDOW, self.first[self.row + 1] - self.begin)

    def windows(self, which: np.ndarray | slice) -> tuple[np.ndarray, np.ndarray]:
        """(word numbers, mask), each (time, window)."""
        step = np.arange(WINDOW)[:, None]
        size = self.size[which]
        at = self.begin[which] + np.minimum(step, size - 1)
        return self.word[at], (step < size).astype(np.float32)


class RecurrentScorer:
    """Words become vectors: the evidence each and its first bytes carried in the learned documents, a hashed embedding, and the last states of
    two character networks. Two word networks read a window in both directions, attention pools their states into one logit."""

    def __init__(self, seed: int = 3) -> None:
        rng = np.random.default_rng(seed)
        draw = lambda *shape: (rng.standard_normal(shape) * 0.3).astype(np.float32)
        self.p = {"chars": draw(256, _CHAR), "words": draw(_BUCKETS, _WORD) * np.float32(0.1)}
        for name, inputs, hidden in (("cf", _CHAR, _CHAR_STATE), ("cb", _CHAR, _CHAR_STATE), ("wf", _INPUT, _STATE), ("wb", _INPUT, _STATE)):
            self.p |= gru_params(rng, inputs, hidden, name)
        self.p |= {"att": draw(2 * _STATE, _ATTEND), "query": draw(_ATTEND), "out": draw(2 * _STATE), "shift": np.zeros(1, np.float32)}
        self.known, self.weight = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.float32)
        self.curve = (1.0, 0.0)

    def evidence(self, keys: list[np.ndarray]) -> np.ndarray:
        """What words and their beginnings told in the learned documents, a column each."""
        out = np.zeros((len(keys[0]), _EVIDENCE), dtype=np.float32)
        for k, key in enumerate(keys if len(self.known) else []):
            at = np.minimum(np.searchsorted(self.known, key), len(self.known) - 1)
            out[:, k] = np.where(self.known[at] == key, self.weight[at], 0)
        return out

    def vectors(self, hashes: np.ndarray, spelled: np.ndarray, mask: np.ndarray, evidence: np.ndarray, keep: bool = False) -> tuple[np.ndarray, list]:
        """A vector for each distinct word."""
        p, parts, tapes = self.p, [evidence, p_words(self.p, hashes)], []
        for k, name in enumerate(("cf", "cb")):
            table = p["chars"] @ p[f"{name}.w"] + p[f"{name}.b"]
            states, tape = gru(table[spelled[k].T], mask.T, p[f"{name}.u"], keep)
            parts.append(states[-1])
            tapes.append(tape)
        return np.concatenate(parts, axis=1).astype(np.float32), tapes

    def windows(self, vectors: np.ndarray, words: np.ndarray, mask: np.ndarray, keep: bool = False) -> tuple[np.ndarray, tuple]:
        """A logit for each window, from vectors of distinct words and the word numbers of its places."""
        p, states, tapes = self.p, [], []
        for name, turn in (("wf", slice(None)), ("wb", slice(None, None, -1))):
            table = vectors @ p[f"{name}.w"] + p[f"{name}.b"]
            found, tape = gru(table[words[turn]], mask[turn], p[f"{name}.u"], keep)
            states.append(found[turn])
            tapes.append(tape)
        h = np.concatenate(states, axis=2)
        t = np.tanh(h @ p["att"])
        e = np.exp(t @ p["query"]) * mask
        a = e / e.sum(axis=0)
        z = (a[:, :, None] * h).sum(axis=0)
        return z @ p["out"] + p["shift"][0], (h, t, a, z, tapes)

    def learn(self, adam: Adam, texts: Texts, which: np.ndarray, y: np.ndarray, weight: np.ndarray, evidence: np.ndarray) -> None:
        """One step on some windows, through the words they hold."""
        p = self.p
        words, mask = texts.windows(which)
        distinct, words = np.unique(words, return_inverse=True)
        words = words.reshape(mask.shape)
        hashes, spelled, marks = texts.hash[distinct], texts.spelled[:, distinct], texts.mask[distinct]
        vectors, char_tapes = self.vectors(hashes, spelled, marks, evidence[distinct], keep=True)
        logit, (h, t, a, z, tapes) = self.windows(vectors, words, mask, keep=True)
        d = ((sigmoid(logit) - y) * weight).astype(np.float32)
        g = {"out": z.T @ d, "shift": np.array([d.sum()])}
        dz = d[:, None] * p["out"]
        da = (h * dz[None]).sum(axis=2)
        de = a * (da - (a * da).sum(axis=0))
        dt = de[:, :, None] * p["query"] * (1 - t * t)
        g["query"] = np.einsum("tb,tbk->k", de, t)
        g["att"] = np.einsum("tbi,tbk->ik", h, dt)
        dh = a[:, :, None] * dz[None] + dt @ p["att"].T
        d_vectors = np.zeros_like(vectors)
        for k, (name, turn) in enumerate((("wf", slice(None)), ("wb", slice(None, None, -1)))):
            d_in, g[f"{name}.u"] = gru_grad(dh[turn][:, :, k * _STATE : (k + 1) * _STATE], tapes[k], p[f"{name}.u"])
            d_table = np.zeros((len(vectors), d_in.shape[2]), dtype=np.float32)
            np.add.at(d_table, words[turn].reshape(-1), d_in.reshape(-1, d_in.shape[2]))
            g[f"{name}.w"], g[f"{name}.b"] = vectors.T @ d_table, d_table.sum(axis=0)
            d_vectors += d_table @ p[f"{name}.w"].T
        g["words"] = np.zeros_like(p["words"])
        np.add.at(g["words"], word_bucket(hashes), d_vectors[:, _EVIDENCE : _EVIDENCE + _WORD])
        g["chars"] = np.zeros_like(p["chars"])
        for k, name in enumerate(("cf", "cb")):
            d_states = np.zeros((SPELLED, len(vectors), _CHAR_STATE), dtype=np.float32)
            d_states[-1] = d_vectors[:, _EVIDENCE + _WORD + k * _CHAR_STATE : _EVIDENCE + _WORD + (k + 1) * _CHAR_STATE]
            d_in, g[f"{name}.u"] = gru_grad(d_states, char_tapes[k], p[f"{name}.u"])
            d_table = np.zeros((256, d_in.shape[2]), dtype=np.float32)
            np.add.at(d_table, spelled[k].T.reshape(-1), d_in.reshape(-1, d_in.shape[2]))
            g[f"{name}.w"], g[f"{name}.b"] = p["chars"].T @ d_table, d_table.sum(axis=0)
            g["chars"] += d_table @ p[f"{name}.w"].T
        adam.step({k: v + (3e-3 if k in ("words", "chars") else 3e-4) * p[k] for k, v in g.items()})

    def best_windows(self, texts: Texts, vectors: np.ndarray, block: int = 4096) -> np.ndarray:
        """The logits of all windows."""
        out = np.zeros(len(texts.row), dtype=np.float32)
        for a in range(0, len(out), block):
            which = slice(a, a + block)
            out[which] = self.windows(vectors, *texts.windows(which))[0]
        return out


def word_bucket(hashes: np.ndarray) -> np.ndarray:
    return (textkit.mix(hashes) >> np.uint64(20) & np.uint64(_BUCKETS - 1)).astype(np.int64)


def p_words(params: dict, hashes: np.ndarray) -> np.ndarray:
    return params["words"][word_bucket(hashes)]


def _evidence(good: np.ndarray, bad: np.ndarray, n_good: int, n_bad: int) -> np.ndarray:
    """Per key: the log ratio of its shares of toxic and other documents, shrunk by its standard error; 0 for words of fewer than 3 documents."""
    ratio = np.log((bad + 0.5) / (n_bad + 1)) - np.log((good + 0.5) / (n_good + 1))
    error = np.sqrt(1 / (bad + 0.5) + 1 / (good + 0.5))
    sure = np.maximum(0, np.abs(ratio) - 1.5 * error)
    return np.where(good + bad >= 3, np.sign(ratio) * np.minimum(sure, 4), 0).astype(np.float32)


def train(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE, epochs: int = 6) -> RecurrentScorer | None:
    """Learns from at most `bound` labelled documents outside the held-out fold; None without both labels.

    Word evidence that a document is trained with comes from the other folds of the sample alone. Each epoch scores all windows of all
    documents and learns from the highest of each, as a toxic document need only have one toxic window, and from one other of each.
    """
    rows = labelled_sample(docs, labels, "toxic", fold("doc_id", 4) != 2, bound)
    y = np.array([r[1] for r in rows], dtype=np.float32)
    if not len(y) or y.min() == y.max():
        return None
    data, offsets = textkit.column_bytes(pa.array([r[0] for r in rows], pa.large_string()))
    texts, model, folds = Texts(data, offsets), RecurrentScorer(), 4
    doc = np.repeat(np.arange(len(y)), texts.count)
    rng = np.random.default_rng(5)
    part = rng.permutation(len(y)) % folds
    sizes = np.array([[((part == f) & (y == v)).sum() for v in (0, 1)] for f in range(folds)])
    without = [np.zeros((len(texts.hash), _EVIDENCE), dtype=np.float32) for _ in range(folds)]
    known, weight = [], []
    for c, keys in enumerate(texts.keys):
        keys, of = np.unique(keys, return_inverse=True)
        once = np.unique(doc * len(keys) + of[texts.word])
        doc_of, key_of = once // len(keys), once % len(keys)
        counts = np.stack([np.stack([np.bincount(key_of[(part[doc_of] == f) & (y[doc_of] == v)], minlength=len(keys)) for v in (0, 1)]) for f in range(folds)])
        for f in range(folds):
            without[f][:, c] = _evidence(*(counts.sum(axis=0) - counts[f]), *(sizes.sum(axis=0) - sizes[f]))[of]
        full = _evidence(*counts.sum(axis=0), *sizes.sum(axis=0))
        known.append(keys[full != 0])
        weight.append(full[full != 0])
    part_of = part[texts.row]
    adam = Adam(model.p, 0.01)
    share = np.where(y == 1, 0.5 / (y == 1).sum(), 0.5 / (y == 0).sum()) * len(y)
    share = np.sqrt(share).astype(np.float32)
    logits = np.concatenate([np.zeros(0, np.float32)] + [np.zeros(len(texts.row), np.float32)])
    for epoch in range(epochs + 1):
        for f in range(folds):
            mine = np.flatnonzero(part_of == f)
            if epoch == 0:  # before anything is learned, windows rank by their strongest word
                words, mask = texts.windows(mine)
                logits[mine] = (without[f].sum(axis=1)[words] * mask).max(axis=0)
            else:
                vectors = model.vectors(texts.hash, texts.spelled, texts.mask, without[f])[0]
                for a in range(0, len(mine), 4096):
                    logits[mine[a : a + 4096]] = model.windows(vectors, *texts.windows(mine[a : a + 4096]))[0]
        order = np.lexsort((-logits, texts.row))
        top = order[np.searchsorted(texts.row[order], np.unique(texts.row))]
        if epoch == epochs:
            break
        adam.rate = 0.01 if epoch < epochs - 3 else 0.003
        some = rng.choice(len(texts.row), size=min(len(y), len(texts.row)), replace=False)
        some = some[y[texts.row[some]] == 0]
        take = np.unique(np.concatenate([top, some]))
        for f in range(folds):
            mine = rng.permutation(take[part_of[take] == f])
            for a in range(0, len(mine), 128):
                which = mine[a : a + 128]
                w = share[texts.row[which]]
                model.learn(adam, texts, which, y[texts.row[which]], w / w.sum(), without[f])
    model.curve = platt(logits[top].astype(np.float64), y[texts.row[top]])
    known, weight = np.concatenate(known), np.concatenate(weight)
    order = np.argsort(known)
    model.known, model.weight = known[order], weight[order]
    return model


class _Words:
    """Vectors of words already met by a task."""

    def __init__(self, model: RecurrentScorer) -> None:
        self.model = model
        self.hash, self.vector = np.zeros(0, dtype=np.uint64), np.zeros((0, _INPUT), dtype=np.float32)

    def __call__(self, texts: Texts) -> np.ndarray:
        if len(self.hash) > CACHE_WORDS:
            self.hash, self.vector = self.hash[:0], self.vector[:0]
        at = np.searchsorted(self.hash, texts.hash)
        new = np.ones(len(texts.hash), dtype=bool) if not len(self.hash) else self.hash[np.minimum(at, len(self.hash) - 1)] != texts.hash
        if new.any():
            k = np.flatnonzero(new)
            made = self.model.vectors(texts.hash[k], texts.spelled[:, k], texts.mask[k], self.model.evidence([x[k] for x in texts.keys]))[0]
            place = np.searchsorted(self.hash, texts.hash[k])
            self.hash, self.vector = np.insert(self.hash, place, texts.hash[k]), np.insert(self.vector, place, made, axis=0)
        return self.vector[np.searchsorted(self.hash, texts.hash)]


def score_toxicity(docs: DataFrame, model: RecurrentScorer | None) -> DataFrame:
    """doc_id, held_out, score, predicted for every document: its highest window, over the whole text, on a calibrated scale.

    A null text, and one without words, scores 0. Without a model every score is 0. Equal texts get equal scores; a null id falls into fold 0.
    An empty table gives no rows. Other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        words = _Words(model) if model is not None else None
        for batch in batches:
            for a, b, data, offsets in textkit.texts(batch.column("text")):
                score = np.zeros(b - a)
                if model is not None:
                    texts = Texts(data, offsets)
                    if len(texts.row):
                        logit = model.best_windows(texts, words(texts)).astype(np.float64)
                        best = np.full(b - a, -np.inf)
                        np.maximum.at(best, texts.row, logit)
                        slope, shift = model.curve
                        score = np.where(np.isfinite(best), sigmoid(slope * np.where(np.isfinite(best), best, 0) + shift), 0.0)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(a, b - a), batch.column("held_out").slice(a, b - a), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))],
                    names=["doc_id", "held_out", "score", "predicted"],
                )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 4) == 2).alias("held_out"), "text")
    return rows.mapInArrow(scored, "doc_id long, held_out boolean, score double, predicted int")
