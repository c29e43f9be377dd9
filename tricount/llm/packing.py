"""Packing token sequences into windows by online sum-of-squares placement."""

from __future__ import annotations

import os
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm import textkit

#: Tokens of a window, and the id that ends a document.
WINDOW, END_ID = 4096, 2
#: Distinct words whose ids a worker remembers before it starts over.
CACHE_WORDS = 1_000_000
#: New words are encoded so many at a time, with this word between them.
JOINED, BETWEEN = 256, "→"
#: Groups (or words) whose encodings, of some 200 bytes a token, are held at once.
ENCODED = 32
#: Partially filled windows a task holds (some 8 KB each): when there are more, the fullest one is filled up from the emptiest.
OPEN_WINDOWS = 4096

SCHEMA = "doc_id long, start long, length long, doc_tokens long, sequence_id long, offset long, ids binary"


class WordTokens:
    """Token ids of whole texts, put together from those of their words.

    For tokenizers that drop white space, so that no token reaches over it: the ids of a text are then those of its words one after another.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        between = self.tokenizer.encode(BETWEEN, add_special_tokens=False).ids
        self.between = between[0] if len(between) == 1 else None
        self._forget()

    def _forget(self) -> None:
        self.known = np.zeros(0, dtype=np.uint64)
        self.at, self.size = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        self.flat = np.zeros(0, dtype=np.uint32)

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        parts = (texts[a : a + ENCODED] for a in range(0, len(texts), ENCODED))
        return [np.array(x.ids, dtype=np.uint32) for part in parts for x in self.tokenizer.encode_batch_fast(part, add_special_tokens=False)]

    def _encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words, how many each has). Words are encoded in groups and told apart by the id of the word between them; a group in which a word has that id itself is encoded word by word."""
        groups = [words[a : a + JOINED] for a in range(0, len(words), JOINED)]
        flat, sizes = [], []
        for group, ids in zip(groups, self._ids([f" {BETWEEN} ".join(g) for g in groups]), strict=True):
            cut = np.flatnonzero(ids == self.between) if self.between is not None else []
            if len(cut) == len(group) - 1 and self.between is not None:
                sizes.append(np.diff(np.concatenate([[-1], cut, [len(ids)]])) - 1)
                flat.append(np.delete(ids, cut))
            else:
                alone = self._ids(group)
                sizes.append(np.array([len(x) for x in alone]))
                flat += alone
        return np.concatenate(flat), np.concatenate(sizes).astype(np.int64)

    def _learn(self, hashes: np.ndarray, words: list[str]) -> None:
        ids, size = self._encoded(words)
        at = len(self.flat) + np.cumsum(size) - size
        self.flat = np.concatenate([self.flat, ids])
        place = np.searchsorted(self.known, hashes)
        self.known, self.at, self.size = np.insert(self.known, place, hashes), np.insert(self.at, place, at), np.insert(self.size, place, size)

    def __call__(self, data: np.ndarray, offsets: np.ndarray) -> list[np.ndarray]:
        """The ids of each text, END_ID last."""
        words = textkit.Words(data, offsets, lower=False)
        distinct, first, inverse = np.unique(words.hashes(), return_index=True, return_inverse=True)
        if len(self.known) > CACHE_WORDS:
            self._forget()
        spot = np.minimum(np.searchsorted(self.known, distinct), max(len(self.known) - 1, 0))
        new = np.ones(len(distinct), dtype=bool) if not len(self.known) else self.known[spot] != distinct
        if new.any():
            raw = data.tobytes()
            spans = zip(words.start[first[new]].tolist(), words.end[first[new]].tolist(), strict=True)
            self._learn(distinct[new], [raw[a:b].decode("utf-8", "replace") for a, b in spans])
        spot = np.searchsorted(self.known, distinct)
        at, size = self.at[spot][inverse], self.size[spot][inverse]
        upto = np.cumsum(size)
        flat = self.flat[np.repeat(at - (upto - size), size) + np.arange(int(upto[-1]) if len(upto) else 0)]
        upto = np.concatenate([[0], upto])[words.first]
        end = np.array([END_ID], dtype=np.uint32)
        return [np.concatenate([flat[a:b], end]) for a, b in zip(upto[:-1].tolist(), upto[1:].tolist(), strict=True)]


@lru_cache(maxsize=1)
def word_tokens(path: str) -> WordTokens:
    """One for each worker process, so that its tasks share what it remembers. What reading its file took (some 60 MB) goes back to the system before texts are read."""
    tokens = WordTokens(path)
    textkit.release()
    return tokens


class Packer:
    """Places pieces of documents into windows of fixed length, one document after another.

    A document's whole windows are cut off first. The rest goes to the fill level for which the sum, over levels, of the squared count of
    windows at that level is least afterwards; an empty window is one of the choices, and ties go to the fullest. `count[level]` is
    the level array. Full windows are handed out at once. With more than `most` windows open, and for all of them at the end, the fullest window is
    filled up with what the emptiest one holds, cut where it is full: so fuller windows keep what was placed in them, and one window at most is left to be padded.
    """

    def __init__(self, first_sequence: int, window: int = WINDOW, most: int | None = None) -> None:
        self.window, self.next, self.most = window, first_sequence, OPEN_WINDOWS if most is None else most
        self.count = np.zeros(window + 1, dtype=np.int64)
        self.open: dict[int, list[list]] = {}
        self.held = 0
        self.done: list[tuple] = []

    def _emit(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc, start, ids, total in pieces:
            self.done.append((doc, start, len(ids), total, self.next, offset, ids.tobytes()))
            offset += len(ids)
        self.next += 1

    def level_for(self, size: int) -> int:
        """The level at which a piece of this size is best placed; 0 is an empty window."""
        room = self.window - size
        levels = np.flatnonzero(self.count[: room + 1])
        after = self.count[levels + size]
        after[levels == room] = 0  # full windows leave the sum
        change = 2 * after - 2 * self.count[levels] + 1 + (levels < room)
        if not len(levels):
            return 0
        best = len(levels) - 1 - int(np.argmin(change[::-1]))
        return int(levels[best]) if change[best] <= 2 * self.count[size] + 1 else 0

    def add(self, doc: int | None, ids: np.ndarray) -> None:
        total, whole = len(ids), len(ids) // self.window * self.window
        for a in range(0, whole, self.window):
            self._emit([(doc, a, ids[a : a + self.window], total)])
        size = total - whole
        if not size:
            return
        piece = (doc, whole, ids[whole:].copy() if whole else ids, total)  # a view would keep the whole document as long as its window is open
        level = self.level_for(size)
        pieces = self._open_at(level) if level else []
        pieces.append(piece)
        self._put(level + size, pieces)
        while self.held > self.most:
            self._fill_up()

    def _open_at(self, level: int) -> list[tuple]:
        self.count[level] -= 1
        self.held -= 1
        return self.open[level].pop()

    def _fill_up(self) -> None:
        """Moves what the emptiest window holds into the fullest, as far as there is room."""
        levels = np.flatnonzero(self.count)
        most, least = int(levels[-1]), int(levels[0])
        into, out = self._open_at(most), self._open_at(least)
        while out and most < self.window:
            doc, start, ids, total = out.pop()
            keep = max(0, len(ids) - (self.window - most))
            into.append((doc, start + keep, ids[keep:], total))
            most, least = most + len(ids) - keep, least - len(ids) + keep
            if keep:
                out.append((doc, start, ids[:keep], total))
        self._put(most, into)
        if out:
            self._put(least, out)

    def _put(self, level: int, pieces: list[tuple]) -> None:
        if level == self.window:
            self._emit(pieces)
            return
        self.open.setdefault(level, []).append(pieces)
        self.count[level] += 1
        self.held += 1

    def close(self) -> None:
        while self.held > 1:
            self._fill_up()
        for level in np.flatnonzero(self.count).tolist():
            self._emit(self._open_at(level))

    def taken(self) -> list[tuple]:
        out, self.done = self.done, []
        return out


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW) -> DataFrame:
    """Pieces of all documents in sequences of at most `window` tokens: doc_id, start, length, doc_tokens, sequence_id, offset, ids.

    A document's ids are its tokens and END_ID; each lies in one piece (`ids`: little-endian unsigned 32-bit). Each input partition is packed by one task in
    the order of its rows, without a shuffle, and numbers its sequences from its own range, so a repeated task gives the same rows. All sequences of a partition
    are full but for one, which is to be padded: with partitions of many documents padding vanishes.

    A null or empty text has END_ID alone. Null and repeated ids are packed like others, each row as a document of its own. A long text runs through many sequences.
    An empty table gives no rows. Other columns are ignored.
    """
    columns = [x.split()[0] for x in SCHEMA.split(", ")]
    types = [pa.int64()] * 6 + [pa.binary()]

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = None
        packer = Packer(TaskContext.get().partitionId() << 32, window)

        def rows() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*packer.taken(), strict=True), types, strict=True)], names=columns)

        for batch in batches:
            tokens = tokens or word_tokens(tokenizer_path)
            ids = batch.column("doc_id").to_pylist()
            for a, _, data, offsets in textkit.texts(batch.column("text")):
                for k, found in enumerate(tokens(data, offsets)):
                    packer.add(ids[a + k], found)
                if len(packer.done) > 2000:
                    yield rows()
        packer.close()
        if packer.done:
            yield rows()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(packed, SCHEMA)
