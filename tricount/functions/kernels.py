"""Intersections of sorted lists, for whole batches of list pairs at once, with the cost counters of a two-cursor merge."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa


def _keys(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(number of the list, value) of every element."""
    sizes = np.diff(lists.offsets.to_numpy())
    return np.repeat(np.arange(len(sizes)), sizes), lists.flatten().to_numpy()


def _composite(a: pa.Array, b: pa.Array) -> tuple[np.ndarray, np.ndarray, int]:
    """Both sides as ascending keys that order by list number first; values are replaced by their rank in the batch."""
    (ra, va), (rb, vb) = _keys(a), _keys(b)
    values, rank = np.unique(np.concatenate([va, vb]), return_inverse=True)
    n = max(len(values), 1)
    return ra * n + rank[: len(va)], rb * n + rank[len(va) :], n


def sorted_run(a: pa.Array, b: pa.Array) -> np.ndarray:
    """Sizes of the intersections, by sorting both sides into one run: equal neighbours are shared."""
    x, y, n = _composite(a, b)
    run = np.concatenate([x, y])
    run.sort(kind="stable")
    return np.bincount(run[1:][run[1:] == run[:-1]] // n, minlength=len(a))


def gallop(a: pa.Array, b: pa.Array) -> np.ndarray:
    """Sizes of the intersections, by binary search of the side with fewer elements in the other."""
    x, y, n = _composite(a, b)
    few, many = (x, y) if len(x) <= len(y) else (y, x)
    if not len(many):
        return np.zeros(len(a), dtype=np.int64)
    at = np.minimum(np.searchsorted(many, few), len(many) - 1)
    return np.bincount(few[many[at] == few] // n, minlength=len(a))


def _cursors(lists: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(elements with one more behind the last, where each list begins, where it ends)."""
    offsets = lists.offsets.to_numpy().astype(np.int64)
    return np.append(lists.flatten().to_numpy(), 0), offsets[:-1] - offsets[0], offsets[1:] - offsets[0]


def walk(a: pa.Array, b: pa.Array, eager: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(shared elements, steps, elements read) of each pair of lists, all pairs walking at once with two cursors that stop where either list ends.

    A step moves the cursor at the smaller head, or both at equal heads. The eager form reads both heads at each step. The lazy form keeps the heads and reads one element for
    each cursor that has moved, and none behind a list's end. Pairs that have ended are put aside when they are a quarter of those that walk.
    """
    (x, i, ends_i), (y, j, ends_j) = _cursors(a), _cursors(b)
    shared, steps, reads = (np.zeros(len(a), dtype=np.int64) for _ in range(3))
    pair = np.flatnonzero((i < ends_i) & (j < ends_j))
    i, j, ends_i, ends_j = i[pair], j[pair], ends_i[pair], ends_j[pair]
    at_x, at_y = x[i], y[j]
    found, moves, read = np.zeros(len(pair), dtype=np.int64), np.zeros(len(pair), dtype=np.int64), np.full(len(pair), 0 if eager else 2)
    going = np.ones(len(pair), dtype=bool)
    left = len(pair)
    while left:
        if eager:
            at_x, at_y = x[i], y[j]
            read += 2 * going
        left_on, right_on = (at_x <= at_y) & going, (at_y <= at_x) & going
        found += left_on & right_on
        moves += going
        i += left_on
        j += right_on
        going = (i < ends_i) & (j < ends_j)
        if not eager:
            for moved, cursor, ends, values, head in ((left_on, i, ends_i, x, at_x), (right_on, j, ends_j, y, at_y)):
                new = np.flatnonzero(moved & (cursor < ends))
                head[new] = values[cursor[new]]
                read[new] += 1
        left = int(going.sum())
        if 4 * left <= 3 * len(going):
            done = ~going
            shared[pair[done]], steps[pair[done]], reads[pair[done]] = found[done], moves[done], read[done]
            pair, i, j, ends_i, ends_j, at_x, at_y, found, moves, read = (v[going] for v in (pair, i, j, ends_i, ends_j, at_x, at_y, found, moves, read))
            going = np.ones(left, dtype=bool)
    shared[pair], steps[pair], reads[pair] = found, moves, read
    return shared, steps, reads


def merge(a: pa.Array, b: pa.Array) -> np.ndarray:
    """Sizes of the intersections, by two cursors."""
    return walk(a, b)[0]


#: Kernels give (shared elements, steps, elements read) of each pair of lists; only the merges count steps and reads.
KERNELS: dict[str, Callable[[pa.Array, pa.Array], tuple[np.ndarray, np.ndarray, np.ndarray]]] = {
    "merge": walk, "merge_eager": lambda a, b: walk(a, b, eager=True), "sorted_run": lambda a, b: (sorted_run(a, b),) + (np.zeros(0, dtype=np.int64),) * 2, "gallop": lambda a, b: (gallop(a, b),) + (np.zeros(0, dtype=np.int64),) * 2,
}


def counted(kernel: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """An Arrow function over the columns nu and nv: one row per batch with the triangles found and, for the merges, steps and reads."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, steps, reads = KERNELS[kernel](batch.column("nu"), batch.column("nv"))
            yield pa.RecordBatch.from_pydict({"triangles": [int(found.sum())], "steps": [int(steps.sum())], "reads": [int(reads.sum())]})

    return run


COUNTED = "triangles long, steps long, reads long"
