"""Bounded partial states of the sample-type sketches, kept by each task over Arrow batches: what a task sends on is at most M rows for each view and seed.

Batches and states are arrays: a batch is cut by each view's bound and freed of repetitions before it meets the state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SCHEMA = "view_id string, seed int, h long, key long"
LEVELED_SCHEMA = "view_id string, seed int, key long, level int, level_floor int"


def _views(batch: pa.RecordBatch) -> Iterator[tuple[tuple, np.ndarray]]:
    """(view_id, seed) and row positions of each that the batch holds."""
    view = batch.column("view_id").dictionary_encode()
    seeds, seed = np.unique(batch.column("seed").to_numpy(), return_inverse=True)
    names = view.dictionary.to_pylist()
    code = view.indices.to_numpy() * len(seeds) + seed
    order = np.argsort(code, kind="stable")
    for own in np.split(order, np.flatnonzero(np.diff(code[order])) + 1):
        if len(own):
            c = int(code[own[0]])
            yield (names[c // len(seeds)], int(seeds[c % len(seeds)])), own


def _distinct(h: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Positions of the distinct (h, key), in their order."""
    order = np.lexsort((key, h))
    first = np.ones(len(order), bool)
    first[1:] = (np.diff(h[order]) != 0) | (np.diff(key[order]) != 0)
    return order[first]


def bottom(M: int):
    """Keeps the M smallest (h, key) of each view."""

    def run(batches):
        held: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}
        none = np.empty(0, np.int64)
        for batch in batches:
            h, key = batch.column("h").to_numpy(), batch.column("key").to_numpy()
            for view, own in _views(batch):
                now = held.get(view, (none, none))
                if len(now[0]) == M:
                    own = own[h[own] <= now[0][-1]]
                if len(own):
                    both = np.concatenate([now[0], h[own]]), np.concatenate([now[1], key[own]])
                    at = _distinct(*both)[:M]
                    held[view] = both[0][at], both[1][at]
        for (view, seed), (h, key) in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([view] * len(h), pa.string()), pa.array(np.full(len(h), seed, np.int32)), pa.array(h), pa.array(key)], names=["view_id", "seed", "h", "key"])

    return run


def leveled(M: int):
    """Keeps the distinct tuples of at least a floor that rises while there are more than M; a view's floor comes with its rows, and alone (null key) if none is left."""

    def run(batches):
        held: dict[tuple, tuple[np.ndarray, np.ndarray, int]] = {}
        none = np.empty(0, np.int64)
        for batch in batches:
            level, key = batch.column("h").to_numpy(), batch.column("key").to_numpy()
            for view, own in _views(batch):
                levels, keys, floor = held.get(view, (none, none, 0))
                own = own[level[own] >= floor]
                if len(own):
                    levels, keys = np.concatenate([levels, level[own]]), np.concatenate([keys, key[own]])
                    at = _distinct(levels, keys)
                    levels, keys = levels[at], keys[at]
                    while len(levels) > M:  # in order of levels, so a floor is a cut
                        floor = max(floor + 1, int(levels[-M - 1]) + 1)
                        cut = int(np.searchsorted(levels, floor))
                        levels, keys = levels[cut:], keys[cut:]
                held[view] = levels, keys, floor
        for (view, seed), (levels, keys, floor) in held.items():
            n = max(1, len(levels))
            yield pa.RecordBatch.from_arrays([
                pa.array([view] * n, pa.string()), pa.array(np.full(n, seed, np.int32)), pa.array(keys if len(keys) else [None], pa.int64()),
                pa.array(levels.astype(np.int32) if len(levels) else [-1], pa.int32()), pa.array(np.full(n, floor, np.int32)),
            ], names=["view_id", "seed", "key", "level", "level_floor"])

    return run
