"""The sketches by definition, over sets of hashes in plain Python: a second opinion for the tests."""

from __future__ import annotations

import math
from collections import defaultdict
from itertools import count


def zeros(x: int, most: int) -> int:
    """How often 2 divides x, ``most`` at most (and for 0)."""
    return next(i for i in range(most + 1) if i == most or x >> i & 1)


def ranks(ys, M, L) -> dict[int, set[int]]:
    """Bucket -> the ranks seen in it, from 0."""
    k, out = M.bit_length() - 1, defaultdict(set)
    for y in set(ys):
        out[y & (M - 1)].add(zeros(y >> k, L - k))
    return out


def probabilistic_counting(ys, M, L):
    missing = (next(i for i in count() if i not in seen) for seen in ranks(ys, M, L).values())
    return 2 ** (sum(missing) / M) * M / 0.77351


def loglog(ys, M, L):
    top = sum(max(seen) + 1 for seen in ranks(ys, M, L).values())
    return (0.39701 - (2 * math.pi**2 + math.log(2) ** 2) / (48 * M)) * M * 2 ** (top / M)


def adaptive(ys, M, L):
    unused = 1 - len(ranks(ys, M, L)) / M
    return -M * math.log(unused) if unused >= 0.051 else loglog(ys, M, L)


def smallest_hashes(pairs, M, L):
    """pairs of (hash, tuple)."""
    kept = sorted(set(pairs))[:M]
    return float(len(kept)) if len(kept) < M or not kept[-1][0] else 2.0**L * M / kept[-1][0]


def level_pruned(pairs, M, L):
    """(estimate, floor), the floor the least whose tail fits."""
    level = {x: zeros(y, L) for y, x in pairs}
    tail = lambda t: sum(v >= t for v in level.values())
    floor = next(t for t in count() if tail(t) <= M)
    return 2.0**floor * tail(floor), floor
