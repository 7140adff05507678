"""The hashes of mode 'md5' in numpy, many at once: the same numbers as hashing.tuple_hash(), at a part of its cost where each tuple is hashed for many seeds."""

from __future__ import annotations

import hashlib
import math

import numpy as np

_TERMS = [int(abs(math.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64)]
_TURNS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_POWERS = np.array([10**i for i in range(1, 20)], np.uint64)
#: Texts hashed at once: their words stay in the cache.
_BLOCK = 16_384
#: Texts kept with their hashes, for each dimension and task.
_MEMO = 20_000


def _first_words(words: list, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the digests of n messages of one block; words: its 16 words, each an array or a number that all share."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            w = words[i]
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            w = words[(5 * i + 1) % 16]
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            w = words[(3 * i + 5) % 16]
        else:
            np.bitwise_not(d, out=f)
            f |= b
            f ^= c
            w = words[7 * i % 16]
        f += a
        if isinstance(w, int):
            f += np.uint32((w + _TERMS[i]) & 0xFFFFFFFF)
        else:
            f += w
            f += np.uint32(_TERMS[i])
        np.left_shift(f, np.uint32(_TURNS[i]), out=t)
        f >>= np.uint32(32 - _TURNS[i])
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])


def of_text(text: bytes) -> int:
    """The first 64 bits of the digest."""
    return int.from_bytes(hashlib.md5(text).digest()[:8], "big")


def of_numbers(prefix: bytes, values: np.ndarray) -> np.ndarray:
    """of_text(prefix + decimal text) of each long."""
    if len(prefix) + 20 > 55:  # more than a block
        return np.fromiter((of_text(prefix + b"%d" % v) for v in values.tolist()), np.uint64, len(values))
    out, minus, size = np.empty(len(values), np.uint64), values < 0, values.view(np.uint64)
    size = np.where(minus, np.uint64(0) - size, size)
    kind = (np.searchsorted(_POWERS, size, side="right") + 1) * 2 + minus
    for of_kind in np.unique(kind).tolist():
        digits, head = of_kind // 2, prefix + b"-" * (of_kind % 2)
        length, found = len(head) + digits, np.flatnonzero(kind == of_kind)
        block = bytearray(64)
        block[: len(head)], block[length], block[56:] = head, 0x80, (8 * length).to_bytes(8, "little")
        fixed = [int.from_bytes(block[4 * i : 4 * i + 4], "little") for i in range(16)]
        for lo in range(0, len(found), _BLOCK):
            own = found[lo : lo + _BLOCK]
            words, rest = list(fixed), size[own]
            for at in range(length - 1, len(head) - 1, -1):
                less = rest // np.uint64(10)
                digit = (rest - less * np.uint64(10)).astype(np.uint32) + np.uint32(48)
                if isinstance(words[at // 4], int):
                    words[at // 4] = np.full(len(own), words[at // 4], np.uint32)
                words[at // 4] |= digit << np.uint32(8 * (at % 4))
                rest = less
            a, b = _first_words(words, len(own))
            out[own] = (a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap()
    return out


class TupleHash:
    """Hashes of the tuples of a view for several seeds. names: of its dimensions; a dimension is given as an array of longs with a mask of nulls, or as a list of texts and None."""

    def __init__(self, names: list[str], seeds: list[int], L: int, mix: str):
        self.names, self.seeds, self.L, self.mix = names, seeds, L, mix
        self._kept: dict = {n: (None, None) for n in names}
        self._texts: dict = {n: {} for n in names}

    def _cut(self, h: np.ndarray) -> np.ndarray:
        return h >> np.uint64(32) if self.L == 32 else h

    def _null(self, name: str) -> list[int]:
        return [of_text(f"{s}:{name}:n".encode()) for s in self.seeds]

    def _numbers(self, name: str, values: np.ndarray, null: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(a row of hashes for each seed, a column for each value and one for null; each tuple's column)."""
        once, at = np.unique(values, return_inverse=True)
        kept, table = self._kept[name]
        if kept is None or not np.array_equal(kept, once):
            rows = [np.append(of_numbers(f"{s}:{name}:v:".encode(), once), np.uint64(n)) for s, n in zip(self.seeds, self._null(name))]
            table = self._cut(np.array(rows, np.uint64))
            self._kept[name] = once, table
        return table, np.where(null, len(once), at) if null.any() else at

    def _strings(self, name: str, values: list) -> tuple[np.ndarray, np.ndarray]:
        own, memo = {}, self._texts[name]
        at = np.fromiter((own.setdefault(v, len(own)) for v in values), np.int64, len(values))
        if len(memo) > _MEMO:
            memo.clear()
        for v in own:
            if v not in memo:
                memo[v] = self._null(name) if v is None else [of_text(f"{s}:{name}:v:{v}".encode("utf-8", "surrogatepass")) for s in self.seeds]
        return self._cut(np.array([memo[v] for v in own], np.uint64).T), at

    def each(self, dims: list):
        """(seed, hashes as longs) for each seed; dims in the order of names."""
        tables = [self._strings(n, d) if isinstance(d, list) else self._numbers(n, *d) for n, d in zip(self.names, dims)]
        for i, seed in enumerate(self.seeds):
            y = tables[0][0][i][tables[0][1]]
            for table, at in tables[1:]:
                y = y ^ table[i][at]
            yield seed, (self._cut(of_numbers(b"", y.view(np.int64))) if self.mix == "final" else y).view(np.int64)
