"""Error theory: standard errors, reliability bounds and their inverses, bit requirements."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession


def rse_pc(M: int) -> float:
    return 0.78 / math.sqrt(M)


def rse_ll(M: int) -> float:
    return 1.3 / math.sqrt(M)


def gc_delta(M: int, k: int, eps: float, form: str = "printed") -> float:
    """1 - reliability of Generalized Counting within eps, k-wise hashing, M >= 2k >= 4, eps < 1/2. 'printed': the stated bound. 'tight': the step
    before it with the exact success rate, which the stated one replaces by a value that it doesn't quite reach."""
    if k < 2 or M < 2 * k or not 0 < eps < 0.5:
        raise ValueError("needs M >= 2k >= 4 and 0 < eps < 1/2")
    if form == "printed":
        return (4 * k / (math.exp(2 / 3) * eps**2 * M)) ** (k / 2)
    p = (2 + eps + eps**2) / (2 * (1 + eps))
    return (k * p / (math.exp(2 / 3) * (1 - p) ** 2 * M)) ** (k / 2)


def gc_eps(M: int, k: int, delta: float = 0.05) -> float:
    """The error that the printed bound gives reliability 1 - delta (not capped at 1/2)."""
    return math.sqrt(4 * k / (math.exp(2 / 3) * M * delta ** (2 / k)))


def gc_min_bits(f0: float, M: int, eps: float) -> float:
    return 1 + math.log2(f0 / (eps * M))


def gc_max_f0(L: int, M: int, eps: float) -> float:
    return 2.0 ** (L - 1) * eps * M


def bits_original(cardinalities: list[int]) -> float:
    """Hash bits of the unmodified method, by the volume of the cuboid."""
    return 3 * sum(math.log2(c) for c in cardinalities)


def bits_modified(f0: float, eps: float, M: int) -> float:
    return gc_min_bits(f0, M, eps)


def _lps_at(M: int, k: int, eps: float, alpha: float) -> float:
    return k ** (k / 2) / (math.exp(k / 3) * M ** (k / 2)) * (alpha ** (k / 2) / (1 - alpha) ** k + 4 ** (k / 2) / (alpha ** (k / 2) * eps**k * (2 ** (k / 2) - 1)))


def lps_delta(M: int, k: int, eps: float) -> float:
    """1 - reliability of level-pruned sampling within eps, minimised over alpha in [4k/M, 1); M >= 8k, k >= 2. The bound is convex enough for a ternary search."""
    if k < 2 or M < 8 * k or eps <= 0:
        raise ValueError("needs k >= 2, M >= 8k, eps > 0")
    a, b = 4 * k / M, 1 - 1e-9
    for _ in range(200):
        c, d = a + (b - a) / 3, b - (b - a) / 3
        a, b = (a, d) if _lps_at(M, k, eps, c) < _lps_at(M, k, eps, d) else (c, b)
    return _lps_at(M, k, eps, (a + b) / 2)


def lps_eps(M: int, k: int, delta: float = 0.05) -> float:
    lo, hi = 1e-6, 1e6
    for _ in range(200):
        mid = math.sqrt(lo * hi)
        lo, hi = (lo, mid) if lps_delta(M, k, mid) < delta else (mid, hi)
    return hi


def lps_eps_short(M: int) -> float:
    return 5 / math.sqrt(M)


def max_level_bound(c: float) -> tuple[float, float]:
    """(relative error, reliability) of the maximum-level counter, c > 2."""
    if c <= 2:
        raise ValueError("c must exceed 2")
    return c - 1, 1 - 2 / c


def curves(spark: SparkSession, ms: list[int] = (16, 64, 128, 256, 2048), ks: list[int] = (2, 3, 4, 8)) -> DataFrame:
    """(curve, k, M, value): standard errors by M, and error bounds 19 times of 20 by M and k where they hold."""
    rows = [(n, None, m, f(m)) for n, f in (("rse_pc", rse_pc), ("rse_ll", rse_ll), ("lps_short", lps_eps_short)) for m in ms]
    rows += [("gc_bound", k, m, gc_eps(m, k)) for k in ks for m in ms if m >= 2 * k]
    rows += [("lps_bound", k, m, e) for k in ks for m in ms if m >= 8 * k and (e := lps_eps(m, k)) < 1e5]  # small M: no error has that reliability
    return spark.createDataFrame(rows, "curve string, k int, M long, value double")
