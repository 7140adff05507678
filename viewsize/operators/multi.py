"""Estimates of many views from one scan, and the one-view entry point."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import MapType

from ..functions.hashing import HashSpec, prehashed
from ..plans.views import ViewSpec, hashed_many
from . import bottomk, counting, levels

METHODS = ("pc", "pc_guarded", "ll", "ac", "linear", "maxlevel", "gc", "gc_printed", "gc_hashkey", "lps")
#: The first pass of level-pruned sampling reads one of so many facts; the second reads all.
PART = 16
_WITH_KEY = frozenset(("gc", "gc_printed", "lps"))


def _diag(df: DataFrame, method: str, M: int, L: int, **cols: str) -> DataFrame:
    made = F.create_map(*[x for k, c in cols.items() for x in (F.lit(k), F.col(c).cast("bigint"))])
    return df.select("view_id", F.lit(method).alias("method"), F.lit(M).cast("bigint").alias("M"), F.lit(L).alias("L"), "seed", "estimate", "branch", made.alias("diag"))


def finish(rows: DataFrame, method: str, M: int, L: int, plan: str = "threshold") -> DataFrame:
    """Hashed rows to (view_id, method, M, L, seed, estimate, branch, diag): diag holds the integers that the estimate follows from."""
    return finish_many(rows, method, [M], L, plan)


def finish_many(rows: DataFrame, method: str, ms: list[int], L: int, plan: str = "threshold", some: DataFrame | None = None) -> DataFrame:
    """finish() for several M. A sample-type state of the largest M holds those of the smaller ones, so the rows are read for it alone. ``some``: see levels.lps_state()."""
    if method in ("gc", "gc_printed", "gc_hashkey"):
        state = bottomk.gc_state(rows, max(ms), L, plan, "hash" if method == "gc_hashkey" else "tuple")
        each = [_diag(bottomk.gc_estimate(state if m == max(ms) else bottomk.gc_merge(state, M=m), m, L, method != "gc_printed"), method, m, L, kept="kept", top="top") for m in ms]
    elif method == "lps":
        state = levels.lps_state(rows, max(ms), L, plan, some)
        each = [_diag(levels.lps_estimate(state if m == max(ms) else levels.lps_merge(state, M=m)), method, m, L, floor="level_floor", kept="kept") for m in ms]
    elif method in ("pc", "pc_guarded"):
        each = [_diag(counting.pc_estimate(counting.pc_state(rows, m, L), m, counting.SWITCH if method == "pc_guarded" else None), method, m, L, a="a", beta="beta") for m in ms]
    elif method in ("ll", "ac", "linear"):
        each = [_diag(getattr(counting, f"{method}_estimate")(counting.ll_state(rows, m, L), m), method, m, L, a="a", beta="beta") for m in ms]
    elif method == "maxlevel":
        each = [_diag(counting.max_level_estimate(counting.max_level_state(rows, L)), method, m, L, a="a") for m in ms]
    else:
        raise ValueError(f"unknown method {method}")
    return reduce(DataFrame.unionByName, each)


def _part(df: DataFrame, views: list[ViewSpec]) -> DataFrame:
    """A PART-th of the facts, by a hash of the columns that views name: enough for a first bound, and hashed in that share of the time."""
    names = sorted({d for v in views for d in v.dims if isinstance(d, str)})
    plain = [n for n in names if not isinstance(df.schema[n].dataType, MapType)]
    return df.where(F.pmod(F.xxhash64(F.lit(PART), *plain), F.lit(PART)) == 0) if plain else df


def estimate_many(df: DataFrame, views: list[ViewSpec], methods: list[str] = ("ac",), M: int | list[int] = 2048, spec: HashSpec = HashSpec(), plan: str = "threshold") -> DataFrame:
    """One row per view, method and M. The scan and the dimension hashes are shared by all views of a method; Spark reuses them over methods where it can."""
    out = None
    for method in methods:
        some = hashed_many(_part(df, list(views)), list(views), spec) if method == "lps" and plan == "threshold" and isinstance(spec.seed, int) else None
        one = finish_many(hashed_many(df, list(views), spec, key=method in _WITH_KEY), method, [M] if isinstance(M, int) else list(M), spec.L, plan, some)
        out = one if out is None else out.unionByName(one)
    return out


def estimate(df: DataFrame, dims: list, method: str = "ac", M: int = 2048, spec: HashSpec = HashSpec(), where: str | None = None, plan: str = "threshold") -> DataFrame:
    """The size of one view: a lazy one-row DataFrame."""
    return estimate_many(df, [ViewSpec("view", tuple(dims), "facts", where)], [method], M, spec, plan)


def estimate_stored(stored: DataFrame, names: list[str], method: str = "ac", M: int = 2048, spec: HashSpec = HashSpec(), plan: str = "threshold") -> DataFrame:
    """The size of a view over dimensions whose hash columns ``h_<dim>`` are stored (persist_hashed, with the same spec): no value is read or hashed again. The
    stored columns stand for the values, so two values of one hash count as one; the tuple's second hash is made of them."""
    y = prehashed(names, spec)
    key = F.xxhash64(*[F.col(f"h_{n}") for n in names])
    rows = stored.select(F.lit("view").alias("view_id"), spec.seed_column().cast("int").alias("seed"), y.alias("y"), *([key.alias("key")] if method in _WITH_KEY else []))
    return finish(rows, method, M, spec.L, plan)
