"""Views: named groupings of a fact table, the catalogue of the given tables, and their hashed rows."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import HashSpec, canonical, dim_hash, key_all, key_hash, xor_all
from ..sources import data


@dataclass(frozen=True)
class ViewSpec:
    """dims: column names, or (name, SQL expression) pairs for derived ones. where: an SQL predicate on the facts."""

    name: str
    dims: tuple
    table: str = "star"
    where: str | None = None

    @property
    def names(self) -> list[str]:
        return [d if isinstance(d, str) else d[0] for d in self.dims]

    def raw(self) -> dict[str, Column]:
        return {d: F.col(d) for d in self.dims if isinstance(d, str)} | {d[0]: F.expr(d[1]) for d in self.dims if not isinstance(d, str)}

    def bind(self, df: DataFrame) -> DataFrame:
        """The facts, filtered and projected to canonical dimension columns. Unknown columns and maps raise here, not in a task."""
        if not self.dims:
            raise ValueError(f"{self.name} has no dimension")
        df = df.where(self.where) if self.where else df
        out = df.select(*[c.alias(n) for n, c in self.raw().items()])
        return out.select(*[canonical(F.col(f"`{f.name}`"), f.dataType).alias(f.name) for f in out.schema.fields])


_C = """C01 l_returnflag,l_linestatus,o_orderstatus,o_orderpriority
C02 l_returnflag,l_linestatus,l_linenumber,c_mktsegment
C03 sy,sm,l_returnflag,l_linestatus
C04 cr,oy,l_tax,l_linestatus
C05 c_mktsegment,p_type,sr,l_linenumber
C06 c_nationkey,c_mktsegment,o_orderpriority,l_returnflag
C07 oy,om,o_orderpriority,c_mktsegment
C08 cr,sr,sy,c_mktsegment,o_orderpriority
C09 o_orderstatus,om,s_nationkey,l_discount
C10 c_nationkey,s_nationkey,sy,l_returnflag
C11 p_type,p_brand,p_size,l_linestatus
C12 l_quantity,l_discount,l_tax,l_returnflag
C13 p_brand,l_tax,l_discount,l_linenumber
C14 p_size,p_brand,l_returnflag,c_mktsegment
C15 l_linenumber,o_orderpriority,sm,p_size
C16 oy,om,sy,sm,c_mktsegment
C17 l_quantity,sm,p_brand,o_orderpriority
C18 l_quantity,l_discount,p_size,c_nationkey
C19 c_nationkey,s_nationkey,p_brand,p_size
C20 l_quantity,l_discount,l_tax,p_size,c_nationkey,s_nationkey
D1 l_suppkey
D2 sd
D3 l_partkey
D4 l_orderkey
D5 l_orderkey,l_linenumber
D6 o_custkey,l_suppkey
D7 l_partkey,l_suppkey,l_quantity,l_returnflag
D8 l_partkey,l_quantity,l_discount,sm,c_nationkey
D9 o_custkey,l_partkey,l_suppkey"""
_V = """V1 user_id
V2 event_type
V3 user_id,event_type
V4 user_id,hour
V5 event_type,hour
V6 user_id,event_type,day,v"""

CATALOGUE: dict[str, ViewSpec] = {}
for _table, _text in (("star", _C), ("events", _V)):
    for _line in _text.splitlines():
        _name, _dims = _line.split()
        CATALOGUE[_name] = ViewSpec(_name, tuple(_dims.split(",")), _table)
CENSUS = [v for n, v in CATALOGUE.items() if n[0] == "C"]
SYNTHETIC = [CATALOGUE[f"D{i}"] for i in range(1, 9)]


def facts(spark: SparkSession, sf_dir: str, *views: ViewSpec, extra: tuple[str, ...] = ()) -> DataFrame:
    """The fact table of views of one table, with just the columns that they need."""
    table = {v.table for v in views}
    if len(table) != 1:
        raise ValueError("views of one table are asked for")
    if table == {"events"}:
        return data.event_facts(spark, sf_dir)
    if table == {"star"}:
        plain = all(isinstance(d, str) for v in views for d in v.dims) and not any(v.where for v in views)
        return data.star(spark, sf_dir, list(dict.fromkeys([d for v in views for d in v.dims] + list(extra))) if plain else None)
    return data.load(spark, sf_dir, table.pop())


def tuples(df: DataFrame, view: ViewSpec) -> DataFrame:
    """The distinct tuples of a view: by exact grouping, for ground truth and for protocols that hash one view with many seeds."""
    return view.bind(df).distinct()


def hashed(df: DataFrame, view: ViewSpec, spec: HashSpec, key: bool = False, bound: bool = False) -> DataFrame:
    """(view_id, seed, y[, key]) for each fact: no shuffle, no Python. With a seed column in spec, df must hold it; ``bound``: df is bound already. The key,
    a second hash of 64 bits that no seed changes, stands for the tuple: two tuples of one hash are told apart but for a chance of 2^-64."""
    seed = spec.seed_column().cast("int").alias("seed")
    if bound:
        cols = {n: F.col(n) for n in view.names}
        src = df
    else:
        keep = [spec.seed] if isinstance(spec.seed, str) else []
        src = (df.where(view.where) if view.where else df).select(*[c.alias(n) for n, c in view.raw().items()], *keep)
        cols = {f.name: canonical(F.col(f"`{f.name}`"), f.dataType) for f in src.schema.fields if f.name not in keep}
    y = xor_all([dim_hash(n, c, spec) for n, c in cols.items()], spec)
    return src.select(F.lit(view.name).alias("view_id"), seed, y.alias("y"), *([key_all([key_hash(n, c) for n, c in cols.items()]).alias("key")] if key else []))


def hashed_many(df: DataFrame, views: list[ViewSpec], spec: HashSpec, key: bool = False) -> DataFrame:
    """(view_id, seed, y[, key]) of several views in one scan: each dimension is hashed once, a view combines what it needs, and one explode
    makes a row for each view. Views must agree on their predicate."""
    wheres = {v.where for v in views}
    if len(wheres) > 1:
        raise ValueError("views with different predicates need a scan each")
    where = wheres.pop()
    raw = {n: c for v in views for n, c in v.raw().items()}
    keep = [spec.seed] if isinstance(spec.seed, str) else []
    src = (df.where(where) if where else df).select(*[c.alias(n) for n, c in raw.items()], *keep)
    cols = {f.name: canonical(F.col(f"`{f.name}`"), f.dataType) for f in src.schema.fields if f.name not in keep}
    hashes = {f"h_{n}": dim_hash(n, c, spec) for n, c in cols.items()} | ({f"k_{n}": key_hash(n, c) for n, c in cols.items()} if key else {})
    once = src.select(*[c.alias(n) for n, c in hashes.items()], spec.seed_column().cast("int").alias("seed"))
    one = lambda v: F.struct(
        F.lit(v.name).alias("view_id"),
        xor_all([F.col(f"h_{n}") for n in v.names], spec).alias("y"),
        *([key_all([F.col(f"k_{n}") for n in v.names]).alias("key")] if key else []),
    )
    return once.select("seed", F.explode(F.array(*[one(v) for v in views])).alias("x")).select("x.view_id", "seed", "x.y", *(["x.key"] if key else []))


def sampled_tuples(df: DataFrame, view: ViewSpec, spec: HashSpec, state: DataFrame) -> DataFrame:
    """The tuples that a state of Generalized Counting or level-pruned sampling holds, as columns, beside their (seed, key): the facts' distinct tuples, semi-joined
    with the state's at most M keys."""
    own = tuples(df, view)
    cols = {n: F.col(n) for n in view.names}
    keyed = own.withColumn("key", key_all([key_hash(n, c) for n, c in cols.items()]))
    return keyed.join(state.where(F.col("view_id") == view.name).select("seed", "key"), "key")
