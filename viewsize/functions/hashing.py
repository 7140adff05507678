"""Hashing of dimension tuples: one keyed random table per dimension, combined by exclusive or.

A table is either a pure expression (the value of a keyed hash is the table's entry) or a stored DataFrame that is joined. Both give
the same hashes, so a stored table can be dropped or rebuilt at any time, and a retried task never draws anew.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

MIN_LONG = -(2**63)
_KEY_SEED = 0x51ED270B
#: A stored table is broadcast up to so many rows; beyond, it is joined by shuffling.
BROADCAST_ROWS = 200_000


@dataclass(frozen=True)
class HashSpec:
    """L: hash bits (32: 0..2^32-1; 64: a signed long whose bits are the hash). mode: 'xx' (fast) or 'md5' (reproducible in other engines).
    mix: 'none' keeps the plain exclusive or, which is three-wise independent only; 'final' passes it through one more hash, which
    breaks its linear structure. seed: an integer, or the name of a column that holds one."""

    L: int = 64
    mode: str = "xx"
    mix: str = "final"
    seed: int | str = 0

    def __post_init__(self):
        if self.L not in (32, 64) or self.mode not in ("xx", "md5") or self.mix not in ("none", "final"):
            raise ValueError(f"unknown hash specification {self}")

    def with_seed(self, seed: int | str) -> "HashSpec":
        return replace(self, seed=seed)

    def seed_column(self) -> Column:
        return F.col(self.seed) if isinstance(self.seed, str) else F.lit(self.seed)

    def independence(self, n_dims: int) -> str:
        """What the plain tables guarantee for the hash of a tuple."""
        return "full" if n_dims == 1 else "3-wise"


def canonical(col: Column, kind: T.DataType) -> Column:
    """A value such that equal groups are equal values: one zero, one NaN, whole numbers as bigint, times as microseconds, dates as days, the rest as text."""
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return col.cast("bigint")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        d = col.cast("double")
        return F.when(F.isnan(d), F.lit(float("nan"))).otherwise(d + F.lit(0.0))
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(col.cast("timestamp"))
    if isinstance(kind, T.DateType):
        return F.unix_date(col).cast("bigint")
    if isinstance(kind, (T.ArrayType, T.StructType)):
        return F.to_json(F.struct(col.alias("v")))
    if isinstance(kind, T.MapType):
        raise ValueError("a map can't be a dimension: it can't be grouped by")
    return col.cast("string")


def _hex(text: Column, L: int) -> Column:
    return F.conv(F.substring(F.md5(text), 1, L // 4), 16, 10 if L == 32 else -10).cast("bigint")


def _cut(h: Column, L: int) -> Column:
    return F.shiftrightunsigned(h, 32) if L == 32 else h


def dim_hash(name: str, value: Column, spec: HashSpec) -> Column:
    """The table entry of a canonical value of one dimension. The name is part of the key, so equal values of two dimensions don't cancel; null has an entry of its own."""
    if spec.mode == "md5":
        seed = spec.seed_column().cast("string")
        return _hex(F.when(value.isNull(), F.concat_ws(":", seed, F.lit(name), F.lit("n"))).otherwise(F.concat_ws(":", seed, F.lit(name), F.lit("v"), value.cast("string"))), spec.L)
    return _cut(F.xxhash64(spec.seed_column().cast("bigint"), F.lit(name), value.isNull().cast("int"), value), spec.L)


def finish(y: Column, spec: HashSpec) -> Column:
    if spec.mix == "none":
        return y
    return _hex(y.cast("string"), spec.L) if spec.mode == "md5" else _cut(F.xxhash64(y), spec.L)


def xor_all(parts: list[Column], spec: HashSpec) -> Column:
    return finish(reduce(lambda a, b: a.bitwiseXOR(b), parts), spec)


def tuple_hash(dims: dict[str, Column], spec: HashSpec) -> Column:
    """dims: name -> canonical value."""
    return xor_all([dim_hash(n, c, spec) for n, c in dims.items()], spec)


def tuple_hash_direct(dims: dict[str, Column], spec: HashSpec) -> Column:
    """The comparator without tables: one hash of the whole tuple."""
    if spec.mode == "md5":
        return _hex(F.concat_ws(":", spec.seed_column().cast("string"), *[F.when(c.isNull(), F.lit("n")).otherwise(c.cast("string")) for c in dims.values()]), spec.L)
    flat = [x for c in dims.values() for x in (c.isNull().cast("int"), c)]
    return _cut(F.xxhash64(spec.seed_column().cast("bigint"), *flat), spec.L)


def order_key(y: Column, L: int) -> Column:
    """A long whose signed order is the hash's unsigned order."""
    return y.bitwiseXOR(F.lit(MIN_LONG)) if L == 64 else y


def unsigned(y: Column, L: int) -> Column:
    """The hash as a double."""
    d = y.cast("double")
    return F.when(y < 0, d + F.lit(float(2**64))).otherwise(d) if L == 64 else d


def tuple_key(dims: dict[str, Column]) -> Column:
    """The tuple as one string that equals another's only if the tuples are equal: lengths go before values."""
    part = lambda c: F.when(c.isNull(), F.lit("n")).otherwise(F.concat(F.length(c.cast("string")).cast("string"), F.lit(":"), c.cast("string")))
    return F.concat_ws("|", *[part(c) for c in dims.values()])


def key_hash(name: str, value: Column) -> Column:
    """One dimension's entry in the second family of tables, which tells apart tuples that share a hash: always 64 bits, and blind to the seed."""
    return F.xxhash64(F.lit(_KEY_SEED), F.lit(name), value.isNull().cast("int"), value)


def key_all(parts: list[Column]) -> Column:
    return F.xxhash64(reduce(lambda a, b: a.bitwiseXOR(b), parts))


# Stored tables.


def build_lookup(df: DataFrame, name: str, value: Column, spec: HashSpec) -> DataFrame:
    """(dim, value_key, h): the table of one dimension for the values that occur."""
    return df.select(value.alias("value_key")).distinct().select(F.lit(name).alias("dim"), "value_key", dim_hash(name, F.col("value_key"), spec).alias("h"))


def with_lookup(df: DataFrame, dims: dict[str, Column], tables: dict[str, DataFrame], spec: HashSpec, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """df with a column ``h_<dim>`` for each dimension, from the stored tables (broadcast where their counted rows are few); a value that a table lacks is hashed on the fly."""
    for name, value in dims.items():
        table = tables[name].select(F.col("value_key").alias("lookup_key"), F.col("h").alias("lookup_h"))
        table = F.broadcast(table) if table.limit(broadcast_rows + 1).count() <= broadcast_rows else table
        df = df.join(table, value.eqNullSafe(F.col("lookup_key")), "left")
        df = df.withColumn(f"h_{name}", F.coalesce("lookup_h", dim_hash(name, value, spec))).drop("lookup_key", "lookup_h")
    return df


def missing_values(df: DataFrame, name: str, value: Column, table: DataFrame, spec: HashSpec) -> DataFrame:
    """(dim, value_key, h) of the values in df that a stored table lacks, by an anti join: what is to be added to it."""
    fresh = build_lookup(df, name, value, spec)
    old = table.select(F.col("value_key").alias("old_key"))
    return fresh.join(old, fresh["value_key"].eqNullSafe(old["old_key"]), "left_anti")


def with_array_lookup(df: DataFrame, dims: dict[str, Column], sizes: dict[str, int], spec: HashSpec) -> DataFrame:
    """df with ``h_<dim>`` from tables that are plain arrays, for whole-number dimensions of values 0 to size - 1: no join, an index instead. Other values are hashed on the fly."""
    for name, value in dims.items():
        entries = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(sizes[name] - 1).cast("bigint")), lambda v: dim_hash(name, v, spec))
        table = F.lit(None) if sizes[name] < 1 else F.try_element_at(entries, (value + 1).cast("int"))
        df = df.withColumn(f"h_{name}", F.coalesce(F.when(value.between(0, sizes[name] - 1), table), dim_hash(name, value, spec)))
    return df


def persist_hashed(df: DataFrame, dims: dict[str, Column], spec: HashSpec, path: str, sort: bool = False) -> DataFrame:
    """Write the dimensions' hash columns (``h_<dim>``) for later estimates; sorted by their combination, row groups can be skipped by threshold plans."""
    out = df.select(*[dim_hash(n, c, spec).alias(f"h_{n}") for n, c in dims.items()])
    if sort:
        key = order_key(xor_all([F.col(f"h_{n}") for n in dims], spec), spec.L)
        out = out.withColumn("y_order", key).repartitionByRange("y_order").sortWithinPartitions("y_order")
    out.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.parquet(path)


def prehashed(names: list[str], spec: HashSpec) -> Column:
    """The tuple hash over stored hash columns."""
    return xor_all([F.col(f"h_{n}") for n in names], spec)


def hash_uniformity(hashes: DataFrame, bins: int = 64, col: str = "y") -> DataFrame:
    """(n, bins, chi2) of distinct hash values over equal bins."""
    counts = hashes.select(col).distinct().groupBy(F.pmod(F.col(col), F.lit(bins)).alias("bin")).agg(F.count("*").alias("c"))
    total = counts.agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.col("c")).alias("s2"))
    return total.select("n", F.lit(bins).alias("bins"), (F.col("s2") * bins / F.col("n") - F.col("n")).alias("chi2"))
