"""Reading facts: Parquet and other formats, the star of the given tables, generated keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_delimited(spark: SparkSession, path: str, sep: str, schema: StructType | str, header: bool = False) -> DataFrame:
    """Comma-, pipe- or otherwise separated text; the schema is given, never inferred. A trailing separator gives a column that isn't in the schema and is dropped."""
    return spark.read.csv(path, schema=schema, sep=sep, header=header, mode="PERMISSIVE", enforceSchema=True)


def read(spark: SparkSession, path: str, format: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """Any built-in format (parquet, orc, json, csv), partition folders included."""
    reader = spark.read.format(format).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


#: Where a column of the star comes from.
_OWNER = {"l": "lineitem", "o": "orders", "c": "customer", "s": "supplier", "p": "part"}
_DERIVED = {"sy": "lineitem", "sm": "lineitem", "sd": "lineitem", "oy": "orders", "om": "orders", "od": "orders", "cr": "customer_nation", "sr": "supplier_nation"}


def tables_of(columns: list[str]) -> set[str]:
    """The tables that these columns of the star need."""
    return {_DERIVED.get(c) or _OWNER[c.split("_")[0]] for c in columns}


def star(spark: SparkSession, sf_dir: str, columns: list[str] | None = None) -> DataFrame:
    """lineitem with the dimensions around it. Only the tables that the wanted columns need are joined: every foreign key is total and
    unique on its far side, so a join that adds no wanted column would change nothing. No join is forced; sizes decide."""
    need = tables_of(columns) if columns else {"lineitem", "orders", "customer", "supplier", "part", "customer_nation", "supplier_nation"}
    t = lambda n: load(spark, sf_dir, n)
    df = t("lineitem").withColumns({"sy": F.year("l_shipdate"), "sm": F.month("l_shipdate"), "sd": F.to_date("l_shipdate")})
    if need & {"orders", "customer", "customer_nation"}:
        o = t("orders").withColumns({"oy": F.year("o_orderdate"), "om": F.month("o_orderdate"), "od": F.to_date("o_orderdate")})
        df = df.join(o, df.l_orderkey == o.o_orderkey)
    if need & {"customer", "customer_nation"}:
        df = df.join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    if "customer_nation" in need:
        df = df.join(t("nation").select(F.col("n_nationkey").alias("cn"), F.col("n_regionkey").alias("cr")), F.col("c_nationkey") == F.col("cn")).drop("cn")
    if need & {"supplier", "supplier_nation"}:
        df = df.join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    if "supplier_nation" in need:
        df = df.join(t("nation").select(F.col("n_nationkey").alias("sn"), F.col("n_regionkey").alias("sr")), F.col("s_nationkey") == F.col("sn")).drop("sn")
    if "part" in need:
        df = df.join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    return df.select(*columns) if columns else df


def event_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    ts = F.col("ts").cast("timestamp_ntz")
    return load(spark, sf_dir, "events").withColumns({"hour": F.date_trunc("hour", ts.cast("timestamp")), "day": F.to_date(ts), "v": F.floor("value"), "k": F.get_json_object("props", "$.k").cast("int")})


def skewed(column: str, cardinality: int) -> F.Column:
    """A skewed stand-in for a near-uniform key of values 1..cardinality."""
    return F.floor(cardinality * F.pow(F.col(column) / F.lit(float(cardinality)), F.lit(3.0))).cast("bigint")


def synthetic_keys(spark: SparkSession, n: int, dims: int = 1, repeat: int = 1) -> DataFrame:
    """n distinct tuples of ``dims`` columns k0.., each ``repeat`` times; the first column is the number itself, the others are digits of it."""
    base = spark.range(n * repeat).select((F.col("id") % n).alias("k0"))
    return base.select("k0", *[(F.shiftright("k0", 4 * i) % 97).alias(f"k{i}") for i in range(1, dims)])
