"""Helpers shared by the corpus operators: folds, scratch tables, bounded samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import clean, scratch, settle, ship  # noqa: F401

#: A word of a text: a run of anything but space, tab, line feed, vertical tab, form feed and carriage return.
WORD = r"[^\x20\x09-\x0D]+"


def id_crc(col: str = "doc_id") -> Column:
    """crc32 of an id written as text; the folds of the labelled operators are remainders of it (null id: of '')."""
    return F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary"))


def in_fold(col: str, parts: int, part: int) -> Column:
    return (id_crc(col) % parts) == part


def words(col: str | Column) -> Column:
    """Number of words of a text (null: 0)."""
    return F.coalesce(F.regexp_count(F.col(col) if isinstance(col, str) else col, F.lit(WORD)), F.lit(0)).cast("long")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def keyed_order(seed: int, col: str) -> Column:
    """A keyed hash of a column, the order in which bounded samples are drawn."""
    return F.xxhash64(F.lit(seed), col)


def keyed_share(order: str) -> Column:
    """Such a hash as a number from 0 to 1."""
    return F.col(order).bitwiseAND(F.lit((1 << 53) - 1)) / float(1 << 53)


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, max_rows: int, seed: int, *more: str) -> DataFrame:
    """(doc_id, label int, text, more columns of labels) of at most about ``max_rows`` labelled documents, half for each label 0 and 1 where there are
    enough, drawn by a keyed hash of the id, the same whenever it runs. The drawn labels are bounded, so they are what is broadcast; texts are never shuffled."""
    rows = labels.where(F.col(label).isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label"), *more)
    n = {r["label"]: r["count"] for r in rows.groupBy("label").count().collect()}
    rate = [min(1.0, max_rows / 2 / n.get(i, 1)) for i in (0, 1)]
    drawn = rows.withColumn("o", keyed_order(seed, "doc_id")).where(keyed_share("o") < F.when(F.col("label") == 0, F.lit(rate[0])).otherwise(F.lit(rate[1])))
    drawn = drawn.orderBy("o", "doc_id", "label").limit(2 * max_rows).select("doc_id", "label", *more)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.join(F.broadcast(drawn), "doc_id").select("doc_id", "label", "text", *more)
