"""A training-data pipeline of five stages over the documents table.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes it as Parquet and the next stage reads that. All but
the last return the columns of documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from viewsize.llm import language_id, toxicity
from viewsize.llm.common import load, settle
from viewsize.llm.mixing import mix_documents
from viewsize.llm.near_dup import drop_near_duplicates
from viewsize.llm.packing import pack_documents
from viewsize.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: A document whose language is predicted with less than this calibrated probability is rejected, as is one without a letter.
LEAST_LANGUAGE_SCORE = 0.5


def _own(docs: DataFrame) -> dict:
    return {c: F.col(c) for c in COLUMNS if c != "doc_id"}


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    found = language_id.identify(docs, language_id.train(docs), _own(docs))
    return found.where((F.col("lang_pred") != language_id.UNDETERMINED) & (F.col("score") >= LEAST_LANGUAGE_SCORE)).select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    model = toxicity.train(docs, load(spark, sf_dir, "labels"))
    return toxicity.flag(docs, model, _own(docs)).where("toxic = 0").select(*COLUMNS)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_near_duplicates(docs, k=5, num=80, den=100).select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix_documents(docs).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs)


STAGES = [
    ("language_id", identify_language),
    ("toxicity", drop_toxic),
    ("near_dedup", drop_copies),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: No SQL: the stages hold trained models, signatures and seeded draws; tests/llm checks them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = settle(stage(spark, docs, sf_dir), name)
    return docs
