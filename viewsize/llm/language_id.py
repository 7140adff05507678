"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Document frequencies come from every labelled row of the training folds, in one pass that adds up arrays of fixed size; the
model is fitted with follow-the-regularised-leader and elastic-net penalties on a bounded, language-balanced sample of them
(``max_rows``) and its scores are tempered on a fifth of that sample which the weights never saw.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .common import keyed_order, keyed_share
from .ftrl import FtrlSoftmax, fit_temperature, softmax

BITS = 15
ORDERS = (1, 2, 3)
UNDETERMINED = "und"
_TABLE: list[np.ndarray] = []


def _letters() -> np.ndarray:
    """Code point -> its lower-case code point if it is a letter, else 0; built once in a worker."""
    if not _TABLE:
        table = np.zeros(0x110000, np.uint32)
        for c in range(0x110000):
            ch = chr(c)
            if ch.isalpha():
                table[c] = ord(ch.lower()[0])
        _TABLE.append(table)
    return _TABLE[0]


def ngrams(text: str | None, bits: int = BITS, orders: tuple[int, ...] = ORDERS) -> tuple[np.ndarray, np.ndarray] | None:
    """(buckets, counts) of a whole text's n-grams: letters lower-cased, every other run one blank. None without a letter."""
    points = np.frombuffer((text or "").encode("utf-32-le", "surrogatepass"), np.uint32)
    folded = _letters()[points]
    if not folded.any():
        return None
    keep = np.ones(len(folded), bool)
    keep[1:] = (folded[1:] != 0) | (folded[:-1] != 0)
    s = np.zeros(keep.sum() + 2, np.uint32)
    s[1:-1] = folded[keep]
    counts = np.zeros(1 << bits, np.int64)
    h = np.zeros(len(s), np.uint32)
    for n in range(1, max(orders) + 1):
        h = (h[: len(s) - n + 1] ^ s[n - 1 :]) * np.uint32(0x9E3779B1)
        h ^= h >> np.uint32(15)
        if n in orders:
            counts += np.bincount((h * np.uint32(2 * n + 0x85EBCA6B)) >> np.uint32(32 - bits), minlength=1 << bits)
    at = np.flatnonzero(counts)
    return at, counts[at]


def _document_frequencies(batches):
    df, rows = np.zeros(1 << BITS, np.int64), 0
    for batch in batches:
        for text in batch.column(0):
            if (found := ngrams(text.as_py())) is not None:
                df[found[0]] += 1
                rows += 1
    at = np.flatnonzero(df)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(df[at], rows))], names=["bucket", "df"])


def _featurise(batches):
    for batch in batches:
        found = [ngrams(t.as_py()) or (np.empty(0, np.int64),) * 2 for t in batch.column(1)]
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array([a.astype(np.uint16).tobytes() for a, _ in found], pa.binary()), pa.array([c.astype(np.uint32).tobytes() for _, c in found], pa.binary())],
            names=["lang", "buckets", "counts"],
        )


@dataclass
class LanguageModel:
    langs: list[str]
    idf: np.ndarray
    weights: np.ndarray
    intercept: np.ndarray
    temperature: float

    def vector(self, at: np.ndarray, counts: np.ndarray) -> np.ndarray:
        x = (1.0 + np.log(counts)) * self.idf[at]
        return x / max(1e-12, float(np.sqrt(x @ x)))

    def predict(self, text: str | None) -> tuple[str, float]:
        found = ngrams(text) if self.langs else None
        if found is None:
            return UNDETERMINED, 0.0
        p = softmax((self.vector(*found) @ self.weights[found[0]] + self.intercept) / self.temperature)
        return self.langs[int(p.argmax())], float(min(1.0, p.max()))


def train(labelled: DataFrame, max_rows: int = 3000, seed: int = 7, **ftrl) -> LanguageModel:
    """labelled (doc_id, text, lang). ``max_rows``: bound of the rows that the weights are fitted on, shared equally by the
    languages; every row counts in the document frequencies, and every language is learned, of one row at least if its draw allows. Null languages are
    left out; no rows give a model that knows nothing."""
    ship(labelled.sparkSession)
    rows = labelled.where("lang is not null").select(F.col("doc_id").cast("string").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    per_lang = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    df = {r["bucket"]: r["df"] for r in rows.select("text").mapInArrow(_document_frequencies, "bucket long, df long").groupBy("bucket").agg(F.sum("df").alias("df")).collect()}
    idf = np.zeros(1 << BITS, np.float64)
    total = df.pop(-1, 0)
    for b, n in df.items():
        idf[b] = np.log((1 + total) / (1 + n)) + 1.0
    langs = sorted(per_lang)
    if not langs:
        return LanguageModel([], idf, np.zeros((1 << BITS, 0)), np.zeros(0), 1.0)
    share = max(1, max_rows // len(langs))
    # One row a language, as many as the model has classes.
    rates = labelled.sparkSession.createDataFrame([(lang, min(1.0, share / n)) for lang, n in per_lang.items()], "lang string, rate double")
    drawn = rows.withColumn("o", keyed_order(seed, "doc_id")).join(F.broadcast(rates), "lang").where(keyed_share("o") < F.col("rate"))
    most = 2 * max(max_rows, len(langs))
    first = [r["o"] for r in drawn.select("o").orderBy("o").limit(most + 1).collect()]
    if len(first) > most:  # repeated ids: what comes first by the hash is kept
        drawn = drawn.where(F.col("o") <= first[-2]).orderBy("o", F.xxhash64("text")).limit(most)
    sample = drawn.select("lang", "text").mapInArrow(_featurise, "lang string, buckets binary, counts binary").collect()
    model = LanguageModel(langs, idf, np.zeros((1 << BITS, len(langs))), np.zeros(len(langs)), 1.0)
    code = {lang: i for i, lang in enumerate(langs)}
    data, y = [], []
    for r in sorted(((r["lang"], bytes(r["buckets"]), bytes(r["counts"])) for r in sample if len(r["buckets"]))):
        at = np.frombuffer(r[1], np.uint16).astype(np.int32)
        data.append((at, model.vector(at, np.frombuffer(r[2], np.uint32).astype(np.float64)).astype(np.float32)))
        y.append(code[r[0]])
    y, held = np.array(y, np.int64), np.arange(len(y)) % 5 == 4
    fit = FtrlSoftmax(1 << BITS, len(langs), **ftrl).fit([d for d, h in zip(data, held) if not h], y[~held], seed=seed)
    model.weights, model.intercept = fit.weights()
    if held.any():
        model.temperature = fit_temperature(np.array([v @ model.weights[at] + model.intercept for (at, v), h in zip(data, held) if h]), y[held])
    return model


def identify(docs: DataFrame, model: LanguageModel, extra: dict[str, Column] | None = None) -> DataFrame:
    """One row per document: (doc_id, <extra>, lang_pred, score). ``score`` is the tempered probability of the predicted
    language. Null, empty and letterless texts: 'und' with score 0. Ties go to the language first in code-point order. Equal texts
    get equal results; repeated rows and null ids pass through; other columns of docs are ignored."""
    ship(docs.sparkSession)
    extra = extra or {}
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(c.alias(n) for n, c in extra.items()), F.col("text").cast("string").alias("input_text"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            found = [m.predict(t.as_py()) for t in batch.column(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], pa.array([a for a, _ in found], pa.string()), pa.array([b for _, b in found], pa.float64())],
                names=[*batch.schema.names[:-1], "lang_pred", "score"],
            )

    kept = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{kept}, lang_pred string, score double")
