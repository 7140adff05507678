"""Document quality from preference pairs: a Bradley-Terry model on statistics of the text's surface and on its content, as hashed character trigrams.

Every labelled pair (better, worse) says that one score exceeds another; the score is linear in the statistics, so the
logistic loss on a pair depends on the difference of two rows alone. The raw score is then cut at the quantile that
separates the labels best and mapped, monotonically, so that the cut sits at ``cut`` on a scale of 0 to 1.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .common import labelled_sample

#: Buckets of the hashed trigrams.
GRAMS = 256
SURFACE = (
    "log_bytes", "log_words", "mean_word", "upper", "digits", "blank", "newlines", "letters", "high_bytes", "pipes", "shouts", "marks", "odd_marks",
    "stops", "commas", "repeat_next", "distinct_words", "top_word", "pipe_words", "mark_tailed", "upper_words", "log_repeat", "log_pipes", "log_marks", "log_upper",
)
FEATURES = SURFACE + tuple(f"gram_{i}" for i in range(GRAMS))
#: Penalties of the surface statistics' and of the trigrams' weights.
L2 = np.repeat([1e-3, 3.0], [len(SURFACE), GRAMS])


def grams(raw: bytes) -> np.ndarray:
    """Square roots of the shares of the hashed trigrams of bytes, ASCII letters lower-cased."""
    a = np.frombuffer(raw.lower(), np.uint8).astype(np.uint32)
    if len(a) < 3:
        return np.zeros(GRAMS)
    h = (a[:-2] << np.uint32(16) | a[1:-1] << np.uint32(8) | a[2:]) * np.uint32(0x9E3779B1)
    return np.sqrt(np.bincount(h >> np.uint32(24), minlength=GRAMS) / (len(a) - 2))


def statistics(text: str | None) -> np.ndarray:
    """The features of a whole text; all but the lengths are shares of its bytes, words or trigrams. Null counts as empty."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    n = max(1, len(raw))
    c = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    found = raw.split()
    m = max(1, len(found))
    upper, lower, digits = c[65:91].sum(), c[97:123].sum(), c[48:58].sum()
    odd = c[35] + c[36] + c[37] + c[38] + c[42] + c[43] + c[60] + c[61] + c[62] + c[64] + c[94] + c[95] + c[96] + c[123:127].sum()  # # $ % & * + < = > @ ^ _ ` { | } ~
    marks = c[33:48].sum() + c[58:65].sum() + c[91:97].sum() + c[123:127].sum()
    repeat = sum(map(bytes.__eq__, found, found[1:])) / m
    tally: dict[bytes, int] = {}
    for w in found:
        tally[w] = tally.get(w, 0) + 1
    top = max(tally.values(), default=0) / m
    tailed = sum(not w[-1:].isalnum() and w[-1] < 128 for w in found) / m
    shouted = sum(map(bytes.isupper, found)) / m
    pipes = found.count(b"|") / m
    up = upper / max(1, upper + lower)
    own = np.array([
        np.log1p(len(raw)), np.log1p(len(found)), len(raw) / m if found else 0.0, up, digits / n, c[32] / n, c[10] / n, (upper + lower) / n, c[128:].sum() / n, c[124] / n, c[33] / n, marks / n, odd / n,
        c[46] / n, c[44] / n, repeat, len(tally) / m, top, pipes, tailed, shouted, np.log1p(50 * repeat), np.log1p(50 * c[124] / n), np.log1p(50 * odd / n), np.log1p(20 * up),
    ])
    return np.concatenate([own, grams(raw)])


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    at_cut: float
    slope: float
    cut: float

    def score(self, rows: np.ndarray) -> np.ndarray:
        raw = (np.clip((rows - self.mean) / self.scale, -8, 8) * self.weights).sum(axis=1)  # row by row, so that equal rows score alike in any batch
        x = self.slope * (raw - self.at_cut) + np.log(self.cut / (1 - self.cut))
        return 1.0 / (1.0 + np.exp(-np.clip(x, -500, 500)))


def _pairs(good: np.ndarray, bad: np.ndarray, n_pairs: int, rng: np.random.Generator) -> np.ndarray:
    """Feature differences of preference pairs in which every row of either side takes part as evenly as possible."""
    n = max(n_pairs, len(good), len(bad))
    draw = lambda rows: rows[np.concatenate([rng.permutation(len(rows)) for _ in range(-(-n // len(rows)))])[:n]]
    return draw(good) - draw(bad)


def bradley_terry(diff: np.ndarray, l2: float | np.ndarray = 1e-3, steps: int = 40) -> np.ndarray:
    """The weights with the least mean logistic loss on differences (better minus worse), by Newton steps."""
    w = np.zeros(diff.shape[1])
    for _ in range(steps):
        p = 1.0 / (1.0 + np.exp(np.clip(diff @ w, -500, 500)))
        grad = -(diff * p[:, None]).mean(axis=0) + l2 * w
        hess = (diff * (p * (1 - p))[:, None]).T @ diff / len(diff) + np.diag(np.broadcast_to(l2, len(w)))
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def fit(rows: np.ndarray, y: np.ndarray, cut: float = 0.3, n_pairs: int = 20_000, seed: int = 5) -> QualityModel:
    """rows of statistics with labels 0 or 1. With one label only, or none, all scores are that label's side of the cut (none: 1)."""
    d = len(FEATURES)
    if not len(y) or y.min() == y.max():
        return QualityModel(np.zeros(d), np.ones(d), np.zeros(d), 1.0 if len(y) and y.max() == 0 else -1.0, 3.0, cut)
    mean, scale = rows.mean(axis=0), np.maximum(rows.std(axis=0), 1e-6)
    x = np.clip((rows - mean) / scale, -8, 8)
    w = bradley_terry(_pairs(x[y == 1], x[y == 0], n_pairs, np.random.default_rng(seed)), L2)
    raw = x @ w
    order = np.argsort(raw, kind="stable")
    below = np.cumsum(np.r_[0, y[order] == 0])  # bad rows caught if the lowest i rows are rejected
    lost = np.cumsum(np.r_[0, y[order] == 1])
    right = below / max(1, below[-1]) - lost / max(1, lost[-1])  # Youden's index at each quantile
    best = np.flatnonzero(right >= right.max() - 1e-12)
    i = int(best[len(best) // 2])
    lo, hi = raw[order[max(0, i - 1)]], raw[order[min(len(raw) - 1, i)]]
    at_cut = (lo + hi) / 2
    spread = max(1e-6, float(np.median(np.abs(raw - at_cut))))
    return QualityModel(mean, scale, w, float(at_cut), 3.0 / spread, cut)


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 8000, seed: int = 5, **how) -> QualityModel:
    """docs (doc_id, text), labels (doc_id, quality). ``max_rows``: bound of the labelled rows that the model is fitted on, half
    for each label where there are enough. Null labels and labels without a document are left out."""
    ship(docs.sparkSession)
    sample = labelled_sample(docs, labels, "quality", max_rows, seed).select("label", "text").mapInArrow(_featurise, "label int, x binary").collect()
    got = sorted((bytes(r["x"]), r["label"]) for r in sample)
    x = np.array([np.frombuffer(b, np.float64) for b, _ in got]).reshape(len(got), len(FEATURES))
    return fit(x, np.array([y for _, y in got], np.int64), seed=seed, **how)


def _featurise(batches):
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([statistics(t.as_py()).tobytes() for t in batch.column(1)], pa.binary())], names=["label", "x"])


def rate(docs: DataFrame, model: QualityModel, extra: dict[str, Column] | None = None) -> DataFrame:
    """One row per document: (doc_id, <extra>, score, predicted); predicted is 1 from the model's cut on. Null texts count as
    empty, which are scored like any other; equal texts score alike; repeated rows and null ids pass through; other columns are ignored."""
    ship(docs.sparkSession)
    extra = extra or {}
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(c.alias(n) for n, c in extra.items()), F.col("text").cast("string").alias("input_text"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            x = np.array([statistics(t.as_py()) for t in batch.column(batch.num_columns - 1)]).reshape(batch.num_rows, len(FEATURES))
            s = m.score(x)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(s), pa.array((s >= m.cut).astype(np.int32))], names=[*batch.schema.names[:-1], "score", "predicted"])

    kept = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{kept}, score double, predicted int")
