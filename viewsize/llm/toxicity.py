"""Toxicity by a classifier chain of linear models on words and word stems.

The chain's categories are columns of the labels table, predicted in order; each later model also sees the probabilities of the earlier ones. In
training these are out-of-fold predictions (folds by a hash of the text, so copies never straddle two folds), at prediction time those of the models
fitted on everything. Terms are chosen anew within each fold's training rows, so that nothing of a row's own label is in its
out-of-fold prediction. The last category's probability is cut where the out-of-fold F1 is best.

What the driver gathers is bounded by parameters: the chosen terms, and for each sampled row its counts of these.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .common import labelled_sample

_WORDS = re.compile(r"[^\W\d_]+")
STEMS = (4, 5)
#: (name, column of the labels table, the label that means it): what a chain predicts, in this order; the last is the answer.
CATEGORIES = (("junk", "quality", 0), ("toxic", "toxic", 1))
FOLDS = 5
#: Columns of a row after its terms: hits of the telling terms, as a logarithm, per hundred words and at all; shares of capitals and of marks.
EXTRAS = 5


def tokens(text: str | None) -> tuple[Counter, int]:
    """Counts of the lower-cased words of a whole text and of the longer words' first letters (marked by a trailing *), and the number of words."""
    found = _WORDS.findall((text or "").lower())
    tally = Counter(found)
    for w, n in list(tally.items()):
        for k in STEMS:
            if len(w) > k:
                tally[w[:k] + "*"] += n
    return tally, len(found)


def surface(text: str | None) -> tuple[float, float]:
    """Shares of ASCII capitals among ASCII letters and of ASCII marks among bytes."""
    c = np.bincount(np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8), minlength=256)
    capitals, small = int(c[65:91].sum()), int(c[97:123].sum())
    marks = int(c[33:48].sum() + c[58:65].sum() + c[91:97].sum() + c[123:127].sum())
    return capitals / max(1, capitals + small), marks / max(1, int(c.sum()))


def fold_of(text: str | None, folds: int = FOLDS) -> int:
    return xxhash.xxh32_intdigest((text or "").encode("utf-8", "surrogatepass")) % folds


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -500, 500)))


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 0.3, steps: int = 30) -> np.ndarray:
    """Weights (intercept last) of an L2-penalised logistic regression, by Newton steps with halving. One label only, or no rows: an intercept for it (none: 0)."""
    w = np.zeros(x.shape[1] + 1)
    if not len(y) or y.min() == y.max():
        w[-1] = 20.0 if len(y) and y.max() == 1 else -20.0
        return w
    x = np.hstack([x, np.ones((len(x), 1))])
    pen = np.full(x.shape[1], l2)
    pen[-1] = 1e-4

    def loss(w: np.ndarray) -> float:
        s = x @ w
        return float(np.logaddexp(0, np.where(y == 1, -s, s)).sum() + 0.5 * (pen * w * w).sum())

    now = loss(w)
    for _ in range(steps):
        p = _sigmoid(x @ w)
        step = np.linalg.solve((x * (p * (1 - p) + 1e-9)[:, None]).T @ x + np.diag(pen), x.T @ (p - y) + pen * w)
        size = 1.0
        while size > 1e-4 and loss(w - size * step) > now:
            size /= 2
        w = w - size * step
        before, now = now, loss(w)
        if before - now < 1e-7 * max(1.0, before):
            break
    return w


def choose(counts: dict[str, tuple[int, int]], n1: int, n0: int, keep: int, support: int, least: float) -> tuple[tuple[str, ...], frozenset]:
    """counts: term -> (rows with the label, rows without it) that hold it, of n1 and n0 rows. The ``keep`` terms most tied to the label, by the likelihood-ratio
    statistic, of those in ``support`` rows with the label at least and of a statistic of ``least`` at least; and those of them that point to it nearly always."""
    if not n1 or not n0:
        return (), frozenset()

    def tie(a: int, b: int) -> float:
        def part(seen: float, rows: float, rate: float) -> float:
            return sum(x * np.log(x / e) for x, e in ((seen, rows * rate), (rows - seen, rows * (1 - rate))) if x > 0)

        rate = (a + b) / (n1 + n0)
        return 2.0 * (part(a, n1, rate) + part(b, n0, rate))

    strong = {t: g for t, (a, b) in counts.items() if a >= support and (g := tie(a, b)) >= least}
    ranked = tuple(sorted(strong, key=lambda t: (-strong[t], t))[:keep])
    return ranked, frozenset(t for t in ranked if counts[t][0] / n1 > 20 * counts[t][1] / n0)


@dataclass
class Link:
    """One category's model: its terms, those of them that point to the category nearly always, and its weights (terms, extras, earlier categories, intercept)."""

    name: str
    terms: dict[str, int]
    telling: frozenset
    weights: np.ndarray

    def row(self, tally, n_words: int, shares: tuple[float, float]) -> np.ndarray:
        x, hits = np.zeros(len(self.terms) + EXTRAS), 0
        for t in self.terms.keys() & tally.keys() if len(self.terms) < len(tally) else (t for t in tally if t in self.terms):
            n = tally[t]
            x[self.terms[t]] = np.log1p(n)
            if t in self.telling:
                hits = max(hits, n) if t.endswith("*") else hits + n
        x[len(self.terms) :] = np.log1p(hits), min(1.0, 100.0 * hits / max(1, n_words)), float(hits > 0), *shares
        return x


@dataclass
class ChainModel:
    links: list[Link]
    cut: float

    @property
    def categories(self) -> tuple[str, ...]:
        return tuple(k.name for k in self.links)

    def predict(self, rows: list[tuple]) -> np.ndarray:
        """rows of (counts of terms, words, shares) -> probabilities, a column for each category."""
        out = np.zeros((len(rows), len(self.links)))
        for i, link in enumerate(self.links):
            x = np.array([link.row(*r) for r in rows]).reshape(len(rows), len(link.terms) + EXTRAS)
            out[:, i] = _sigmoid((np.hstack([x, out[:, :i]]) * link.weights[:-1]).sum(axis=1) + link.weights[-1])  # row by row, so that equal rows score alike in any batch
        return out


def fit(rows: list[tuple], fold: np.ndarray, targets: list[tuple[str, np.ndarray]], chosen: dict[tuple[int, int], tuple], l2: float = 0.3) -> ChainModel:
    """rows of (counts, words, shares) with their folds; targets of 0, 1 or -1 (unknown) by category, in order; chosen: (category, fold that is left out, or -1) ->
    (terms, telling ones)."""
    links, earlier = [], np.zeros((len(rows), 0))
    out, y = np.zeros(len(rows)), np.zeros(len(rows), np.int64)
    for c, (name, y) in enumerate(targets):
        known, out = y >= 0, np.zeros(len(rows))

        def link(f: int) -> Link:
            terms, telling = chosen[c, f]
            return Link(name, {t: i for i, t in enumerate(terms)}, telling, np.zeros(0))

        for f in sorted(set(fold.tolist())):
            one, test = link(f), fold == f
            x = np.hstack([np.array([one.row(*r) for r in rows]), earlier])
            w = logistic(x[known & ~test], y[known & ~test], l2)
            out[test] = _sigmoid(x[test] @ w[:-1] + w[-1])
        last = link(-1)
        x = np.hstack([np.array([last.row(*r) for r in rows]).reshape(len(rows), len(last.terms) + EXTRAS), earlier])
        last.weights = logistic(x[known], y[known], l2)
        links.append(last)
        earlier = np.hstack([earlier, out[:, None]])
    out, y = out[y >= 0], y[y >= 0]
    cut = 0.5
    if len(y) and y.min() != y.max():
        order = np.argsort(-out, kind="stable")
        right = np.cumsum(y[order])
        best = int((2 * right / (np.arange(1, len(y) + 1) + y.sum())).argmax())
        after = out[order[best + 1]] if best + 1 < len(y) else 0.0
        cut = float((out[order[best]] + after) / 2)
    return ChainModel(links, cut)


def _counter(n_categories: int, folds: int):
    """Rows (labels, text) to (term, counts): how many rows of each category, label and fold hold the term; the empty term stands for all rows."""
    width = n_categories * 2 * folds

    def flush(held: dict[str, np.ndarray]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array([v.tolist() for v in held.values()], pa.list_(pa.int64()))], names=["term", "c"])

    def run(batches):
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            for labels, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = text.as_py()
                at = [(c * 2 + v) * folds + fold_of(text, folds) for c, v in enumerate(labels) if v >= 0]
                for t in ["", *tokens(text)[0]]:
                    if (own := held.get(t)) is None:
                        own = held[t] = np.zeros(width, np.int64)
                    own[at] += 1
                if len(held) > 200_000:
                    yield flush(held)
                    held = {}
        yield flush(held)

    return run


def _profiler(terms: frozenset, folds: int):
    def run(batches):
        for batch in batches:
            rows = []
            for text in batch.column(1):
                text = text.as_py()
                tally, n = tokens(text)
                own = sorted(t for t in tally if t in terms)
                rows.append((own, [tally[t] for t in own], n, *surface(text), fold_of(text, folds)))
            cols = list(zip(*rows)) or [()] * 6
            kinds = (pa.list_(pa.string()), pa.list_(pa.int64()), pa.int64(), pa.float64(), pa.float64(), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(list(c), k) for c, k in zip(cols, kinds))], names=["labels", "terms", "counts", "n", "capitals", "marks", "fold"])

    return run


def train(
    docs: DataFrame, labels: DataFrame, max_rows: int = 4000, seed: int = 11, keep: int = 300, support: int = 3, least: float = 15.0, folds: int = FOLDS, l2: float = 0.3, categories: tuple = CATEGORIES
) -> ChainModel:
    """docs (doc_id, text), labels (doc_id, and a column for each category). ``max_rows``: bound of the labelled rows that the chain is fitted on, half of them with
    the last category where there are enough; ``keep``, ``support`` and ``least``: bounds of a category's terms, as in choose(). Unknown labels (null, or
    anything but 0 and 1) leave a row out of that category alone; rows without the last one, and labels without a document, are left out."""
    ship(docs.sparkSession)
    wanted = F.array(*[F.coalesce(F.when(F.col(col).isin(0, 1), (F.col(col) == value).cast("int")), F.lit(-1)) for _, col, value in categories])
    last, value = categories[-1][1:]
    rows = labelled_sample(docs, labels.select("doc_id", last, wanted.alias("wanted")), last, max_rows, seed, "wanted").select("wanted", "text")
    width = len(categories) * 2 * folds
    found = rows.mapInArrow(_counter(len(categories), folds), "term string, c array<long>")
    found = found.groupBy("term").agg(*[F.sum(F.element_at("c", i + 1)).alias(f"c{i}") for i in range(width)])
    marked = [sum((F.col(f"c{(c * 2 + 1) * folds + f}") for f in range(folds)), F.lit(0)) >= support for c in range(len(categories))]
    enough = F.lit(False)
    for m in marked:
        enough = enough | m
    counts = {r[0]: np.array(r[1:], np.int64).reshape(len(categories), 2, folds) for r in found.where(enough | (F.col("term") == "")).collect()}
    total = counts.pop("", np.zeros((len(categories), 2, folds), np.int64))
    chosen = {}
    for c in range(len(categories)):
        for f in range(-1, folds):
            rest = [g for g in range(folds) if g != f]
            own = {t: (int(v[c, 1, rest].sum()), int(v[c, 0, rest].sum())) for t, v in counts.items()}
            chosen[c, f] = choose(own, int(total[c, 1, rest].sum()), int(total[c, 0, rest].sum()), keep, support, least)
    terms = frozenset(t for some, _ in chosen.values() for t in some)
    sample = rows.mapInArrow(_profiler(terms, folds), "labels array<int>, terms array<string>, counts array<long>, n long, capitals double, marks double, fold int").collect()
    sample = sorted((tuple(r["labels"]), tuple(zip(r["terms"], r["counts"])), r["n"], r["capitals"], r["marks"], r["fold"]) for r in sample)
    profiles = [(dict(x[1]), x[2], (x[3], x[4])) for x in sample]
    targets = [(name, np.array([x[0][c] for x in sample], np.int64)) for c, (name, _, _) in enumerate(categories)]
    return fit(profiles, np.array([x[5] for x in sample], np.int64), targets, chosen, l2)


def flag(docs: DataFrame, model: ChainModel, extra: dict[str, Column] | None = None) -> DataFrame:
    """One row per document: (doc_id, <extra>, p_<category> for each category, score, toxic); score is the last category's probability,
    toxic is 1 from the model's cut on. Null, empty and wordless texts are scored as texts without any word; equal texts score alike; repeated
    rows and null ids pass through; other columns are ignored."""
    ship(docs.sparkSession)
    extra = extra or {}
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(c.alias(n) for n, c in extra.items()), F.col("text").cast("string").alias("input_text"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        wanted = frozenset(t for k in m.links for t in k.terms)
        for batch in batches:
            own = []
            for text in batch.column(batch.num_columns - 1):
                text = text.as_py()
                tally, n = tokens(text)
                own.append(({t: tally[t] for t in wanted & tally.keys()}, n, surface(text)))
            p = m.predict(own)
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], *(pa.array(p[:, i]) for i in range(p.shape[1])), pa.array(p[:, -1]), pa.array((p[:, -1] >= m.cut).astype(np.int32))],
                names=[*batch.schema.names[:-1], *(f"p_{c}" for c in m.categories), "score", "toxic"],
            )

    kept = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{kept}, {', '.join(f'p_{c} double' for c in model.categories)}, score double, toxic int")
