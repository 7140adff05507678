import math
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from viewsize.llm import language_id, quality, toxicity
from viewsize.llm.common import in_fold
from viewsize.llm.ftrl import FtrlSoftmax, fit_temperature
from viewsize.llm.queries import op1_language_id, op3_pairwise_quality, op9_toxicity_chain

SF = "/root/testdata/sf0.01"


def test_ftrl_is_sparse_and_separates():
    rng = np.random.default_rng(0)
    y = rng.integers(0, 3, 600)
    rows = [(np.array([c, 3 + rng.integers(50)]), np.array([1.0, 0.5])) for c in y]
    model = FtrlSoftmax(60, 3, l1=1.0).fit(rows, y)
    w, b = model.weights()
    assert (w[3:] == 0).mean() > 0.3
    assert np.mean([(v @ w[a] + b).argmax() == c for (a, v), c in zip(rows, y)]) > 0.99


def test_temperature_softens_overconfident_scores():
    rng = np.random.default_rng(1)
    y = rng.integers(0, 2, 2000)
    scores = np.zeros((2000, 2))
    scores[np.arange(2000), np.where(rng.random(2000) < 0.75, y, 1 - y)] = 10.0
    assert 7 < fit_temperature(scores, y) < 12


def test_ngrams_of_whole_texts():
    assert language_id.ngrams(None) is None and language_id.ngrams("12 $$") is None
    a, b = language_id.ngrams("Ab  cd"), language_id.ngrams("aB-cd")
    assert (a[0] == b[0]).all() and (a[1] == b[1]).all()
    assert language_id.ngrams("a" * 5000 + "z")[0].size > language_id.ngrams("a" * 5000)[0].size


def test_language_held_out(spark):
    r = op1_language_id(spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id").toPandas()
    held = r[r.held_out]
    assert len(r) == 1000 and len(held) > 150 and (held.lang == held.lang_pred).mean() > 0.97
    assert r.score.between(0, 1).all()


def test_quality_held_out(spark):
    r = op3_pairwise_quality(spark, SF).toPandas().merge(spark.read.parquet(f"{SF}/labels.parquet").select("doc_id", "quality").toPandas(), on="doc_id")
    held = r[r.held_out]
    assert (held.quality == held.predicted).mean() > 0.93
    assert r.score.between(0, 1).all() and ((r.score >= 0.3) == (r.predicted == 1)).all()


def test_toxicity_held_out(spark):
    r = op9_toxicity_chain(spark, SF).toPandas().merge(spark.read.parquet(f"{SF}/labels.parquet").selectExpr("doc_id", "toxic AS y").toPandas(), on="doc_id")
    assert (r[r.held_out].y == r[r.held_out].toxic).mean() > 0.93


def test_bradley_terry_recovers_an_order():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 4))
    score = x @ np.array([2.0, -1.0, 0.0, 0.5])
    i, j = rng.integers(0, 400, (2, 3000))
    better = score[i] > score[j]
    w = quality.bradley_terry(np.where(better[:, None], x[i] - x[j], x[j] - x[i]))
    assert np.corrcoef(x @ w, score)[0, 1] > 0.99


def toxic_table(spark, n=600, seed=4):
    """Texts that are junk (marked by a word of its own) or not, toxic ones among the junk only; the toxic word alone is in clean texts as well."""
    rng = np.random.default_rng(seed)
    docs, labels = [], []
    for i in range(n):
        junk, word = i % 2 == 0, i % 3 == 0
        body = " ".join(f"w{rng.integers(400)}x" for _ in range(25)).replace("0", "o").replace("1", "l")
        body = "".join(c if not c.isdigit() else "abcdefghij"[int(c)] for c in body)
        docs.append((i, f"{body} {'spamword' if junk else 'fineword'} {'nastyword' if word else 'kindword'} {body[:40]}"))
        labels.append((i, 0 if junk else 1, int(junk and word)))
    return spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_a_later_link_uses_the_earlier_one(spark):
    """Toxic means junk and the word: the chain's second link puts weight on the first one's probability, and without it predicts worse."""
    docs, labels = toxic_table(spark)
    model = toxicity.train(docs, labels, keep=3)
    assert model.categories == ("junk", "toxic")
    assert [len(k.weights) for k in model.links] == [len(k.terms) + toxicity.EXTRAS + 1 + i for i, k in enumerate(model.links)]
    rows = [(dict(toxicity.tokens(r["text"])[0]), toxicity.tokens(r["text"])[1], toxicity.surface(r["text"])) for r in docs.collect()]
    truth = np.array([r["toxic"] for r in labels.orderBy("doc_id").collect()])
    second = model.links[1]
    assert second.weights[-2] > 0.5  # of the first category's probability
    x = np.array([second.row(*r) for r in rows])
    with_, without = (toxicity._sigmoid(np.hstack([x, e[:, None]]) @ second.weights[:-1] + second.weights[-1]) for e in (model.predict(rows)[:, 0], np.zeros(len(rows))))
    loss = lambda p: -np.mean(np.log(np.clip(np.where(truth == 1, p, 1 - p), 1e-9, 1)))
    assert loss(with_) < loss(without)
    got = {r["doc_id"]: r["toxic"] for r in toxicity.flag(docs, model).collect()}
    assert np.mean([got[i] == t for i, t in enumerate(truth)]) > 0.97


def test_out_of_fold_predictions_see_nothing_of_their_own_label():
    """Labels drawn at random, a term for each row: terms chosen, or weights fitted, on a row's own label would predict it."""
    rng = np.random.default_rng(8)
    y, fold = rng.integers(0, 2, 400), np.arange(400) % 5
    rows = [({f"t{i % 40}": 1}, 10, (0.0, 0.0)) for i in range(400)]
    chosen = {}
    for f in range(-1, 5):
        rest = fold != f
        counts = {f"t{j}": (int(((np.arange(400) % 40 == j) & rest & (y == 1)).sum()), int(((np.arange(400) % 40 == j) & rest & (y == 0)).sum())) for j in range(40)}
        chosen[0, f] = chosen[1, f] = toxicity.choose(counts, int((rest & (y == 1)).sum()), int((rest & (y == 0)).sum()), 300, 3, 0.0)
    model = toxicity.fit(rows, fold, [("a", y), ("b", y)], chosen)
    own = toxicity._sigmoid(np.hstack([np.array([model.links[0].row(*r) for r in rows])]) @ model.links[0].weights[:-1] + model.links[0].weights[-1])
    assert np.mean((own > 0.5) == y) > 0.55 and abs(model.links[1].weights[-2]) < 6  # the first link's out-of-fold probabilities tell little of the label


def test_choosing_terms():
    counts = {"bad": (30, 0), "usual": (50, 50), "rare": (2, 0), "good": (0, 40), "weak": (6, 0)}
    assert toxicity.choose(counts, 100, 100, 300, 3, 15.0) == (("bad",), frozenset(["bad"]))
    assert set(toxicity.choose(counts, 100, 100, 300, 3, 5.0)[0]) == {"bad", "weak"}
    assert toxicity.choose(counts, 0, 100, 300, 3, 5.0) == ((), frozenset())


def shuffled_labels(labels, parts):
    """The labels with those of the held-out rows turned around."""
    held = in_fold("doc_id", parts, 0)
    return labels.withColumns({c: F.when(held, 1 - F.col(c)).otherwise(F.col(c)) for c in ("quality", "toxic")})


@pytest.mark.parametrize("kind", ["quality", "toxicity", "language"])
def test_labels_of_held_out_rows_change_nothing(spark, tmp_path, kind):
    for t in ("documents", "labels"):
        df = spark.read.parquet(f"{SF}/{t}.parquet")
        if t == "labels":
            df = shuffled_labels(df, 5)
        elif kind == "language":
            df = df.withColumn("lang", F.when(in_fold("doc_id", 4, 2), F.lit("zz")).otherwise(F.col("lang")))
        df.write.parquet(str(tmp_path / f"{t}.parquet"))
    run = {"quality": op3_pairwise_quality, "toxicity": op9_toxicity_chain, "language": op1_language_id}[kind]
    first, second = (sorted(tuple(r) for r in run(spark, d).collect()) for d in (SF, str(tmp_path)))
    assert first == second
    parts, part = (4, 2) if kind == "language" else (5, 0)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % parts == part) for r in run(spark, SF).select("doc_id", "held_out").collect())


def test_quality_by_content_alone(spark):
    """Good and bad texts of the same shape (lengths, marks, capitals) that differ in their words: unseen ones in other words of the same make are told apart."""
    rng = np.random.default_rng(12)

    def text(good):
        a, b = ("bdglmn", "aeo") if good else ("kpstvz", "iuy")
        return " ".join("".join(rng.choice(list(a)) + rng.choice(list(b)) for _ in range(3)) for _ in range(40)) + "."

    made = [(i, text(i % 2), i % 2) for i in range(600)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in made], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q) for i, _, q in made[:400]], "doc_id long, quality int")
    got = {r["doc_id"]: r["predicted"] for r in quality.rate(docs, quality.train(docs, labels)).collect()}
    assert np.mean([got[i] == q for i, _, q in made[400:]]) > 0.95


def test_quality_scores_from_the_exported_weights(spark):
    """Every score, worked out again from the model's numbers by a plain loop."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = quality.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in quality.rate(docs, model).where("doc_id % 37 = 0").collect():
        x = quality.statistics(texts[r["doc_id"]]).tolist()
        raw = sum(w * max(-8.0, min(8.0, (v - m) / s)) for v, m, s, w in zip(x, model.mean.tolist(), model.scale.tolist(), model.weights.tolist()))
        z = model.slope * (raw - model.at_cut) + math.log(model.cut / (1 - model.cut))
        assert r["score"] == pytest.approx(1 / (1 + math.exp(-max(-500.0, min(500.0, z)))), abs=1e-9)


def test_language_scores_from_the_exported_weights(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = language_id.train(docs)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in language_id.identify(docs, model).where("doc_id % 37 = 0").collect():
        at, counts = language_id.ngrams(texts[r["doc_id"]])
        v = [(1 + math.log(c)) * model.idf[a] for a, c in zip(at.tolist(), counts.tolist())]
        norm = math.sqrt(sum(x * x for x in v))
        s = [(sum(x / norm * model.weights[a, j] for x, a in zip(v, at.tolist())) + model.intercept[j]) / model.temperature for j in range(len(model.langs))]
        p = [math.exp(x - max(s)) for x in s]
        best = max(range(len(p)), key=lambda j: (p[j], -j))
        assert r["lang_pred"] == model.langs[best] and r["score"] == pytest.approx(p[best] / sum(p), abs=1e-9)


def test_six_hundred_languages(spark):
    """Every language of a label column can be predicted, however many there are."""
    alphabet = [chr(c) for c in range(0x4E00, 0x4E00 + 1200)]
    rows = [(i, " ".join(alphabet[2 * (i % 600)] + alphabet[2 * (i % 600) + 1] for _ in range(8)), f"l{i % 600:03d}") for i in range(1800)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.train(docs, max_rows=1800)
    assert len(model.langs) == 600
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.identify(docs, model).collect()}
    assert np.mean([got[i] == lang for i, _, lang in rows]) > 0.9


def test_counts_beyond_16_bits_are_alike_in_training_and_prediction():
    text = "a" * 70_000
    batch = next(language_id._featurise([pa.RecordBatch.from_pydict({"lang": ["x"], "text": [text]})]))
    at, counts = language_id.ngrams(text)
    assert counts.max() >= 69_998 and np.frombuffer(batch.column(2)[0].as_py(), np.uint32).tolist() == counts.tolist()
    assert np.frombuffer(batch.column(1)[0].as_py(), np.uint16).tolist() == at.tolist()


@pytest.mark.parametrize("kind", ["language", "quality", "toxicity"])
def test_messy_rows(spark, messy, nothing, kind):
    labels = spark.createDataFrame([(3, 1, 0), (9, 0, 1), (8, 1, None), (None, 0, 1)], "doc_id long, quality int, toxic int")
    if kind == "language":
        run = lambda train, docs: language_id.identify(docs, language_id.train(train))
    elif kind == "quality":
        run = lambda train, docs: quality.rate(docs, quality.train(train, labels))
    else:
        run = lambda train, docs: toxicity.flag(docs, toxicity.train(train, labels))
    rows = run(messy, messy).collect()
    assert len(rows) == messy.count() and all(0 <= r["score"] <= 1 for r in rows)
    assert len(run(nothing, messy).collect()) == messy.count()
    assert run(messy, nothing).collect() == []
    if kind == "language":
        assert {r["lang_pred"] for r in rows if r["doc_id"] in (0, 1, 2, 9)} == {"und"}
    by = {}
    for r, t in zip(rows, messy.collect()):
        assert by.setdefault(t["text"], r["score"]) == r["score"]
