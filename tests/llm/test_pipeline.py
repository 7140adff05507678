import corpus_pipeline as cp

from viewsize.llm.common import settle

from .test_layout import check_packed
from .test_near_dup import brute

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = {}
    for i, (name, stage) in enumerate(cp.STAGES):
        before, docs = docs, settle(stage(spark, docs, SF), name)
        seen[name] = docs
        if i < len(cp.STAGES) - 1:
            assert tuple(docs.columns) == cp.COLUMNS
            assert dict(docs.dtypes) == dict(before.dtypes)
    n = {k: v.count() for k, v in seen.items()}
    assert n["language_id"] == 200 and n["toxicity"] < 200
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    left = {r["doc_id"] for r in seen["toxicity"].collect()}
    assert sum(labels.get(d) == 1 for d in left) <= 0.05 * len(labels)
    assert sum(t == 0 and d not in left for d, t in labels.items()) <= 0.05 * len(labels)
    rows = [(r["doc_id"], r["text"]) for r in seen["toxicity"].collect()]
    comp, _ = brute(rows, 5, 80, 100)
    assert sorted(r["doc_id"] for r in seen["near_dedup"].collect()) == sorted(set(comp))
    sizes = {}
    for r in seen["mixing"].collect():
        sizes[r["doc_id"]] = sizes.get(r["doc_id"], 0) + len(r["text"].encode().split())
    assert sum(r["n_words"] for r in seen["packing"].collect()) == sum(sizes.values())
    if len(sizes) == n["mixing"]:
        check_packed(seen["packing"].collect(), sizes, (512, 1024, 2048, 4096))


def test_messy_documents(spark, messy, nothing):
    for _, stage in cp.STAGES:
        stage(spark, messy, SF).collect()
        assert stage(spark, nothing, SF).collect() == []


def test_oracle_is_declared():
    assert cp.ORACLE_SQL is None and [n for n, _ in cp.STAGES] == ["language_id", "toxicity", "near_dedup", "mixing", "packing"]
