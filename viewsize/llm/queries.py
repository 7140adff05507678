"""The registered queries of the corpus operators: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import in_fold, load


def op10_minhash_inverted_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dup import near_duplicate_groups

    return near_duplicate_groups(load(spark, sf_dir, "documents"), k=3, num=85, den=100).drop("text_key")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained on rows whose crc32(doc_id) mod 4 is not 2; every document is predicted."""
    from . import language_id

    docs = load(spark, sf_dir, "documents")
    model = language_id.train(docs.where(~in_fold("doc_id", 4, 2)))
    return language_id.identify(docs, model, {"held_out": in_fold("doc_id", 4, 2)})


def op2_media_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .media import media_features

    return media_features(load(spark, sf_dir, "documents"))


def op3_pairwise_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained on labelled rows whose crc32(doc_id) mod 5 is not 0; every document is scored."""
    from . import quality

    docs = load(spark, sf_dir, "documents")
    model = quality.train(docs, load(spark, sf_dir, "labels").where(~in_fold("doc_id", 5, 0)))
    return quality.rate(docs, model, {"held_out": in_fold("doc_id", 5, 0)})


def op4_dom_boosted_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import html_text

    pages = load(spark, sf_dir, "pages")
    return html_text.extract(pages, html_text.train(pages))


def op5_vector_bin_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard_documents

    return shard_documents(load(spark, sf_dir, "documents"), shards=40)


def op6_pivot_distance_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries: the vectors whose id is divisible by 50, against all rows."""
    from .topk import prepare, top_k

    rows = prepare(load(spark, sf_dir, "embeddings"))
    return top_k(rows, rows.where("vec_id % 50 = 0"), k=5)


def op7_block_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mixture_report

    return mixture_report(load(spark, sf_dir, "documents"))


def op8_variable_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(load(spark, sf_dir, "documents"))


def op9_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained on labelled rows whose crc32(doc_id) mod 5 is not 0; every document is scored."""
    from . import toxicity

    docs = load(spark, sf_dir, "documents")
    model = toxicity.train(docs, load(spark, sf_dir, "labels").where(~in_fold("doc_id", 5, 0)))
    return toxicity.flag(docs, model, {"held_out": in_fold("doc_id", 5, 0)})


def queries() -> dict:
    return {f.__name__: f for f in (op1_language_id, op2_media_archive, op3_pairwise_quality, op4_dom_boosted_text, op5_vector_bin_packing, op6_pivot_distance_topk, op7_block_mixture, op8_variable_best_fit, op9_toxicity_chain, op10_minhash_inverted_join)}


_OP6 = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5"""

_OP10 = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS t FROM documents),
g AS (SELECT doc_id, unnest(CASE WHEN len(t) = 0 THEN [] WHEN len(t) < 3 THEN [array_to_string(t, ' ')] ELSE list_transform(range(1, len(t) - 1), lambda i: t[i] || ' ' || t[i + 1] || ' ' || t[i + 2]) END) AS x FROM w),
s AS (SELECT DISTINCT doc_id, hash(x) AS x FROM g),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * i >= 85 * (na.n + nb.n - i)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
c AS (SELECT doc_id AS node, doc_id AS root FROM documents UNION SELECT e.b, c.root FROM c JOIN e ON e.a = c.node AND c.root < e.b)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, min(c.root) AS component_id, d.doc_id = min(c.root) AS kept FROM documents d LEFT JOIN n USING (doc_id) JOIN c ON c.node = d.doc_id GROUP BY d.doc_id, n.n"""


def oracle_sql() -> dict:
    return {"op6_pivot_distance_topk": _OP6, "op10_minhash_inverted_join": _OP10}
