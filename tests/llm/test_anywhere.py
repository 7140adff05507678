"""Public functions as the first call of a session, from a folder where the workers can't import the library."""

import os
import subprocess
import sys

import pytest

from ..conftest import ROOT

FIRST = {
    "language": "language_id.identify(docs, language_id.train(docs))",
    "near_dup": "near_dup.near_duplicate_groups(docs)",
    "quality": "quality.rate(docs, quality.train(docs, labels))",
    "toxicity": "toxicity.flag(docs, toxicity.train(docs, labels))",
    "html": "html_text.extract(pages, html_text.train(None, generated=30))",
    "topk": "topk.top_k(topk.prepare(vectors), topk.prepare(vectors), 1)",
}


@pytest.mark.parametrize("name", FIRST)
def test_first_call_from_another_folder(tmp_path, name):
    code = f"""
import sys
sys.path.insert(0, {ROOT!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
docs = spark.createDataFrame([(1, "one two three four five six", "en"), (2, "eins zwei drei", "de")], "doc_id long, text string, lang string")
labels = spark.createDataFrame([(1, 1, 0), (2, 0, 1)], "doc_id long, quality int, toxic int")
pages = spark.createDataFrame([(1, "u", "<p>text</p>")], "page_id long, url string, html string")
vectors = spark.createDataFrame([(1, [1.0, 2.0]), (2, [2.0, 1.0])], "vec_id long, embedding array<float>")
from viewsize.llm import html_text, language_id, near_dup, quality, topk, toxicity
print("rows", len({FIRST[name]}.collect()))
"""
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=300)
    assert f"rows {1 if name == 'html' else 2}" in done.stdout, done.stderr[-2000:]


def test_scratch_on_one_machine_is_refused_on_a_cluster():
    from viewsize import session

    class Conf:
        def get(self, key, default=None):
            return default

    class Context:
        master, applicationId = "spark://host:7077", "test-app"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    shipped, session.ship = session.ship, lambda spark: None
    try:
        with pytest.raises(ValueError, match="spark.checkpoint.dir"):
            session.scratch(Session())
    finally:
        session.ship = shipped
