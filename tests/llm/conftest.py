import pytest
from pyspark.sql import functions as F

CLASHING = "n size cls print sig comp shard slot score toxic label lang_pred h key v words tokens group item block epoch chunk text_key input_text source_no start held_out predicted kept kept_id kept_key row rows once grp d e top most own freq member".split()


def clashing(df):
    """The same rows with columns of names that the operators use inside."""
    return df.withColumns({c: F.lit("x") for c in CLASHING if c not in df.columns})


@pytest.fixture(scope="session")
def messy(spark):
    """Nulls in every column, empty, blank and very long texts, repeated rows, one id with two texts, equal texts."""
    long = " ".join(f"word{i % 977}" for i in range(60_000))
    rows = [
        (0, "", "en", "a", 0), (1, None, None, None, None), (2, " \t\n", "en", "a", 3), (3, "one", "en", "b", 3), (4, "one two", "fr", None, 7), (5, long, "en", "a", len(long)),
        (5, long, "en", "a", len(long)), (6, long, "de", "b", len(long)), (7, "le chat est sur la table", "fr", "b", 24), (7, "der Hund ist im Haus", "de", "b", 20), (None, "the cat sat on the mat", "en", None, 22),
        (None, None, None, "a", None), (8, "the cat sat on the mat", "en", "c", 22), (9, "12345 $$$ %%%", None, "c", 13), (10, "the cat sat on the mat", "en", "c", 22),
    ]
    return clashing(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")).cache()


@pytest.fixture(scope="session")
def nothing(spark):
    return clashing(spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long"))
