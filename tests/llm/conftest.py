import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def documents(spark):
    """Documents with a null in each column, empty and very long texts, ties, repeated rows and a clashing extra column."""
    long_text = " ".join(f"word{i % 997} filler{i}" for i in range(40_000))
    base = "the quick brown fox jumps over the lazy dog while seven wizards quietly mix potions for the evening feast and nobody complains about it at all"
    rows = [
        (1, base, "en", "a", 10), (2, base, "en", "a", 10), (2, base, "en", "a", 10), (3, base.replace("seven", "eight"), "en", "b", 10),
        (4, None, "en", "b", None), (5, "", "en", "c", 0), (6, "   \n\t", "en", "c", 5), (None, "a text without an id that says little", "en", "c", 3),
        (7, long_text, "en", None, 9), (8, "!!! ???", None, "a", 3), (9, "one", "en", "d", 3), (10, "Ünïcödé ñandú 漢字 emoji 😀", "es", "d", 4),
    ]
    return spark.createDataFrame(rows, DOCS).selectExpr("*", "1 AS size", "'x' AS digest", "0.5D AS score", "7L AS node", "'y' AS class_id")


@pytest.fixture
def no_documents(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture
def real(spark, sf_dir):
    return lambda table: spark.read.parquet(f"{sf_dir}/{table}.parquet")
