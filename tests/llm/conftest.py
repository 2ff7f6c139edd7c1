import pytest


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty, long and repeated texts, ties, clashing extra columns."""
    rows = [
        (1, "the quick brown fox jumps over the lazy dog", "en", "s1", 43, "x"),
        (1, "the quick brown fox jumps over the lazy dog", "en", "s1", 43, "x"),
        (2, None, None, None, None, None),
        (3, "", "en", "s2", 0, ""),
        (None, "no id here but words enough to shingle over", None, "s3", 43, "y"),
        (4, "long " * 30_000, "en", "s4", 150_000, "z"),
        (5, "Secret: token = \"abcdef0123456789abcdef0123\" end", "en", "s5", 48, "a"),
        (6, "ünïcödé ☃ 😀 <|endoftext|> ΑΣ  two  blanks\n\n", "de", "s6", 40, "b"),
        (7, "   ", "en", "s7", 3, "c"),
    ]
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint, size string"
    return spark.createDataFrame(rows, schema)


@pytest.fixture(scope="session")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
