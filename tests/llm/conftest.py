import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, key string"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and blank texts, ties, repeated rows, clashing column names and a long text."""
    long = " ".join(f"w{i % 977} x{i % 13}" for i in range(20_000))
    passage = " ".join(f"p{i}" for i in range(80))
    rows = [
        (1, "a b c d e f g", "en", "s1", 1, 9, "k"),
        (1, "a b c d e f g", "en", "s1", 1, 9, "k"),
        (2, None, "en", None, None, None, None),
        (3, "", None, "s2", 0, 0, ""),
        (4, " \n\t ", "en", "s2", 4, 1, "x"),
        (5, long, "en", "s1", len(long), 2, "y"),
        (6, "x " + passage + " y z", "en", "s3", 5, 3, "z"),
        (7, "q " + passage + " r", "en", "s3", 5, 3, "z"),
        (None, passage, "en", "s3", 5, 3, "z"),
        (8, "mail a.b@c.example.org or call +1 (555) 123-4567 at 10.0.0.1, card 4111 1111 1111 1111", "en", "s4", 1, 1, "k"),
        (9, "İstanbul ΑΣ 你好 <|endoftext|> it's x y", "el", "s5", 1, 1, "k"),
    ]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
