import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls everywhere, empty and very long texts, ties and repeated rows, a clashing extra column."""
    import random

    rng = random.Random(3)
    words = ["alpha", "beta", "gamma", "delta", "Épsilon", "zeta", "the", "of", "and", "x9"]
    long = " ".join(rng.choice(words) for _ in range(30_000))
    some = " ".join(rng.choice(words) for _ in range(120))
    rows = [
        (0, some, "en", "a", 1, 0.5),
        (1, some, "en", "a", 1, None),
        (1, some, "en", "a", 1, None),
        (2, some.replace("alpha", "beta", 1), None, None, None, None),
        (3, "", "de", "b", 0, 1.0),
        (4, None, "de", "b", None, 1.0),
        (5, long, "en", "b", len(long), 1.0),
        (6, "word", None, "c", 4, 1.0),
        (7, "\t\n \x0b", "en", "c", 4, 1.0),
        (None, "only text here without any id at all", "en", None, 1, 1.0),
        (9, "ÄÖÜ straße \U0001f600 naïve " * 20, "de", "c", 4, 1.0),
        (10, "12345 --- 99", "fr", "c", 4, 1.0),
    ]
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="session")
def benchmark(spark, sf):
    return spark.read.parquet(f"{sf}/benchmark.parquet")


@pytest.fixture(scope="session", autouse=True)
def shipped():
    from ruleclosure.llm import ship_by_value

    ship_by_value()
