import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def row(i, text, source="a"):
    return (i, text, "en", source, None if text is None else len(text))


@pytest.fixture(scope="session")
def make(spark):
    def build(pairs, source="a"):
        return spark.createDataFrame([row(p[0], p[1], p[2] if len(p) > 2 else source) for p in pairs], SCHEMA)

    return build


@pytest.fixture(scope="session")
def odd(make):
    """Nulls in every column, empty and very long texts, ties, repeated rows."""
    long = " ".join(f"w{k % 977}" for k in range(60_000))
    return make([(1, "The cat sat on the mat and looked at the dog."), (1, "The cat sat on the mat and looked at the dog."), (2, None), (3, ""), (None, "no id here at all"), (4, " \n\t "), (5, long), (6, "x", None), (7, "Ünïcode — ΑΣ ß 日本 text next")])


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="session")
def labels(spark, sf):
    return spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
