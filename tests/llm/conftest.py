import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
PASSAGE = "a passage of more than fifty bytes that several of the documents share word for word, with a tail"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, ties, copies, repeated rows, and columns whose names clash with outputs."""
    long = " ".join(f"word{i % 977} of{i % 31}" for i in range(6000))
    rows = [
        (1, "plain words of a first text that is long enough to be kept by rules of any kind and then some more", "en", "a", 10), (2, None, "en", "b", 0), (3, "", None, None, None), (4, long, "de", "a", 1),
        (5, PASSAGE + " one", "en", "a", 5), (6, "before " + PASSAGE, "en", "b", 6), (7, PASSAGE + " one", "fr", None, 7), (7, PASSAGE + " one", "fr", None, 7),
        (8, "  \t\n ", "en", "a", 8), (None, PASSAGE + " two", "en", "a", 9), (9, "x", "en", "c", 9), (10, "émile été naïve ça où là  deux  espaces", "fr", "c", 3), (11, "\n".join(["same line here"] * 9), "en", "a", 3),
        (12, "aaaa " * 40, "en", "b", 2), (13, "### $$$ %%% " * 12, None, "b", 2)]
    df = spark.createDataFrame(rows, DOCS)
    from pyspark.sql import functions as F

    for name in ("piece", "length", "size", "fingerprint", "kept", "start", "copies", "label", "pos", "bucket"):
        df = df.withColumn(name, F.lit("clash"))
    return df


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def saved(tmp_path_factory):
    def save(**tables):
        d = tmp_path_factory.mktemp("sf")
        for name, df in tables.items():
            df.write.parquet(f"file://{d}/{name}.parquet")
        return f"file://{d}"

    return save
