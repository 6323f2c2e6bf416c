import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp long, score double, key string, start int"


@pytest.fixture(scope="session")
def docs_of(spark):
    """A documents table with extra columns whose names clash with the operators' own."""

    def make(rows):
        full = [(i, t, lang, src, len(t) if t is not None else None, 7, 0.5, "k", 1) for i, t, lang, src in rows]
        return spark.createDataFrame(full, SCHEMA)

    return make


@pytest.fixture(scope="session")
def folder_of(tmp_path_factory):
    """Write a table so that a registered query can read it."""

    def make(name, df):
        d = tmp_path_factory.mktemp("tables")
        df.write.parquet(f"{d}/{name}.parquet")
        return str(d)

    return make


EDGE = [
    (1, None, "en", "a"), (2, "", "en", None), (3, "   \n\t ", None, "a"), (4, "word", "en", "b"), (5, "word", "en", "b"), (5, "word", "en", "b"),
    (None, "no id here at all", None, None), (6, "two words", "de", "c"), (7, "x" * 5000 + " tail", "en", "a"), (8, "the quick brown fox " * 3000, "en", "a"),
]


@pytest.fixture(scope="session")
def edge(docs_of):
    return docs_of(EDGE)


@pytest.fixture(scope="session")
def empty(docs_of, spark):
    return spark.createDataFrame([], SCHEMA)
