import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    """Makes a documents table of (id, text) pairs, with a column of a clashing name."""

    def make(pairs, lang="en", source="s"):
        rows = [(i, t, lang, source, None if t is None else len(t)) for i, t in pairs]
        return spark.createDataFrame(rows, SCHEMA)

    return make


@pytest.fixture
def table(spark, tmp_path):
    """Writes a frame as a table under a folder of its own; gives the folder."""

    def write(**frames):
        for name, df in frames.items():
            df.write.mode("overwrite").parquet(f"{tmp_path}/{name}.parquet")
        return str(tmp_path)

    return write
