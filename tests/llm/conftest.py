import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def documents(spark):
    """A documents table from (doc_id, text) rows, with a column whose name operators use inside."""

    def make(rows):
        df = spark.createDataFrame([(i, t, None, "s", 0) for i, t in rows], SCHEMA)
        return df.selectExpr("*", "'x' as part", "'y' as id", "1 as fp", "2 as th")

    return make
