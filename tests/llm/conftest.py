import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, k int, body string, fp string, m string, root string, starts string, count int, start int, first int"


@pytest.fixture
def docs(spark):
    """(id, text) rows as a documents table with other columns whose names the operators use inside."""

    def make(rows):
        return spark.createDataFrame([(i, t, None, None, len(t) if t is not None else None, 1, "x", "y", "z", "w", "v", 2, 3, 4) for i, t in rows], DOCS)

    return make


@pytest.fixture
def by_id():
    def rows(df, *names):
        return sorted((tuple(r[n] for n in names) for r in df.collect()), key=lambda r: tuple((x is not None, x) for x in r))

    return rows
