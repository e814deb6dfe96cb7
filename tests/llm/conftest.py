import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    """Documents from (doc_id, text) or longer tuples; the rest is filled up."""

    def make(*rows):
        full = [tuple([*r, None, None, None][:5]) for r in rows]
        return spark.createDataFrame(full, DOCS)

    return make


#: Null, empty, blank, letterless, one word, repeated row, null id, a long single word, a very long text.
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "123 456 !!"), (5, "word"), (5, "word"), (None, "no id here"), (6, "a" * 30_000), (7, "lorem ipsum dolor sit amet " * 40_000)]
