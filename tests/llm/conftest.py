
import pytest


@pytest.fixture(scope="session")
def docs(spark):
    """Make a documents table: (doc_id, text) pairs, with extra columns whose names clash with results."""

    def make(rows):
        schema = "doc_id long, text string, lang string, source string, n_chars long, n_tokens long, score double, keep_id long, component_id long, spans string"
        return spark.createDataFrame([(i, t, None, "s", None if t is None else len(t), -1, None, None, None, "x") for i, t in rows], schema)

    return make


NASTY = [None, "", " ", "\n\t ", "a", "a b", "  a  b  ", "x" * 5000, "word " * 3000, "é漢字😀 ▁ \u0000 <s> <|endoftext|>", "don't  we'll\n\nx　y", "password = \"abcdefgh12345\"", "it's. É*** $%^"]
