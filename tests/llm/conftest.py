import pytest


@pytest.fixture(scope="session")
def docs_schema():
    return "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="session")
def odd_texts():
    """Null, empty, white space, repeated, long and multi-byte texts."""
    base = "The quick brown fox jumps over the lazy dog and runs far away from the old river bank today."
    return [None, "", " \n\t ", "word", base, base, base + " More.", "naïve café 日本語 🎉 " * 30, "x" * 20_000, "a b " * 4000, "\x00 nul \x1f", base.upper()]
