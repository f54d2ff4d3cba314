import pytest


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and long texts, ties, repeated rows, null and repeated ids, and columns whose names clash."""
    rows = [
        (1, None, "a"), (2, "", "a"), (3, "one two three", None), (4, "one two three", "a"), (4, "one two three", "a"), (None, "null id " * 30, "b"), (5, "word " * 40000, "b"),
        (6, "Line é <|endoftext|> <|im_end|>\n\n\tx", "b"), (7, " ".join(f"w{i}" for i in range(200)), "a"), (8, " ".join(f"w{i}" for i in range(198)) + " z y", "a"), (9, " \n ", "c"),
    ]
    return spark.createDataFrame([(i, t, s, 7, "x") for i, t, s in rows], "doc_id long, text string, source string, size int, h string")


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], "doc_id long, text string, source string, n_chars long")
