import pytest


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty, blank and long texts, ties, repeated rows, and columns with clashing names."""
    long = " ".join(f"w{k}" for k in range(3000))
    rows = [
        (1, None), (2, ""), (3, " \n\t"), (4, "One two three four five six."), (5, "one  two three four five six."), (6, "One two three four five six."), (6, "One two three four five six."),
        (None, "One two three four five six."), (7, long), (8, long + " x"), (9, "a" * 5000), (10, "line\nLINE \nother\nline"), (11, "héllo wörld 日本語 😀"), (12, "x  y   z \n\n\n end  "),
    ]
    return spark.createDataFrame([(*r, "src", 0, "k", 1) for r in rows], "doc_id long, text string, source string, n_chars long, digest string, node long")


@pytest.fixture(scope="session")
def none(odd):
    return odd.limit(0)
