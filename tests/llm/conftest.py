import pytest

LONG = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega"


@pytest.fixture(scope="session")
def docs(spark):
    """Nulls, empty and long texts, repeated rows, ties, and columns whose names clash with the operators' own."""
    long = " ".join(f"{w}{i % 7}" for i in range(400) for w in LONG.split())
    rows = [
        (1, LONG, "en", "s0"), (2, LONG, "en", "s0"), (2, LONG, "en", "s0"), (3, LONG + " extra", "en", None), (4, None, None, "s1"), (5, "", "de", "s1"), (6, " \t\n", "de", "s1"), (7, long, "fr", "s1"),
        (8, long + " tail", "fr", "s2"), (9, "one", "es", "s2"), (10, "ONE", None, "s2"), (11, "a b c d", "es", "s2"), (12, "A b C d", "es", "s2"), (None, LONG, "en", "s2"), (13, "😀 naïve <|endoftext|> café　x", "fr", "s2"),
    ]
    return spark.createDataFrame([(*r, 7, True, "x", 0) for r in rows], "doc_id long, text string, lang string, source string, n_words int, kept boolean, component_id string, length int")


@pytest.fixture(scope="session")
def empty(docs):
    return docs.where("false")
