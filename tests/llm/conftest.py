import pytest

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


@pytest.fixture(scope="session")
def prose():
    import random

    rng = random.Random(7)
    return lambda n: " ".join(rng.choice(WORDS) + str(rng.randint(0, 40)) for _ in range(n))


@pytest.fixture(scope="session")
def messy(spark):
    """Documents with nulls everywhere, empty and long texts, repeated rows and a clashing extra column."""
    long = "word " * 30000
    rows = [(1, "a b c d e f g", "en", "s1", 13, 1), (2, None, None, None, None, 2), (3, "", "en", "s2", 0, 3), (4, long, "en", "s1", None, 4), (5, "a b c d e f g", None, "s1", 13, 5), (5, "a b c d e f g", None, "s1", 13, 5), (6, " \t\n ", "de", None, 4, 6), (None, "no id at all here now", "en", "s1", 1, 7)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, _text int")
