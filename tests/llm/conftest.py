import pytest

#: Nulls, blanks, one word, many words, repeated rows, a long text, and columns named like the operators' own.
TEXTS = [
    (1, "The quick brown fox jumps over the lazy dog near the river bank today. " * 3),
    (2, None),
    (3, ""),
    (4, " \t\n "),
    (5, "one"),
    (6, "Ünïcödé ÉTÉ çava <|endoftext|> don't stop 123456"),
    (7, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon\nline two here."),
    (7, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon\nline two here."),
    (8, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon\nline two there."),
    (None, "a text without number"),
    (9, "word " * 30_000 + "end"),
]


@pytest.fixture(scope="session")
def odd(spark):
    rows = [(i, t, None if i == 4 else "en", None if i in (3, None) else f"s{(i or 0) % 3}", len(t or ""), 0, "x", "y") for i, t in TEXTS]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size int, target string, key string")


@pytest.fixture(scope="session")
def empty(odd):
    return odd.where("false")


@pytest.fixture(scope="session")
def small(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
