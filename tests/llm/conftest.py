import pytest

ODD = [
    (1, None), (2, ""), (3, " "), (4, "one"), (5, "Été 日本 🙂 <|endoftext|> a\n\nb  c "), (6, "x y z " * 4000), (7, "same text here. And more of it."), (8, "same text here. And more of it."),
    (8, "same text here. And more of it."), (None, "a null id with some words"), (9, "\t\n\r"), (10, "a." * 300),
]


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty, wordless and long texts, ties, a repeated row, and columns whose names clash with outputs."""
    rows = [(i, t, "en" if k % 2 else "de", 7, "s", "h") for k, (i, t) in enumerate(ODD)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, n_words long, score string, h string")


@pytest.fixture(scope="session")
def docs(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet")
