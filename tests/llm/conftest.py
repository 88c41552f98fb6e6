import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
SENTENCES = "The river runs past the old mill and under the stone bridge . In spring the water rises over the lower path and the ducks nest in the reeds ."


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, repeated rows, ties, and columns whose names clash with the operators' own."""
    long = " ".join(f"w{i % 977}x{i}" for i in range(30_000))
    rows = [
        (1, SENTENCES), (2, SENTENCES), (3, None), (4, ""), (None, SENTENCES), (5, long), (6, " \t\n\x0b "), (7, "four words are few"), (8, "four words are few"), (1, SENTENCES),
        (9, "a.b@c.example.com " * 3 + "ünï ☃ 日本語 😀"), (None, None), (10, SENTENCES + " End"), (11, "x" * 50_000),
    ]
    names = ("n_words", "kept", "tag", "doc", "line_no", "words", "key", "sig", "row", "part", "__x", "lang", "n_lines", "rank", "host", "u", "v", "start", "c1", "family")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    from pyspark.sql import functions as F

    return df.withColumns({n: F.lit("kept as it is") for n in names})


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
