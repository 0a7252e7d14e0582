import re

import pytest

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, extra string"

LONG = " ".join(f"w{i % 977}x{i % 31}" for i in range(4000))
NEAR = LONG.replace("w500x", "other")
#: Nulls, blanks, ties, copies, near copies, very long words and texts, clashing columns.
EDGE = [
    (1, LONG), (2, LONG), (3, NEAR), (4, None), (5, ""), (6, "   \n\t "), (7, "one"), (8, "one"), (9, "ONE two three four"), (None, "one"), (None, None), (10, "é ü ñ " * 30),
    (11, "x" * 5000), (12, "a b c d e f g h i j k"), (12, "a b c d e f g h i j k"), (13, "The quick brown fox jumps over the lazy dog again and again until it is done. " * 3),
    (14, "Prefix here. The quick brown fox jumps over the lazy dog again and again until it is done. Suffix."), (15, "ab" * 200), (16, "ab" * 200 + "c"),
]


def words(text):
    return WORD.findall((text or "").translate(LOWER))


@pytest.fixture(scope="session")
def edge(spark):
    rows = [(i, t, "en" if k % 2 else "fr", None if k % 3 == 0 else "s", len(t or ""), "z") for k, (i, t) in enumerate(EDGE)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
