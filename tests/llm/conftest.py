import pytest

#: Nulls, empty and blank texts, ties, repeated rows, a very long text, and columns whose names operators use themselves.
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id string, size long, row int, fp long, ids string, label string"

LONG = " ".join(f"word{i % 997} the and of" for i in range(60_000))

TEXTS = [
    "The cat and the dog went to the market, and the bird sang of the old days by the river.",
    "The cat and the dog went to the market, and the bird sang of the old days by the river.",
    "THE CAT and the dog went to the market, and the bird sang of the old days by the river.",
    None,
    "",
    " \n\t ",
    "one",
    "two words",
    "Write to jo.doe@mail3.example.com or +1 (437) 555-0689 from 10.20.30.40 with card 4111 1111 1111 1111 now.",
    'From token = "5d190bd7c06284de91015a36974748794293dd8a" the rest is plain, 9807915762804491 is no card.',
    "spam spam spam spam spam spam spam spam spam spam spam spam spam spam spam spam",
    "line one\nline two\nline one\n\nline one",
    "caf\u00e9 na\u00efve \U0001f389 \u65e5\u672c\u8a9e \u0391\u03a3 don't we'll  x\r\ny",
    LONG,
]


@pytest.fixture(scope="session")
def docs(spark):
    rows = [(i, t, "en", ("b", "a", None, "a")[i % 4], None if t is None else len(t), "x", i, 1, 2, "y", "z") for i, t in enumerate(TEXTS)]
    rows += [(0, *rows[0][1:]), (None, "no id at all, but some words for the road", None, "c", None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def corpus(spark):
    """The smallest given documents, as rows."""
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
