import pytest

LONG = " ".join(f"w{i % 977}x{i % 13}" for i in range(30_000))
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id string, _text string, _row long, component_id long, copy_no int, digest string, part long, block string, value string, key_hi long, shard string"
EXTRA = ("k", "t", 5, 6, 7, "d", 8, "b", "v", 9, "s")

ROWS = [
    (1, "the cat sat on the mat and looked at the dog for a while", "en", "a", 10),
    (2, "the cat sat on the mat  and looked\tat the dog for a while", "en", "a", 10),
    (3, None, "en", None, None),
    (4, "", None, "b", 0),
    (5, " \n\t ", "fr", "b", 4),
    (6, LONG, "en", "a", len(LONG)),
    (7, LONG, "en", "a", len(LONG)),
    (8, "le chat était sur le tapis et regardait le chien pendant un moment", "fr", "b", 66),
    (8, "le chat était sur le tapis et regardait le chien pendant un moment", "fr", "b", 66),
    (9, "12345 !!! 67", None, None, 12),
    (None, "the cat sat on the mat and looked at the dog for a while", "en", "a", 10),
    (None, None, None, None, None),
    (10, "日本語のテキスト 😀 e\u0301 \x0b\x0c\xa0x <|endoftext|> y", "xx", "c", 30),
    (11, "one", "en", "c", 3),
]


@pytest.fixture(scope="session")
def edge(spark):
    return spark.createDataFrame([(*r, *EXTRA) for r in ROWS], SCHEMA)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def small(spark):
    """Documents of sf0.001 with their texts by identifier."""
    df = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    return df, {r.doc_id: r.text or "" for r in df.collect()}
