import pytest

DATA = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, extra string, kept string, size long"


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with nulls in every column, empty, blank and very long texts, ties, repeats and clashing columns."""
    long = " ".join(f"word{i % 977}" for i in range(40_000))
    texts = [None, "", " \t\n", "a", "a b c d e f g", "a  b\tc d e f g", "A B C D E F G", long, long, "x " * 300, "# $ %\n" * 40, "été ça über 文字", "<|endoftext|> </turn> \\l"]
    rows = [(i if i % 6 else None, t, "en" if i % 3 else None, f"s{i % 4}" if i % 5 else None, None if t is None else len(t), "e", "k", 3) for i, t in enumerate(texts * 2)]
    rows += [(3, "a", "en", "s0", 1, "e", "k", 3)] * 3
    return spark.createDataFrame(rows, DOCS).repartition(3).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def documents(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet").cache()


@pytest.fixture(scope="session")
def labels(spark):
    return spark.read.parquet(f"{DATA}/labels.parquet")
