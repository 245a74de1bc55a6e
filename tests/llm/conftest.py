import pytest

ODD = [None, "", " ", "\n\n", "\t \x0b", "é", "The THE the", "a b", "x" * 70_000, "word " * 9_000, "tie tie tie", "tie tie tie", "\U0001f600 \U0001f601 　 end", "<|endoftext|> and <s>", "▁▁ a ▁", "½ ² ①", "Ⅷ ½", "?!... a. .b"]


@pytest.fixture(scope="session")
def odd(spark):
    """Null, empty, blank, long, repeated and strange texts, with columns whose names operators use themselves."""
    rows = [(1_000_000 + i, t, None if i % 3 else "en", "src", i, "clash", "clash") for i, t in enumerate(ODD)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, id string, kept string")


@pytest.fixture(scope="session")
def docs(spark, sf, odd):
    return spark.read.parquet(f"{sf}/documents.parquet").unionByName(odd.select("doc_id", "text", "lang", "source", "n_chars")).cache()


@pytest.fixture(scope="session")
def texts(docs):
    return {r.doc_id: r.text for r in docs.collect()}


@pytest.fixture(scope="session")
def none(odd):
    return odd.limit(0)
