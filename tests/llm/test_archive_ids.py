"""Ids of any type through the archives."""

import pytest

from ditherspark.llm import warc


@pytest.mark.parametrize("kind", ["string", "smallint", "int", "bigint"])
def test_ids_come_back(spark, kind):
    body = "x" * 200
    rows = [(None, None, body), ("7", "u", body), ("9", "v\r\nw", "short"), ("8", None, body)] + ([("null", "n", "y" * 120), ("a b%/>", "o", "y" * 120)] if kind == "string" else [])
    df = spark.createDataFrame(rows, "page_id string, url string, html string").selectExpr(f"cast(page_id as {kind}) page_id", "url", "html")
    out = warc.digest(df)
    assert dict(out.dtypes)["page_id"] == kind
    got = {(r.page_id if r.page_id is None else str(r.page_id)): (r.record_type, r.refers_to if r.refers_to is None else str(r.refers_to)) for r in out.collect()}
    want = {None: ("revisit", "7"), "7": ("response", None), "8": ("revisit", "7"), "9": ("response", None)}
    assert got == want | ({"null": ("revisit", "a b%/>"), "a b%/>": ("response", None)} if kind == "string" else {})


def test_dictionary_holds_headers_and_whole_pages(spark, sf):
    d = warc.dictionary_of(spark.read.parquet(f"{sf}/pages.parquet"))
    assert b"WARC-Type: " in d and len(d) <= 64 << 10
    assert len(warc.sample_of(b"ab" * 10**5, 4096)) == 4096 and warc.sample_of(b"x", 10) == b"x"
