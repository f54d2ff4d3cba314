"""Pages are extracted whatever their length."""

from webtext.operators import extract as X


def test_a_page_beyond_any_bound_is_extracted(spark, monkeypatch):
    monkeypatch.setattr(X, "MAX_BYTES", 1000, raising=False)
    text = "A sentence of the article that goes on for some words, as articles do. " * 40
    pages = spark.createDataFrame([(1, f"<html><body><article><p>{text}</p></article></body></html>")], "page_id long, html string")
    row = X.core(pages).first()
    assert row.status == "ok" and "A sentence of the article" in row.main_text
