from __future__ import annotations

from vecforest.llm import language


def test_declared_after_a_long_comment(spark):
    docs = spark.createDataFrame([("the river ran under the bridge", "en")], "text string, lang string")
    html = f"<!-- {'licence ' * 1000}-->\n<html lang='de'><p>the river ran</html>"
    pages = spark.createDataFrame([(1, "http://a.example.com/", html)], "page_id long, url string, html string")
    assert language.of_pages(pages, docs).first()["declared"] == "de"
