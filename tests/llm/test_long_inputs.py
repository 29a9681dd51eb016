"""Urls of very many labels or very long paths, repeated, over any partitions."""

from rasterchain.llm import url_filter


def test_long_urls(spark):
    long_host = "a." * 100_000 + "example.org"
    urls = [f"http://{long_host}/es/", "http://x.org/" + "y" * 300_000, "http://example.org./es/", "http://..org/", "http://" + "." * 5000, "http://example.org/es/"] * 2
    df = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    one, two = ({r["page_id"]: (r["rule"], r["verdict"]) for r in url_filter.filter_urls(df.repartition(n), url_filter.rule_table(spark)).collect()} for n in (1, 5))
    assert one == two
    assert [one[i] for i in range(6)] == [("example.org/es/", "block"), ("org/", "allow"), (None, "allow"), ("org/", "allow"), (None, "allow"), ("example.org/es/", "block")]
    assert [one[i] for i in range(6, 12)] == [one[i] for i in range(6)]


def test_rules_without_any(spark):
    df = spark.createDataFrame([(1, "http://a.b/c")], "page_id bigint, url string")
    assert url_filter.filter_urls(df, url_filter.rule_table(spark).limit(0)).collect()[0]["verdict"] == "allow"
