"""Signals in a URL's query string reach the model."""

from facetspark.llm import url_filter


def test_query_and_fragment_are_scored(spark):
    urls = [f"http://a{k}.com/en/{k}?spam=spam" for k in range(60)] + [f"http://a{k}.net/de/{k}?id=good#top" for k in range(60)]
    urls += ["http://x.info/p?spam=spam", "http://x.info/p?id=good#top"]
    got = {r["page_id"]: r for r in url_filter.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")).collect()}
    assert (got[120]["host"], got[120]["path"], got[120]["rule"]) == ("x.info", "/p", None)
    assert got[120]["score"] < got[121]["score"]
