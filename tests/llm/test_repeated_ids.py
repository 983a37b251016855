"""Rows that repeat a page number with another payload."""

from facetspark.llm import warc


def test_only_the_equal_payload_is_a_revisit(spark):
    pages = [(1, "a", "x"), (7, "b", "x"), (7, "c", "own"), (7, "d", "own too")]
    got = warc.archive_and_read(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()
    assert sorted((r["url"], r["record_type"], r["refers_to"]) for r in got) == [("a", "response", None), ("b", "revisit", 1), ("c", "response", None), ("d", "response", None)]
    assert {r["payload_digest"] for r in got} == {warc.payload_digest(x) for x in (b"x", b"own", b"own too")}
