"""Ranges of the archive follow the bytes, whatever the ids; repeated ids keep all payloads."""

import json

import pytest

from facetspark.llm import warc
from facetspark.llm.store import fresh_path

SCHEMA = "page_id long, url string, html string, digest string, size string"


def test_far_ids_and_hot_ids(spark, tmp_path):
    pages = [(i, "u", f"{i:05d}" * 200, "x", "y") for i in range(300)]
    pages += [(10**17, "far", "far" * 300, "x", "y"), (-5, "low", "low" * 300, None, None)]
    pages += [(77, "hot", f"hot {k} " * 100, "x", "y") for k in range(200)] + [(None, "u", "lost", "x", "y")]
    p = warc.WarcParams(shard_bytes=30_000, roll_bytes=100_000)
    contents = []
    for parts in (3, 11):
        folder = f"file://{tmp_path}/a{parts}"
        warc.write_archive(spark.createDataFrame(pages, SCHEMA).repartition(parts), folder, p)
        files = json.loads((tmp_path / f"a{parts}" / "manifest.json").read_text())["files"]
        contents.append([(f["name"], f["records"], f["sha256"]) for f in files])
        counts = [f["records"] for f in files]
        assert sum(counts) == 502 and max(counts) < 60 and len(files) > 12
    assert contents[0] == contents[1]
    got = [(r["page_id"], r["payload_bytes"], r["record_type"]) for r in warc.read_archive(spark, folder).collect()]
    assert sorted(got) == sorted((i, len(h), "response") for i, _, h, _, _ in pages if i is not None)
    first = tmp_path / "a3" / contents[0][0][0]
    first.write_bytes(first.read_bytes()[: -(len(first.read_bytes()) // 2)])
    with pytest.raises(Exception, match="inside a record|differs from the manifest"):
        warc.read_archive(spark, f"file://{tmp_path}/a3").collect()


def test_repeated_ids_and_rows(spark):
    rows = [(1, "a", "X", "", ""), (2, "b", "X", "", ""), (2, "c", "YY", "", ""), (2, "c", "YY", "", ""), (3, "d", "YY", "", "")]
    folder = fresh_path(spark, "warc")
    warc.write_archive(spark.createDataFrame(rows, SCHEMA), folder)
    got = [(r["page_id"], r["payload_bytes"], r["refers_to"]) for r in warc.read_archive(spark, folder).collect()]
    assert sorted(got, key=str) == sorted([(1, 1, None), (2, 1, 1), (2, 2, None), (2, 2, None), (3, 2, 2)], key=str)
