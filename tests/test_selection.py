"""Ratio selection against score-only selection."""

import duckdb
import glob
import os

from facetspark import registry

FOLDER = "/root/testdata/sf0.001"


def test_score_only_lists_are_measured(spark):
    con = duckdb.connect()
    for f in glob.glob(f"{FOLDER}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    rows = registry.QUERIES["w16_nsim_by_score"](spark, FOLDER).select("query", "asim", "isim", "nsim").collect()
    assert rows and sorted(map(repr, map(tuple, rows))) == sorted(map(repr, con.sql(registry.ORACLES["w16_nsim_by_score"]).fetchall()))
