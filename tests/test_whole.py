"""The queries over every order and seed."""

import duckdb
import pytest

from facetspark import registry

FOLDER = "/root/testdata/sf0.001"


def test_log_has_every_order_line(spark):
    lines = duckdb.sql(f"SELECT count(*) FROM '{FOLDER}/lineitem.parquet'").fetchall()[0][0]
    assert registry.QUERIES["world_commerce_log"](spark, FOLDER).count() == lines


@pytest.mark.parametrize("name", ["m16_hits", "m25_pipeline", "b05_seed_results"])
def test_every_seed_is_followed(spark, name):
    assert registry.QUERIES[name](spark, FOLDER).select("query").distinct().count() == 125


def test_no_query_thins_the_log():
    assert not [n for n, sql in registry.ORACLES.items() if "% (n_nationkey + 1)" in sql or "% 5 + 1" in sql]
