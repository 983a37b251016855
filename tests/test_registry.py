"""Registered queries against DuckDB on the smallest tables, and shapes of plans."""

import glob
import math
import os

import duckdb
import pytest

from facetspark import registry
from facetspark.operators import candidates

FOLDER = "/root/testdata/sf0.001"
#: one query of each chain over the corpus; their variants take the same steps
CHAINS = ["m16_hits", "m18_best_match", "m24_greedy", "w01_systems_side_by_side", "w07_relevance_sample", "x19_cost_counters"]
STARTS = ("m02", "m03", "m05", "m07", "m10", "m11", "m12", "m13", "m14", "m15", "x09", "x13", "join", "agg", "win", "set", "fn", "stream", "round", "udf", "udaf", "udtf", "text", "w04", "w11")
PICKED = CHAINS + [n for n in registry.ORACLES if n.startswith(STARTS)]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{FOLDER}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def plain(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr([None if isinstance(r[i], float) and math.isnan(r[i]) else r[i] for i in order]) for r in rows)


@pytest.mark.parametrize("name", PICKED)
def test_query_equals_sql(spark, duck, name):
    got = registry.QUERIES[name](spark, FOLDER)
    want = duck.sql(registry.ORACLES[name])
    assert plain([tuple(r) for r in got.collect()], got.columns) == plain(want.fetchall(), want.columns)


def test_every_oracle_has_a_query():
    assert set(registry.ORACLES) <= set(registry.QUERIES)


def test_containment_is_a_hash_join(spark):
    freq = spark.createDataFrame([("a b", 2), ("a b c", 1)], "query string, freq long")
    plan = candidates.superstrings(freq, freq.select("query"))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_columns_are_pruned(spark):
    plan = registry.QUERIES["scan_parquet_pruned"](spark, FOLDER)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThanOrEqual(l_quantity,45.0)]" in plan and "l_comment" not in plan


def test_sketch_error(spark):
    est = {r["event_type"]: r["users"] for r in registry.QUERIES["sketch_hll_users"](spark, FOLDER).collect()}
    exact = dict(duckdb.sql(f"SELECT event_type, count(DISTINCT user_id) FROM '{FOLDER}/events.parquet' GROUP BY 1").fetchall())
    assert all(abs(est[k] - exact[k]) <= 0.05 * exact[k] + 1 for k in exact)


def test_count_min_bounds(spark):
    from facetspark.operators.toolbox import count_min
    from facetspark.sources.worlds import click_log, Tables

    log = click_log(Tables(spark, FOLDER))
    exact = {r["query"]: r["count"] for r in log.groupBy("query").count().collect()}
    got = {r["query"]: r["estimate"] for r in count_min(log, "query", width=256).collect()}
    assert got.keys() == exact.keys() and all(exact[k] <= got[k] <= exact[k] + 2.72 / 256 * sum(exact.values()) for k in exact)


def test_kll_and_theta_bounds(spark):
    for r in registry.QUERIES["sketch_kll_prices"](spark, FOLDER).collect():
        values = [x[0] for x in duckdb.sql(f"SELECT o_totalprice FROM '{FOLDER}/orders.parquet' WHERE o_orderstatus = '{r['o_orderstatus']}'").fetchall()]
        for q in (25, 50, 75):
            assert abs(sum(v <= r[f"q{q}"] for v in values) / len(values) - q / 100) < 0.03
    users = {k: set(v) for k, v in duckdb.sql(f"SELECT event_type, list(user_id) FROM '{FOLDER}/events.parquet' GROUP BY 1").fetchall()}
    for r in registry.QUERIES["sketch_theta_overlap"](spark, FOLDER).collect():
        assert abs(r["common"] - len(users[r["a"]] & users[r["b"]])) <= 0.05 * len(users[r["a"]] | users[r["b"]]) + 1


def test_p_value(spark):
    got = registry.QUERIES["udf_pandas_tail"](spark, FOLDER).first()
    assert 0 <= got["p"] <= 1
