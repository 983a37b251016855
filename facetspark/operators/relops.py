"""Relational operators around the methods, each on a given table, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.sources.worlds import Tables


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, order: str) -> DataFrame:
    """Each left row with the last earlier or equal right value: a union and one running window, no range join."""
    names = [c for c in left.columns if c not in (by, at, order)]
    a = left.select(by, at, order, *names, F.lit(1).alias("side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("seen"))
    b = right.select(by, at, F.lit(None).cast(dict(left.dtypes)[order]).alias(order), *(F.lit(None).cast(dict(left.dtypes)[n]).alias(n) for n in names), F.lit(0).alias("side"), F.col(value).alias("seen"))
    run = W.partitionBy(by).orderBy(at, "side", order).rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("last_seen", F.last("seen", ignorenulls=True).over(run)).where("side = 1").select(by, at, order, *names, "last_seen")


def events(t: Tables) -> DataFrame:
    return t.events.select("event_id", "ts", "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("k"))


EV = "(SELECT event_id, ts, user_id, event_type, value, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events)"
WIN = "WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)"


def by_user():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


def _interval(t: Tables) -> DataFrame:
    a = events(t).where("k < 50").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = events(t).where("k >= 50").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return a.join(b, (a["user_id"] == b["user_id"]) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 2 HOURS"))).select("a", "b")


OPERATORS: dict[str, tuple] = {
    "scan_parquet_pruned": (lambda t: t.lineitem.where("l_quantity >= 45").select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 45"),
    "filter_compound": (lambda t: t.orders.where("(o_orderstatus in ('F','O') and o_totalprice between 1000 and 200000) or o_orderpriority like '1-%'").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE (o_orderstatus IN ('F','O') AND o_totalprice BETWEEN 1000 AND 200000) OR o_orderpriority LIKE '1-%'"),
    "filter_null_safe": (lambda t: events(t).where(~F.nullif(F.col("k") % 7, F.lit(0)).eqNullSafe(F.lit(3))).select("event_id"), f"SELECT event_id FROM {EV} WHERE nullif(k % 7, 0) IS DISTINCT FROM 3"),
    "case_bucket": (lambda t: t.part.select(F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large").alias("bucket")).groupBy("bucket").count().withColumnRenamed("count", "n"), "SELECT CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS bucket, count(*) AS n FROM part GROUP BY 1"),
    "join_sort_merge_orders": (lambda t: t.lineitem.hint("merge").join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
    "join_hash_shuffled": (lambda t: t.orders.join(t.customer.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"),
    "join_broadcast_kb": (lambda t: t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"),
    "join_range_steps": (lambda t: t.conversations.where("role='user'").select("conv_id", F.col("turn").alias("a")).join(t.conversations.where("role='user'").select("conv_id", F.col("turn").alias("b")), "conv_id").where("a < b"), "SELECT x.conv_id, x.turn AS a, y.turn AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND x.turn < y.turn WHERE x.role = 'user' AND y.role = 'user'"),
    "join_asof_events": (lambda t: asof_join(events(t).where("k < 50").select("user_id", "ts", "event_id"), events(t).where("k >= 50").groupBy("user_id", "ts").agg(F.max("k").alias("k")), "user_id", "ts", "k", "event_id").select("event_id", "last_seen"), f"SELECT a.event_id, b.k AS last_seen FROM (SELECT * FROM {EV} WHERE k < 50) a ASOF LEFT JOIN (SELECT user_id, ts, max(k) AS k FROM {EV} WHERE k >= 50 GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts"),
    "join_interval_events": (_interval, f"SELECT a.event_id AS a, b.event_id AS b FROM {EV} a JOIN {EV} b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR WHERE a.k < 50 AND b.k >= 50"),
    "join_semi": (lambda t: t.customer.join(t.orders.where("o_orderstatus = 'P'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')"),
    "join_anti": (lambda t: t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"),
    "join_left": (lambda t: t.documents.join(t.labels, "doc_id", "left").groupBy("lang", "quality").agg(F.count("*").alias("n")), "SELECT lang, quality, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL"),
    "join_right": (lambda t: t.supplier.join(t.nation, F.col("s_nationkey") == F.col("n_nationkey"), "right").groupBy("n_name").agg(F.count("s_suppkey").alias("n")), "SELECT n_name, count(s_suppkey) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY 1"),
    "join_full": (lambda t: t.customer.groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("c")).where("k % 2 = 0").join(t.supplier.groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("s")).where("k % 3 = 0"), "k", "full_outer"), "SELECT coalesce(a.k, b.k) AS k, c, s FROM (SELECT c_nationkey AS k, count(*) AS c FROM customer WHERE c_nationkey % 2 = 0 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS s FROM supplier WHERE s_nationkey % 3 = 0 GROUP BY 1) b ON a.k = b.k"),
    "join_lateral_tokens": (lambda t: t.benchmark.select("item_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("length(w) > 5").groupBy("w").agg(F.count("*").alias("n")), "SELECT w, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS w FROM benchmark) WHERE length(w) > 5 GROUP BY 1"),
    "agg_basic": (lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 4).alias("d"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi")), "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 4) AS d, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY ALL"),
    "agg_distinct": (lambda t: t.lineitem.groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("s"), F.count_distinct("l_partkey").alias("p")), "SELECT l_returnflag, count(DISTINCT l_suppkey) AS s, count(DISTINCT l_partkey) AS p FROM lineitem GROUP BY 1"),
    "agg_conditional": (lambda t: t.labels.agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("bad"), F.bool_or(F.col("toxic") == 1).alias("some")), "SELECT count_if(quality = 1) AS good, count_if(toxic = 1) AS bad, bool_or(toxic = 1) AS some FROM labels"),
    "agg_having": (lambda t: t.orders.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 15"),
    "agg_rollup": (lambda t: t.documents.rollup("lang", "source").agg(F.count("*").alias("n")), "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)"),
    "agg_cube": (lambda t: t.orders.cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "agg_grouping_sets": (lambda t: t.orders.groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))"),
    "agg_pivot_verdict": (lambda t: t.lineitem.groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))), "SELECT l_linestatus, count_if(l_returnflag = 'A') AS A, count_if(l_returnflag = 'N') AS N, count_if(l_returnflag = 'R') AS R FROM lineitem GROUP BY 1"),
    "agg_unpivot": (lambda t: t.part.unpivot(["p_partkey"], ["p_brand", "p_type"], "kind", "value").groupBy("kind", "value").agg(F.count("*").alias("n")), "SELECT kind, value, count(*) AS n FROM (SELECT 'p_brand' AS kind, p_brand AS value FROM part UNION ALL SELECT 'p_type', p_type FROM part) GROUP BY ALL"),
    "agg_max_by": (lambda t: t.part.groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("top")), "SELECT p_brand, arg_max(p_partkey, (p_retailprice, p_partkey)) AS top FROM part GROUP BY 1"),
    "agg_listagg": (lambda t: t.nation.groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1"),
    "agg_percentile": (lambda t: t.part.groupBy("p_type").agg(F.round(F.percentile("p_size", 0.5), 4).alias("median")), "SELECT p_type, round(quantile_cont(p_size, 0.5)::DOUBLE, 4) AS median FROM part GROUP BY 1"),
    "agg_stats": (lambda t: t.customer.groupBy("c_mktsegment").agg(F.round(F.stddev_samp("c_acctbal"), 4).alias("sd"), F.round(F.corr("c_acctbal", "c_nationkey"), 6).alias("r")), "SELECT c_mktsegment, round(stddev_samp(c_acctbal), 4) AS sd, round(corr(c_acctbal, c_nationkey), 6) AS r FROM customer GROUP BY 1"),
    "win_rank_family": (lambda t: t.part.select("p_partkey", *(f.over(W.partitionBy("p_type").orderBy("p_size")).cast("long").alias(n) for f, n in ((F.rank(), "r"), (F.dense_rank(), "d")))), "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_size)"),
    "win_ntile_cume": (lambda t: t.part.select("p_partkey", F.ntile(4).over(W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("long").alias("q"), F.round(F.cume_dist().over(W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")), 6).alias("c")), "SELECT p_partkey, ntile(4) OVER w AS q, round(cume_dist() OVER w, 6) AS c FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)"),
    "win_lag_lead": (lambda t: events(t).select("event_id", F.lag("k").over(by_user()).alias("before"), F.lead("k").over(by_user()).alias("after")), f"SELECT event_id, lag(k) OVER u AS before, lead(k) OVER u AS after FROM {EV} {WIN}"),
    "win_first_last_nth": (lambda t: events(t).select("event_id", F.first("k").over(by_user()).alias("f"), F.nth_value("k", 2).over(by_user().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("n2")), f"SELECT event_id, first_value(k) OVER u AS f, nth_value(k, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS n2 FROM {EV} {WIN}"),
    "win_running_rows": (lambda t: events(t).select("event_id", F.sum("k").over(by_user().rowsBetween(-2, 0)).alias("s")), f"SELECT event_id, CAST(sum(k) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM {EV}"),
    "win_trailing_range": (lambda t: events(t).withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("sec").rangeBetween(-7 * 86400, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, CAST(floor(epoch(ts)) AS BIGINT) AS sec FROM events)"),
    "win_partition_total": (lambda t: t.orders.groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).withColumn("total", F.sum("n").over(W.partitionBy("o_orderstatus"))), "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(sum(count(*)) OVER (PARTITION BY o_orderstatus) AS BIGINT) AS total FROM orders GROUP BY o_orderstatus, o_orderpriority"),
    "sort_global_limit": (lambda t: t.orders.orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    "sort_nulls": (lambda t: t.documents.join(t.labels, "doc_id", "left").orderBy(F.col("quality").desc_nulls_last(), "doc_id").limit(30).select("doc_id", "quality"), "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id) ORDER BY quality DESC NULLS LAST, doc_id LIMIT 30"),
    "limit_offset": (lambda t: t.part.orderBy("p_partkey").offset(20).limit(10).select("p_partkey"), "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 20"),
    "topk_per_group": (lambda t: t.part.withColumn("r", F.row_number().over(W.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc(), "p_partkey"))).where("r <= 3").select("p_brand", "p_partkey"), "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3"),
    "fn_string": (lambda t: t.supplier.select("s_suppkey", F.lpad(F.reverse(F.substring("s_name", 1, 4)), 8, "*").alias("a"), F.initcap(F.lower("s_name")).alias("b"), F.levenshtein("s_name", F.lit("Supplier")).cast("long").alias("c"), F.md5("s_name").alias("d")), "SELECT s_suppkey, lpad(reverse(substr(s_name, 1, 4)), 8, '*') AS a, upper(left(s_name, 1)) || lower(substr(s_name, 2)) AS b, levenshtein(s_name, 'Supplier') AS c, md5(s_name) AS d FROM supplier"),
    "fn_url": (lambda t: t.pages.select("page_id", F.regexp_extract("url", r"^(\w+)://", 1).alias("scheme"), F.regexp_extract("url", r"[?&]page=(\d+)", 1).alias("page")), r"SELECT page_id, regexp_extract(url, '^(\w+)://', 1) AS scheme, regexp_extract(url, '[?&]page=(\d+)', 1) AS page FROM pages"),
    "fn_date": (lambda t: t.orders.select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("m"), F.datediff(F.lit("1998-12-31").cast("date"), F.col("o_orderdate").cast("date")).cast("long").alias("d")), "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m') AS m, date_diff('day', o_orderdate::DATE, DATE '1998-12-31') AS d FROM orders"),
    "fn_array": (lambda t: t.benchmark.select("item_id", F.size(F.array_distinct(F.split("text", " "))).cast("long").alias("n"), F.element_at(F.array_sort(F.split("text", " ")), -1).alias("top")), "SELECT item_id, len(list_distinct(string_split(text, ' '))) AS n, list_sort(string_split(text, ' '))[-1] AS top FROM benchmark"),
    "fn_json": (lambda t: t.events.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "pages_extract": (lambda t: t.pages.select("page_id", F.regexp_extract("html", "<title>([^<]*)", 1).alias("title"), (F.size(F.split("html", "<a ")) - 1).cast("long").alias("links")), "SELECT page_id, regexp_extract(html, '<title>([^<]*)', 1) AS title, len(string_split(html, '<a ')) - 1 AS links FROM pages"),
    "text_exact_dups": (lambda t: t.documents.groupBy(F.md5("text").alias("h")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).where("n > 1"), "SELECT md5(text) AS h, count(*) AS n, min(doc_id) AS first FROM documents GROUP BY 1 HAVING count(*) > 1"),
    "graph_degree": (lambda t: t.customer.groupBy("c_nationkey").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n")), "SELECT degree, count(*) AS n FROM (SELECT c_nationkey, count(*) AS degree FROM customer GROUP BY 1) GROUP BY 1"),
}

SETS = {"union_all": "unionAll", "union": "union", "intersect": "intersect", "intersect_all": "intersectAll", "except": "subtract", "except_all": "exceptAll"}


def _set(method: str):
    def run(t: Tables) -> DataFrame:
        a = t.orders.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("c"))
        b = t.orders.where("o_orderpriority like '1-%'").select(F.col("o_custkey").alias("c"))
        out = getattr(a, method)(b)
        return out.distinct() if method == "union" else out

    return run


for _name, _method in SETS.items():
    OPERATORS[f"set_{_name}"] = (_set(_method), f"SELECT o_custkey AS c FROM orders WHERE o_orderstatus = 'F' {_name.upper().replace('_', ' ')} SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1-%'")

#: approximate operators: rows only, their error is bounded in the tests
SKETCHES = {
    "sketch_hll_users": lambda t: t.events.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users")),
    "approx_distinct": lambda t: t.lineitem.agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")),
    "approx_quantiles": lambda t: t.orders.agg(F.percentile_approx("o_totalprice", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 1000).alias("q")),
}
