"""Sinks, functions, sketches, lateral and user functions around the methods, each with its SQL where there is one."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from facetspark.operators.measures import t_tail
from facetspark.sources.storage import scratch, ship
from facetspark.sources.worlds import Tables


def round_trip(rows: DataFrame, kind: str) -> DataFrame:
    """The rows after a write to and a read from files of the kind, in the shared folder."""
    path = scratch(rows.sparkSession, kind)
    rows.write.format(kind).save(path)
    reader = rows.sparkSession.read.format(kind)
    return (reader if kind == "text" else reader.schema(rows.schema)).load(path)


def partitioned(rows: DataFrame, *columns: str) -> DataFrame:
    """The rows from files split by columns, so that filters on those read some folders only."""
    path = scratch(rows.sparkSession, "partitioned")
    rows.write.partitionBy(*columns).parquet(path)
    return rows.sparkSession.read.schema(rows.schema).parquet(path)


def bucketed(rows: DataFrame, column: str, buckets: int = 8) -> DataFrame:
    """The rows as a table bucketed and sorted by a column: aggregations and joins on it need no shuffle."""
    path = scratch(rows.sparkSession, "bucketed")
    name = "bucketed_" + path.rsplit("-", 1)[1]
    rows.write.bucketBy(buckets, column).sortBy(column).option("path", path).saveAsTable(name)
    return rows.sparkSession.table(name)


def item_words(t: Tables) -> DataFrame:
    return t.benchmark.select("item_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("word")).where("word <> ''")


WORDS = "(SELECT * FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS word FROM benchmark) WHERE word <> '')"


def _bigrams(t: Tables) -> DataFrame:
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
    grams = F.zip_with(F.slice(words, 1, F.size(words) - 1), F.slice(words, 2, F.size(words)), lambda a, b: F.concat_ws(" ", a, b))
    return t.benchmark.where(F.size(words) > 1).select(F.explode(grams).alias("gram")).groupBy("gram").agg(F.count("*").alias("n"))


BIGRAMS = """SELECT gram, count(*) AS n FROM (SELECT unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS gram
    FROM (SELECT list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM benchmark)) GROUP BY 1"""


def _tfidf(t: Tables) -> DataFrame:
    tf = item_words(t).groupBy("item_id", "word").agg(F.count("*").alias("tf"))
    df = tf.groupBy("word").agg(F.count("*").alias("df"))
    n = t.benchmark.agg(F.count("*").alias("n"))
    value = F.round(F.col("tf") * F.ln((1 + F.col("n")) / (1 + F.col("df"))), 6)
    return tf.join(df, "word").crossJoin(F.broadcast(n)).select("item_id", "word", value.alias("tfidf"))  # one row


TFIDF = f"""WITH tf AS (SELECT item_id, word, count(*) AS tf FROM {WORDS} GROUP BY ALL), df AS (SELECT word, count(*) AS df FROM tf GROUP BY word)
    SELECT item_id, word, round(tf * ln((1 + (SELECT count(*) FROM benchmark)) / (1 + df)), 6) AS tfidf FROM tf JOIN df USING (word)"""


def _lateral(t: Tables) -> DataFrame:
    return t.spark.sql("SELECT n.n_name, p.part FROM {nation} n, LATERAL (SELECT explode(split(n.n_name, '_')) AS part) p", nation=t.nation)


def _exists(t: Tables) -> DataFrame:
    return t.spark.sql("SELECT o_orderkey FROM {o} WHERE EXISTS (SELECT 1 FROM {l} WHERE l_orderkey = o_orderkey AND l_returnflag = 'R' AND l_quantity > 45)", o=t.orders, l=t.lineitem)


def _macro(t: Tables) -> DataFrame:
    t.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION plain_words(x STRING) RETURNS STRING RETURN trim(regexp_replace(lower(x), '[^a-z0-9]+', ' '))")
    return t.spark.sql("SELECT s_suppkey, plain_words(s_name) AS name FROM {s}", s=t.supplier)


def two_sided_p(t: Column, df: Column) -> Column:
    """Two-sided p of Student's t, by row of statistics."""

    def tail(t: pd.Series, df: pd.Series) -> pd.Series:
        return pd.Series([t_tail(a, int(b)) if a is not None and b > 0 and not np.isnan(a) else None for a, b in zip(t, df, strict=True)], dtype="float64")

    ship(SparkSession.active())
    return F.pandas_udf(tail, DoubleType())(t, df)


def pair_f_of(cluster: Column, gold: Column) -> Column:
    """Pairwise F of one clustering, as a grouped aggregate."""

    def score(cluster: pd.Series, gold: pd.Series) -> float:
        def pairs(keys):
            n = keys.value_counts()
            return float((n * (n - 1) / 2).sum())

        made, true, both = pairs(cluster), pairs(gold), pairs(cluster.astype(str) + "\0" + gold.astype(str))
        return 2 * both / (made + true) if made + true else 0.0

    return F.pandas_udf(score, DoubleType())(cluster, gold)


def _pair_f(t: Tables) -> DataFrame:
    x = t.part.select(F.lower("p_type").alias("kind"), F.col("p_brand"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("noun"))
    return x.groupBy("kind").agg(F.round(pair_f_of(F.col("p_brand"), F.col("noun")), 6).alias("f"))


PAIR_F = """WITH x AS (SELECT lower(p_type) AS kind, p_brand, split_part(p_name, ' ', 2) AS noun FROM part),
    made AS (SELECT kind, sum(n * (n - 1) / 2) AS p FROM (SELECT kind, count(*) AS n FROM x GROUP BY kind, p_brand) GROUP BY kind),
    gold AS (SELECT kind, sum(n * (n - 1) / 2) AS p FROM (SELECT kind, count(*) AS n FROM x GROUP BY kind, noun) GROUP BY kind),
    hit AS (SELECT kind, sum(n * (n - 1) / 2) AS p FROM (SELECT kind, count(*) AS n FROM x GROUP BY kind, p_brand, noun) GROUP BY kind)
    SELECT kind, round(2 * hit.p / (made.p + gold.p), 6) AS f FROM made JOIN gold USING (kind) JOIN hit USING (kind)"""


class TokenPhrases:
    """Table function: all contiguous sub-phrases of a text up to a length."""

    def eval(self, text: str, most: int) -> Iterator[tuple[str]]:
        words = (text or "").split(" ")
        for i in range(len(words)):
            for j in range(i + 1, min(i + most, len(words)) + 1):
                yield (" ".join(words[i:j]),)


def _phrases(t: Tables) -> DataFrame:
    ship(t.spark)
    t.spark.udtf.register("token_phrases", F.udtf(TokenPhrases, returnType="phrase string"))
    names = t.part.select(F.lower("p_name").alias("name")).distinct()
    return t.spark.sql("SELECT phrase, count(*) AS n FROM {names}, LATERAL token_phrases(name, 2) GROUP BY phrase", names=names)


PHRASES = """SELECT phrase, count(*) AS n FROM (SELECT unnest(list_concat(w, list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]))) AS phrase
    FROM (SELECT string_split(name, ' ') AS w FROM (SELECT DISTINCT lower(p_name) AS name FROM part))) GROUP BY 1"""


def count_min(rows: DataFrame, key: str, depth: int = 5, width: int = 4096) -> DataFrame:
    """``key, estimate``: a count-min sketch as rows of counters, and each key's least counter.

    An estimate is never below the count, and above it by more than e / width of all rows with
    probability exp(-depth).
    """
    cells = F.explode(F.array(*(F.struct(F.lit(d).alias("d"), F.pmod(F.xxhash64(F.col(key), F.lit(d)), F.lit(width)).alias("cell")) for d in range(depth))))
    sketch = rows.select(cells.alias("c")).groupBy("c.d", "c.cell").agg(F.count("*").alias("n"))
    keys = rows.select(key).distinct().select(key, cells.alias("c")).select(key, "c.d", "c.cell")
    return keys.join(sketch, ["d", "cell"]).groupBy(key).agg(F.min("n").alias("estimate"))


def _theta(t: Tables) -> DataFrame:
    """Users of two event kinds, and the share of common ones, from theta sketches."""
    two = t.events.groupBy("event_type").agg(F.theta_sketch_agg("user_id").alias("s"))
    a, b = two.select(F.col("event_type").alias("a"), F.col("s").alias("sa")), two.select(F.col("event_type").alias("b"), F.col("s").alias("sb"))
    both = F.theta_sketch_estimate(F.theta_intersection("sa", "sb"))
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", both.alias("common"), F.theta_sketch_estimate(F.theta_union("sa", "sb")).alias("either"))  # a row for each event type


def _kll(t: Tables) -> DataFrame:
    sketch = t.orders.groupBy("o_orderstatus").agg(F.kll_sketch_agg_double("o_totalprice").alias("s"))
    return sketch.select("o_orderstatus", *(F.kll_sketch_get_quantile_double("s", F.lit(q)).alias(f"q{int(100 * q)}") for q in (0.25, 0.5, 0.75)))


DAY = "strftime(o_orderdate, '%Y-%m-%d')"
OPERATORS: dict[str, tuple] = {
    "roundtrip_csv": (lambda t: round_trip(t.nation, "csv"), "SELECT * FROM nation"),
    "roundtrip_json": (lambda t: round_trip(t.events.select("event_id", "event_type", "value"), "json"), "SELECT event_id, event_type, value FROM events"),
    "roundtrip_orc": (lambda t: round_trip(t.part, "orc"), "SELECT * FROM part"),
    "roundtrip_text": (lambda t: round_trip(t.supplier.select(F.col("s_name").alias("value")), "text"), "SELECT s_name AS value FROM supplier"),
    "partitioned_log_prune": (
        lambda t: partitioned(t.orders.select("o_orderkey", "o_orderpriority", "o_orderstatus"), "o_orderstatus").where("o_orderstatus = 'P'").groupBy("o_orderpriority").agg(F.count("*").alias("n")),
        "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderstatus = 'P' GROUP BY 1",
    ),
    "bucketed_postings": (lambda t: bucketed(item_words(t), "word").groupBy("word").agg(F.count_distinct("item_id").alias("df")), f"SELECT word, count(DISTINCT item_id) AS df FROM {WORDS} GROUP BY word"),
    "exists_semi": (_exists, "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R' AND l_quantity > 45)"),
    "join_theta_contains": (
        lambda t: t.nation.join(F.broadcast(t.region), F.contains("n_name", F.concat(F.lit("_"), F.col("r_regionkey").cast("string")))).select("n_name", "r_name"),  # five regions
        "SELECT n_name, r_name FROM nation JOIN region ON contains(n_name, '_' || r_regionkey)",
    ),
    "join_cross_sigma": (lambda t: t.region.select("r_name").crossJoin(t.spark.range(1, 20).select((F.col("id") * 5).alias("percent"))), "SELECT r_name, p * 5 AS percent FROM region, range(1, 20) g(p)"),
    "join_self_pairs": (
        lambda t: t.nation.select("n_regionkey", F.col("n_name").alias("a")).join(t.nation.select("n_regionkey", F.col("n_name").alias("b")), "n_regionkey").where("a < b").select("a", "b"),
        "SELECT x.n_name AS a, y.n_name AS b FROM nation x JOIN nation y ON x.n_regionkey = y.n_regionkey AND x.n_name < y.n_name",
    ),
    "join_lateral_phrases": (_lateral, "SELECT n_name, unnest(string_split(n_name, '_')) AS part FROM nation"),
    "fn_regex": (
        lambda t: t.pages.select("page_id", F.regexp_replace(F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1), "[0-9]+", "#").alias("host"), F.col("url").rlike("[?]").alias("asks"), F.regexp_count("url", F.lit("/")).cast("long").alias("slashes")),
        "SELECT page_id, regexp_replace(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '[0-9]+', '#', 'g') AS host, contains(url, '?') AS asks, len(url) - len(replace(url, '/', '')) AS slashes FROM pages",
    ),
    "fn_math": (
        lambda t: t.part.select("p_partkey", F.round(F.sqrt("p_retailprice"), 4).alias("root"), F.round(F.ln("p_size"), 4).alias("log"), F.greatest("p_size", F.lit(20)).cast("long").alias("most"), F.pmod(-F.col("p_size"), F.lit(7)).cast("long").alias("rest"), F.signum(F.col("p_size") - 25).cast("long").alias("sign")),
        "SELECT p_partkey, round(sqrt(p_retailprice), 4) AS root, round(ln(p_size), 4) AS log, greatest(p_size, 20)::BIGINT AS most, (((-p_size) % 7 + 7) % 7)::BIGINT AS rest, sign(p_size - 25)::BIGINT AS sign FROM part",
    ),
    "fn_hof": (
        lambda t: t.benchmark.select("item_id", F.aggregate(F.transform(F.split("text", " "), F.length), F.lit(0), lambda a, b: a + b).cast("long").alias("letters"), F.exists(F.split("text", " "), lambda w: F.length(w) > 12).alias("long_word")),
        "SELECT item_id, list_sum(list_transform(string_split(text, ' '), lambda w: length(w)))::BIGINT AS letters, list_bool_or(list_transform(string_split(text, ' '), lambda w: length(w) > 12)) AS long_word FROM benchmark",
    ),
    "fn_map": (
        lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m")).select("l_returnflag", F.try_element_at("m", F.lit("F")).alias("f"), F.size(F.map_keys("m")).cast("long").alias("kinds")),
        "SELECT l_returnflag, nullif(count(CASE WHEN l_linestatus = 'F' THEN 1 END), 0) AS f, count(DISTINCT l_linestatus) AS kinds FROM lineitem GROUP BY 1",
    ),
    "fn_struct": (
        lambda t: t.customer.select(F.struct("c_custkey", F.struct("c_nationkey", "c_mktsegment").alias("home")).alias("c")).select(F.col("c").withField("home.label", F.concat_ws("/", "c.home.c_nationkey", "c.home.c_mktsegment")).alias("c")).select("c.c_custkey", "c.home.label"),
        "SELECT c_custkey, c_nationkey || '/' || c_mktsegment AS label FROM customer",
    ),
    "fn_variant": (lambda t: t.events.select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "long").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "text_tokens": (lambda t: item_words(t).groupBy("item_id").agg(F.count("*").alias("n"), F.count_distinct("word").alias("words")), f"SELECT item_id, count(*) AS n, count(DISTINCT word) AS words FROM {WORDS} GROUP BY item_id"),
    "text_ngrams": (_bigrams, BIGRAMS),
    "text_tfidf": (_tfidf, TFIDF),
    "udf_sql_macro": (_macro, "SELECT s_suppkey, trim(regexp_replace(lower(s_name), '[^a-z0-9]+', ' ', 'g')) AS name FROM supplier"),
    "udaf_pair_f": (_pair_f, PAIR_F),
    "udtf_phrases": (_phrases, PHRASES),
    "sketch_cms_heavy_queries": (lambda t: count_min(t.events, "event_type").where("estimate > 0"), None),
    "sketch_theta_overlap": (_theta, None),
    "sketch_kll_prices": (_kll, None),
}
