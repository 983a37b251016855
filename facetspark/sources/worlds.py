"""Worlds derived from the given tables: query logs, seeds, knowledge base, corpus.

Commerce world: one order is a session, one line a logged query, one line a document.
Click world: events. Dialogue world: user turns of conversations.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.functions.textkit import analyzed


class Tables:
    """The given Parquet tables of one folder, read lazily with only the columns a plan needs."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def __getattr__(self, name: str) -> DataFrame:
        if name.startswith("_"):
            raise AttributeError(name)
        return self.spark.read.parquet(f"{self.folder}/{name}.parquet")


def commerce_lines(t: Tables) -> DataFrame:
    """Order lines with their dimension words and step within the order."""
    o = t.orders.select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    c = t.customer.select("c_custkey", "c_nationkey", "c_mktsegment")
    n = t.nation.select("n_nationkey", "n_name", "n_regionkey")
    p = t.part.select("p_partkey", "p_name", "p_brand", "p_type", "p_size")
    s = t.supplier.select("s_suppkey", "s_name")
    owners = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    in_order = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    lines = t.lineitem.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    # orders come last: lines are dealt by order then, as the window wants them
    joined = lines.join(p, F.col("l_partkey") == F.col("p_partkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(owners, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.select(
        "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "o_custkey", "o_orderdate", "p_size",
        F.row_number().over(in_order).cast("long").alias("step"),
        F.lower("n_name").alias("ent"), F.lower("c_mktsegment").alias("prop"), F.lower("p_name").alias("name"),
        F.split_part(F.lower("p_name"), F.lit(" "), F.lit(1)).alias("adj"), F.split_part(F.lower("p_name"), F.lit(" "), F.lit(2)).alias("noun"),
        F.lower("p_type").alias("type"), F.lower("p_brand").alias("brand"), F.lower("s_name").alias("supp"),
        F.lower("o_orderpriority").alias("priority"),
    )


def commerce_log(t: Tables, lines: DataFrame | None = None) -> DataFrame:
    """``user_id, session_id, step, ts, query``; one row per logged query."""
    x = commerce_lines(t) if lines is None else lines
    turn = F.col("step") % 4
    words = lambda *c: F.concat_ws(" ", *c)
    text = (
        F.when(F.col("step") == 1, F.col("ent"))
        .when(F.col("step") == 2, F.when(F.col("l_orderkey") % 7 == 0, F.col("prop")).otherwise(words("ent", "prop")))
        .when(turn == 3, F.concat(words("ent", "prop", "noun"), F.when(F.col("l_linenumber") % 2 == 1, "s").otherwise("")))
        .when(turn == 0, words("ent", "prop", "type"))
        .when(turn == 1, F.when(F.col("l_linenumber") % 2 == 0, words("ent", "noun", "adj")).otherwise(words("ent", "name")))
        .when(F.col("l_suppkey") % 4 == 0, F.col("name"))
        .when(F.col("l_suppkey") % 4 == 1, F.col("brand"))
        .when(F.col("l_suppkey") % 4 == 2, words("brand", "noun"))
        .otherwise(F.col("supp"))
    )
    return x.select(
        F.col("o_custkey").alias("user_id"), F.col("l_orderkey").alias("session_id"), "step",
        (F.col("o_orderdate") + F.make_dt_interval(F.lit(0), F.lit(0), F.col("step").cast("int"))).alias("ts"), text.alias("query"),
    )


def click_log(t: Tables) -> DataFrame:
    """Events as queries: the type, with the property value for odd event numbers."""
    k = F.get_json_object("props", "$.k")
    text = F.when(F.col("event_id") % 2 == 0, F.col("event_type")).otherwise(F.concat_ws(" k", "event_type", k))
    return t.events.select("user_id", "event_id", "ts", text.alias("query"))


def dialogue_log(t: Tables) -> DataFrame:
    """User turns; the query is the first few tokens, longer in later turns."""
    toks = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}_#]+"), lambda x: x != "")
    take = F.least(F.lit(1) + F.floor(F.col("turn") / 2), F.lit(4)).cast("int")
    return t.conversations.where("role = 'user'").select(F.col("conv_id").alias("user_id"), F.col("conv_id").alias("session_id"), F.col("turn").alias("step"), F.array_join(F.slice(toks, F.lit(1), take), " ").alias("query"))


def seeds(t: Tables) -> DataFrame:
    """The 125 nation and segment seeds: ``query, entity, property, domain``; domain is the region."""
    n = t.nation.join(t.region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.lower("n_name").alias("entity"), F.lower("r_name").alias("domain"))
    s = t.customer.select(F.lower("c_mktsegment").alias("property")).distinct()
    return n.crossJoin(s).select(F.concat_ws(" ", "entity", "property").alias("query"), "entity", "property", "domain")  # 25 x 5 names


def membership(t: Tables) -> DataFrame:
    """Single-class memberships ``entity, class``: nations in regions, nouns and adjectives of part names, and so on."""
    part = t.part.select(F.lower("p_name").alias("name"), F.lower("p_type").alias("type"), F.lower("p_brand").alias("brand"))
    noun = F.split_part("name", F.lit(" "), F.lit(2))
    rows = [
        t.nation.join(t.region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.lower("n_name"), F.lower("r_name")),
        part.select("name", noun),
        part.select(F.split_part("name", F.lit(" "), F.lit(1)), F.lit("adjective")),
        part.select("type", F.lit("type")),
        part.select("brand", F.lit("brand")),
        t.customer.select(F.lower("c_mktsegment"), F.lit("segment")),
        t.supplier.join(t.nation, F.col("s_nationkey") == F.col("n_nationkey")).select(F.lower("s_name"), F.lower("n_name")),
    ]
    out = None
    for r in rows:
        r = r.toDF("entity", "class")
        out = r if out is None else out.unionByName(r)
    return out.distinct()


def ambiguous(t: Tables) -> DataFrame:
    """Tokens that stand in more than one class."""
    return membership(t).groupBy("entity").agg(F.count_distinct("class").alias("n")).where("n > 1").select(F.col("entity").alias("token"))


def aliases(t: Tables) -> DataFrame:
    """``alias, entity``: swapped part names, plural nouns, short nation names."""
    name = t.part.select(F.lower("p_name").alias("name")).distinct()
    adj, noun = F.split_part("name", F.lit(" "), F.lit(1)), F.split_part("name", F.lit(" "), F.lit(2))
    n = t.nation.select(F.lower("n_name").alias("entity"))
    return (
        name.select(F.concat_ws(" ", noun, adj).alias("alias"), F.col("name").alias("entity"))
        .unionByName(name.select(F.concat(noun, F.lit("s")).alias("alias"), noun.alias("entity")))
        .unionByName(n.select(F.replace("entity", F.lit("nation_"), F.lit("n")).alias("alias"), "entity"))
        .distinct()
    )


def attributes(t: Tables) -> DataFrame:
    """``class, attribute, n``: attribute values of the classes' rows, as an infobox would list them."""
    c = t.customer.join(t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    part = t.part.select(F.split_part(F.lower("p_name"), F.lit(" "), F.lit(2)).alias("class"), F.lower("p_brand").alias("brand"), F.lower("p_type").alias("type"))
    wide = part.unpivot(["class"], ["brand", "type"], "kind", "attribute").select("class", "attribute")
    rows = c.select(F.lower("r_name").alias("class"), F.lower("c_mktsegment").alias("attribute")).unionByName(wide)
    return rows.groupBy("class", "attribute").agg(F.count("*").alias("n"))


def corpus(t: Tables, lines: DataFrame | None = None) -> DataFrame:
    """One document per order line: ``doc_id, head, snippet, body``."""
    x = commerce_lines(t) if lines is None else lines
    tag = lambda letter, c: F.concat(F.lit(letter), F.col(c).cast("string"))
    snippet = F.concat_ws(" ", "ent", "prop", "type", "brand", tag("s", "l_suppkey"), tag("z", "p_size"), F.element_at(F.split("priority", "-"), 2))
    body = F.concat_ws(" ", snippet, tag("c", "o_custkey"), tag("p", "l_partkey"), F.concat(F.lit("m"), F.date_format("o_orderdate", "yyyyMM")))
    return x.select((F.col("l_orderkey") * 100 + F.col("step")).alias("doc_id"), F.col("name").alias("head"), snippet.alias("snippet"), body.alias("body"))


def gold_intent(facets: DataFrame) -> DataFrame:
    """Gold cluster of a facet key: its words folded and sorted."""
    return facets.withColumn("gold", F.array_join(F.array_sort(analyzed(F.col("facet"))), " "))


def preference_votes(t: Tables) -> DataFrame:
    """Stand-in votes ``domain, query, rater, verdict``: they test arithmetic, not quality."""
    x = t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).join(t.customer, F.col("o_custkey") == F.col("c_custkey"))
    x = x.join(t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    verdict = F.when(F.col("l_returnflag") == "R", "F").when(F.col("l_returnflag") == "N", "E").otherwise("A")
    return x.select(F.lower("r_name").alias("domain"), F.lower("n_name").alias("query"), F.col("l_suppkey").alias("rater"), verdict.alias("verdict"))


def relevance_votes(t: Tables) -> DataFrame:
    """Stand-in judgements ``domain, url, rater, covered, relevant``."""
    x = t.lineitem.join(t.part, F.col("l_partkey") == F.col("p_partkey"))
    return x.select(F.lower("p_type").alias("domain"), F.col("l_partkey").alias("url"), F.col("l_suppkey").alias("rater"), (F.col("p_size") <= 25).alias("covered"), (F.col("l_linestatus") == "F").alias("relevant"))
