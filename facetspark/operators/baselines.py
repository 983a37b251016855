"""Systems to compare with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.operators.retrieve import Index


def _top(x: DataFrame, n: int) -> DataFrame:
    order = F.row_number().over(W.partitionBy("query").orderBy(F.round("score", 9).desc(), "group_label"))
    return x.withColumn("rank", order).where(F.col("rank") <= n).select("query", "rank", "group_label", F.round("score", 9).alias("score"))


def related(instance: DataFrame, n: int = 8) -> DataFrame:
    """Related searches: the best candidates of the log alone, without class, clusters or groups."""
    return _top(instance.select("query", F.col("candidate").alias("group_label"), F.col("p_inst").alias("score")), n)


def cluster_labels(seed_hits: DataFrame, index: Index, own_terms: DataFrame, n: int = 8) -> DataFrame:
    """Labels of clusters of the seed's result pages: the words that are frequent there and rare elsewhere."""
    pages = seed_hits.select("query", "doc_id")
    words = pages.join(index.forward.select("doc_id", "words"), "doc_id").select("query", F.explode(F.map_keys("words")).alias("term")).groupBy("query", "term").agg(F.count("*").alias("here"))
    words = words.join(own_terms, ["query", "term"], "left_anti").join(index.terms, "term").crossJoin(F.broadcast(index.totals))
    return _top(words.select("query", F.col("term").alias("group_label"), (F.col("here") * F.ln((1 + F.col("n")) / (1 + F.col("df")))).alias("score")), n)


def navigational(classes: DataFrame, nodes: DataFrame, supported: DataFrame, generic_share: float = 0.8, n: int = 8) -> DataFrame:
    """Class-level suggestions in the supported classes; facets that most classes have are generic and go."""
    total = classes.select("class", "property").distinct().agg(F.count("*").alias("total"))
    spread = classes.groupBy("facet").agg(F.count("*").alias("held")).crossJoin(F.broadcast(total))
    generic = spread.where(F.col("held") > generic_share * F.col("total")).select("facet")
    rows = nodes.join(supported, "class", "left_semi").join(classes.join(generic, "facet", "left_anti"), ["class", "property"])
    return _top(rows.select("query", F.col("facet").alias("group_label"), F.col("p_class").alias("score")), n)


def kb_attributes(nodes: DataFrame, attributes: DataFrame, n: int = 8) -> DataFrame:
    """The most frequent attribute values of the seed's class."""
    return _top(nodes.join(attributes, "class").select("query", F.col("attribute").alias("group_label"), F.col("n").cast("double").alias("score")), n)
