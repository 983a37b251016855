"""Uses of ranked facets: related lists, categories of results, triggers, query sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.functions.textkit import label


def related_list(ranked: DataFrame) -> DataFrame:
    """``query, related``: shown labels in rank order, joined by bars."""
    items = F.array_sort(F.collect_list(F.struct("rank", label(F.col("group_label")).alias("l"))))
    return ranked.groupBy("query").agg(F.array_join(F.transform(items, lambda x: x["l"]), " | ").alias("related"))


def facet_sets(ranked: DataFrame, groups: DataFrame, labels: DataFrame) -> DataFrame:
    """``query, rank, facet``: each ranked entry as the set of all facets behind it."""
    members = ranked.join(groups.select("query", "group_label", F.explode("members").alias("cluster_label")), ["query", "group_label"])
    return members.join(labels.select("query", "cluster_label", "facet"), ["query", "cluster_label"]).select("query", "rank", "facet")


def categorize(seed_hits: DataFrame, facet_pages: DataFrame, pairs: DataFrame) -> DataFrame:
    """``query, doc_id, facet``: each page of the seed under the facet whose pages fit it best."""
    both = pairs.unionByName(pairs.where("d1 < d2").select("query", F.col("d2").alias("d1"), F.col("d1").alias("d2"), "dsim"))
    near = seed_hits.select("query", F.col("doc_id").alias("d1")).join(both, ["query", "d1"]).join(facet_pages.select("query", "facet", F.col("doc_id").alias("d2")), ["query", "d2"])
    best = near.groupBy("query", F.col("d1").alias("doc_id"), "facet").agg(F.round(F.max("dsim"), 9).alias("fit"))
    return best.groupBy("query", "doc_id").agg(F.min(F.struct((-F.col("fit")).alias("f"), "facet")).alias("x")).select("query", "doc_id", "x.facet")


def triggers(ranked: DataFrame, rules: DataFrame) -> DataFrame:
    """``query, gadget``: gadgets whose keyword is a word of some ranked facet."""
    words = ranked.select("query", F.explode(F.split(label(F.col("group_label")), " ")).alias("keyword"))
    return words.join(F.broadcast(rules), "keyword").select("query", "gadget").distinct()  # rules are a short hand-made list
