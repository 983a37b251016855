"""Groups of facets that name different entities of one class."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.functions.textkit import label, phrases


def match_entities(facets: DataFrame, membership: DataFrame, alias: DataFrame | None = None, ambiguous: DataFrame | None = None, ambiguity: str = "drop") -> DataFrame:
    """``query, facet, entity, class``: the longest known entity in each facet, and its class.

    "drop" leaves facets with an ambiguous entity ungrouped; "vote" gives it the sense that
    most of the seed's facets support, the smaller name among equals.
    """
    x = facets.select("query", "facet", label(F.col("facet")).alias("words"))
    parts = x.select("query", "facet", F.explode(F.array_distinct(F.concat(F.array("words"), phrases(F.col("words"))))).alias("phrase"))
    if alias is not None:
        parts = parts.join(alias.select(F.col("alias").alias("phrase"), F.col("entity").alias("main")), "phrase", "left")
    else:
        parts = parts.withColumn("main", F.lit(None).cast("string"))
    known = parts.select("query", "facet", F.coalesce("main", "phrase").alias("entity"), F.length("phrase").alias("size")).join(membership, "entity")
    longest = known.groupBy("query", "facet").agg(F.max("size").alias("size"))
    senses = known.join(longest, ["query", "facet", "size"]).select("query", "facet", "entity", "class").distinct()
    if ambiguity == "vote":
        support = senses.groupBy("query", "class").agg(F.count_distinct("facet").alias("votes"))
        voted = senses.join(support, ["query", "class"])
        return voted.groupBy("query", "facet").agg(F.min(F.struct((-F.col("votes")).alias("v"), "class", "entity")).alias("x")).select("query", "facet", "x.entity", "x.class")
    if ambiguous is not None:
        senses = senses.join(ambiguous.select(F.col("token").alias("entity")), "entity", "left_anti")
    return senses.groupBy("query", "facet").agg(F.min(F.struct("class", "entity")).alias("x")).select("query", "facet", "x.entity", "x.class")


def by_category(scored: DataFrame, matches: DataFrame, min_size: int = 2) -> DataFrame:
    """``query, group_label, kind, score, members``: groups of ``min_size`` entities or more.

    Members stay listed, best first; a group's score is its best member's.
    """
    sizes = matches.groupBy("query", "class").agg(F.count_distinct("entity").alias("n")).where(F.col("n") >= min_size)
    grouped = matches.join(sizes, ["query", "class"]).select("query", "facet", F.col("class").alias("group"))
    x = scored.select("query", "facet", "score").join(grouped, ["query", "facet"], "left")
    x = x.select("query", F.coalesce("group", "facet").alias("group_label"), F.when(F.col("group").isNull(), "single").otherwise("group").alias("kind"), "facet", "score")
    order = F.struct((-F.round("score", 9)).alias("s"), F.col("facet").alias("f"))
    return x.groupBy("query", "group_label", "kind").agg(F.max("score").alias("score"), F.transform(F.array_sort(F.collect_list(order)), lambda m: m["f"]).alias("members"))


def member_label(groups: DataFrame) -> DataFrame:
    """Adds ``shown``: the best member, and how many others a group stands for."""
    shown = F.when(F.col("kind") == "single", label(F.col("group_label"))).otherwise(F.concat(label(F.col("members")[0]), F.lit(" (and "), F.size("members") - 1, F.lit(" more)")))
    return groups.withColumn("shown", shown)
