"""Class-based propagation over the bipartite graph of seeds and class nodes."""

from __future__ import annotations

from math import inf

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def segment(queries: DataFrame, entities: DataFrame) -> DataFrame:
    """Seeds from texts: the longest leading entity, and the rest as property."""
    toks = F.split("query", " ")
    heads = queries.select("query", F.explode(F.transform(F.sequence(F.lit(1), F.size(toks)), lambda k: F.array_join(F.slice(toks, F.lit(1), k), " "))).alias("entity"))
    hit = heads.join(entities.select("entity").distinct(), "entity").groupBy("query").agg(F.max_by("entity", F.length("entity")).alias("entity"))
    rest = F.trim(F.substr("query", F.length("entity") + 1))
    return hit.select("query", "entity", F.when(rest != "", rest).alias("property"))


def classes_of(seeds: DataFrame, membership: DataFrame, alias: DataFrame | None = None, ambiguous: DataFrame | None = None) -> DataFrame:
    """``query, class, property``: class nodes of seeds, through aliases, without ambiguous tokens."""
    x = seeds.select("query", "entity", "property")
    if alias is not None:
        x = x.join(alias.select(F.col("alias").alias("entity"), F.col("entity").alias("main")), "entity", "left").withColumn("entity", F.coalesce("main", "entity")).drop("main")
    if ambiguous is not None:
        x = x.join(ambiguous.select(F.col("token").alias("entity")), "entity", "left_anti")
    return x.join(membership, "entity").select("query", "class", "property").distinct()


def graph_edges(nodes: DataFrame, k: float) -> DataFrame:
    """Directed edges ``source, target, weight``: 1 toward the class, ``k`` back."""
    target = F.concat_ws(" ", "class", "property")
    up = nodes.select(F.col("query").alias("source"), target.alias("target"), F.lit(1.0).alias("weight"))
    return up.unionByName(up.select(F.col("target").alias("source"), F.col("source").alias("target"), F.lit(float(k)).alias("weight")))


def class_scores(inst: DataFrame, nodes: DataFrame, mode: str = "indicator", weights: DataFrame | None = None) -> DataFrame:
    """First round: ``class, property, facet, p_class``. Members without the facet count as 0.

    ``mode`` "mean" averages scores, "indicator" takes the share of members that have the facet.
    ``weights`` (``query, weight``) replaces the equal edge weights.
    """
    w = nodes.join(weights, "query", "left").withColumn("weight", F.coalesce("weight", F.lit(0.0))) if weights is not None else nodes.withColumn("weight", F.lit(1.0))
    sizes = w.groupBy("class", "property").agg(F.sum("weight").alias("size"))
    value = F.col("score") if mode == "mean" else (F.col("score") > 0).cast("double")
    sums = w.join(inst, "query").groupBy("class", "property", "facet").agg(F.sum(value * F.col("weight")).alias("total"))
    return sums.join(sizes, ["class", "property"]).select("class", "property", "facet", F.coalesce(F.try_divide("total", "size"), F.lit(0.0)).alias("p_class"))


def smooth(inst: DataFrame, cls: DataFrame, nodes: DataFrame, k: float = 0.1) -> DataFrame:
    """Second round: ``query, facet, score``. A seed without own candidates takes its class's."""
    down = nodes.join(cls, ["class", "property"]).select("query", "class", "facet", "p_class")
    if k == 0:
        return inst.select("query", "facet", "score")
    # with several classes the mean over the seed's classes
    counts = nodes.groupBy("query").agg(F.count_distinct("class", "property").alias("classes"))
    mean = down.groupBy("query", "facet").agg(F.sum("p_class").alias("s")).join(counts, "query").select("query", "facet", (F.col("s") / F.col("classes")).alias("p_class"))
    both = inst.select("query", "facet", F.col("score").alias("p")).join(mean, ["query", "facet"], "full_outer")
    own, shared = F.coalesce("p", F.lit(0.0)), F.coalesce("p_class", F.lit(0.0))
    score = shared if k == inf else (own + F.lit(float(k)) * shared) / F.lit(1 + float(k))
    return both.select("query", "facet", score.alias("score")).where("score > 0")


def propagate(inst: DataFrame, nodes: DataFrame, k: float = 0.1, mode: str = "indicator") -> DataFrame:
    """Two rounds: class scores, then smoothing."""
    return smooth(inst, class_scores(inst, nodes, mode), nodes, k)


def iterate(inst: DataFrame, nodes: DataFrame, k: float = 0.1, tolerance: float = 1e-9, max_rounds: int = 50, cut=None) -> tuple[DataFrame, int]:
    """Label propagation until scores settle, for entities in several classes.

    Each round averages classes over the current scores and mixes them into the own scores;
    it contracts by k / (1 + k). With one class per entity the first round is a fixed point, so
    the loop ends after the second. ``cut`` stores a round's result (a written table or
    checkpoint); the driver sees one number per round.
    """
    current, rounds = inst.select("query", "facet", "score"), 0
    while rounds < max_rounds:
        rounds += 1
        after = smooth(inst, class_scores(current, nodes, "mean"), nodes, k)
        after = cut(after) if cut else after
        change = after.withColumnRenamed("score", "new").join(current, ["query", "facet"], "full_outer").agg(F.max(F.abs(F.coalesce("new", F.lit(0.0)) - F.coalesce("score", F.lit(0.0))))).first()[0]
        current = after
        if (change or 0.0) <= tolerance:
            break
    return current, rounds
