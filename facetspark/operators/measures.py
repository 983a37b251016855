"""Measures of facet lists, clusterings and studies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def eval_sim(pages: DataFrame, topics: DataFrame) -> DataFrame:
    """``query, a, b, sim`` for a <= b: mean topic similarity over all page pairs of two facets.

    ``pages`` has ``query, facet, doc_id``; ``topics`` has ``doc_id, topic, share`` in long form
    with unit norm per document. The mean over pairs is the product of the facets' mean vectors.
    """
    sums = pages.join(topics, "doc_id").groupBy("query", "facet", "topic").agg(F.sum("share").alias("x"))
    sizes = pages.groupBy("query", "facet").agg(F.count("*").alias("n"))
    mean = sums.join(sizes, ["query", "facet"]).select("query", "facet", "topic", (F.col("x") / F.col("n")).alias("x"))
    a, b = mean.select("query", "topic", F.col("facet").alias("a"), F.col("x").alias("xa")), mean.select("query", "topic", F.col("facet").alias("b"), F.col("x").alias("xb"))
    met = a.join(b, ["query", "topic"]).where("a <= b").groupBy("query", "a", "b").agg(F.sum(F.col("xa") * F.col("xb")).alias("sim"))
    names = pages.select("query", "facet").distinct()
    every = names.withColumnRenamed("facet", "a").join(names.withColumnRenamed("facet", "b"), "query").where("a <= b")
    return every.join(met, ["query", "a", "b"], "left").withColumn("sim", F.coalesce("sim", F.lit(0.0)))


def orthogonality(sims: DataFrame) -> DataFrame:
    """``query, asim, isim, nsim``: mean similarity between facets, within facets, and their ratio."""
    x = sims.groupBy("query").agg(F.avg(F.when(F.col("a") < F.col("b"), F.col("sim"))).alias("asim"), F.avg(F.when(F.col("a") == F.col("b"), F.col("sim"))).alias("isim"))
    return x.withColumn("nsim", F.try_divide("asim", "isim"))


def overlap(facet_hits: DataFrame, seed_hits: DataFrame, k: int, n: int) -> DataFrame:
    """``query, overlap``: share of the facets' top ``k`` pages among the seed's top ``n``."""
    mine = facet_hits.where(F.col("rank") <= k).select("query", "doc_id").distinct()
    top = seed_hits.where(F.col("rank") <= n).select("query", "doc_id", F.lit(1).alias("hit"))
    return mine.join(top, ["query", "doc_id"], "left").groupBy("query").agg((F.count("hit") / F.count("*")).alias("overlap"))


def pair_f(clusters: DataFrame, gold: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Pairwise precision, recall and F of a clustering, from counts; no pair is formed.

    Pairs together in a group of n are n(n-1)/2, so the counts of cells, clusters and gold
    classes give all three numbers.
    """
    by = by or []
    x = clusters.join(gold, ["query", "facet"])
    pairs = lambda *c: x.groupBy(*by, "query", *c).agg(F.count("*").alias("n")).groupBy(*by, "query").agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("_".join(("p", *c))))
    t = pairs("component", "gold").join(pairs("component"), [*by, "query"]).join(pairs("gold"), [*by, "query"])
    t = t.groupBy(*by).agg(F.sum("p_component_gold").alias("tp"), F.sum("p_component").alias("made"), F.sum("p_gold").alias("true")) if by else t.agg(F.sum("p_component_gold").alias("tp"), F.sum("p_component").alias("made"), F.sum("p_gold").alias("true"))
    return t.select(*by, F.try_divide("tp", "made").alias("precision"), F.try_divide("tp", "true").alias("recall"), F.try_divide(2 * F.col("tp"), F.col("made") + F.col("true")).alias("f"))


def breadth(facets: DataFrame, entities: DataFrame) -> DataFrame:
    """``stratum, entities, covered``: entities with a facet, per stratum and in total (null)."""
    has = facets.select("query").distinct().withColumn("has", F.lit(1))
    return entities.join(has, "query", "left").rollup("stratum").agg(F.count("*").alias("entities"), F.count("has").alias("covered"))


def sparsity(inst: DataFrame, nodes: DataFrame, high: int = 8, support: int = 5) -> DataFrame:
    """Per class node: members, members with ``high`` facets or more, with none, and facets of ``support`` members."""
    counts = inst.groupBy("query").agg(F.count("*").alias("n"))
    per = nodes.join(counts, "query", "left").groupBy("class", "property").agg(F.count("*").alias("members"), F.count_if(F.col("n") >= high).alias("many"), F.count_if(F.col("n").isNull()).alias("none"))
    shared = nodes.join(inst, "query").groupBy("class", "property", "facet").agg(F.count_distinct("query").alias("held")).groupBy("class", "property").agg(F.count_if(F.col("held") >= support).alias("shared"))
    return per.join(shared, ["class", "property"], "left").withColumn("shared", F.coalesce("shared", F.lit(0)))


def top_overlap(a: DataFrame, b: DataFrame, k: int = 10) -> DataFrame:
    """``query, shared``: common candidates among the top ``k`` of two score tables (``query, candidate, p``)."""
    top = lambda x: x.withColumn("r", F.row_number().over(W.partitionBy("query").orderBy(F.round("p", 9).desc(), "candidate"))).where(F.col("r") <= k).select("query", "candidate")
    return top(a).join(top(b), ["query", "candidate"]).groupBy("query").agg(F.count("*").alias("shared"))


def lists(ranked: DataFrame) -> DataFrame:
    """``query, facets``: a ranked list as one array."""
    return ranked.groupBy("query").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", F.col("group_label").alias("g")))), lambda x: x["g"]).alias("facets"))


def same_list(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: seeds, and seeds with the same list in both."""
    x, y = lists(a), lists(b).withColumnRenamed("facets", "others")
    return x.join(y, "query").agg(F.count("*").alias("seeds"), F.count_if(F.col("facets") == F.col("others")).alias("same"))


def preference(votes: DataFrame) -> DataFrame:
    """``domain`` (null: total) with responses and query verdicts for, even, against; for and against are compared, even is not."""
    q = votes.groupBy("domain", "query").agg(*(F.count_if(F.col("verdict") == v).alias(v.lower()) for v in "FEA"))
    v = F.when(F.col("f") > F.col("a"), "F").when(F.col("a") > F.col("f"), "A").otherwise("E")
    return q.withColumn("v", v).rollup("domain").agg(*(F.sum(c).alias(c) for c in "fea"), *(F.count_if(F.col("v") == c.upper()).alias(f"q{c}") for c in "fea"))


def paired_t(votes: DataFrame) -> DataFrame:
    """Mean of for minus against per query, its t statistic, and the number of queries."""
    q = votes.groupBy("domain", "query").agg((F.count_if(F.col("verdict") == "F") - F.count_if(F.col("verdict") == "A")).alias("d"))
    return q.agg(F.count("*").alias("queries"), F.avg("d").alias("mean"), (F.avg("d") / (F.stddev_samp("d") / F.sqrt(F.count("*")))).alias("t"))


def t_tail(t: float, df: int) -> float:
    """Two-sided p of Student's t, by the continued fraction of the incomplete beta function."""
    from math import exp, lgamma, log

    x, a, b = df / (df + t * t), df / 2, 0.5
    if x >= 1:
        return 1.0
    swap = x > (a + 1) / (a + b + 2)
    if swap:
        x, a, b = 1 - x, b, a
    front = exp(lgamma(a + b) - lgamma(a) - lgamma(b) + a * log(x) + b * log(1 - x)) / a
    c, d = 1.0, 1 / max(1 - (a + b) * x / (a + 1), 1e-300)
    h = d
    for i in range(1, 300):
        for term in (i * (b - i) * x / ((a + 2 * i - 1) * (a + 2 * i)), -(a + i) * (a + b + i) * x / ((a + 2 * i) * (a + 2 * i + 1))):
            d = 1 / (1 + term * d)
            c = 1 + term / c
            h *= c * d
        if abs(c * d - 1) < 1e-14:
            break
    p = front * h
    return 1 - p if swap else p


def relevance(votes: DataFrame) -> DataFrame:
    """``covered, domain`` (null: all domains) with yes and no responses, and pages by majority (ties count as no)."""
    pages = votes.groupBy("covered", "domain", "url").agg(F.count_if("relevant").alias("y"), F.count_if(~F.col("relevant")).alias("n"))
    sets = pages.groupingSets([["covered", "domain"], ["covered"]], "covered", "domain")
    return sets.agg(F.sum("y").alias("yes"), F.sum("n").alias("no"), F.count_if(F.col("y") > F.col("n")).alias("pages_yes"), F.count_if(F.col("y") <= F.col("n")).alias("pages_no"))
