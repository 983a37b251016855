"""Similarity of facets through the pages that they retrieve."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.functions.textkit import analyzed, label
from facetspark.operators.retrieve import Index

DIGITS = 9


def doc_vectors(hits: DataFrame, index: Index, strip_seed: bool = True) -> DataFrame:
    """``query, doc_id, term, weight``: unit TF/IDF vectors of a seed's pages.

    ``strip_seed`` leaves the seed's own words out, which all its pages share.
    """
    wanted = hits.select("query", "doc_id").distinct()
    x = wanted.join(index.forward.select("doc_id", "words"), "doc_id").select("query", "doc_id", F.explode("words").alias("term", "tf"))
    if strip_seed:
        own = hits.select("query").distinct().select("query", F.explode(F.array_distinct(analyzed(F.col("query")))).alias("term"))
        x = x.join(own, ["query", "term"], "left_anti")
    x = x.join(index.terms, "term").crossJoin(F.broadcast(index.totals))
    x = x.select("query", "doc_id", "term", (F.col("tf") * F.ln((1 + F.col("n")) / (1 + F.col("df")))).alias("w"))
    norm = x.groupBy("query", "doc_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return x.join(norm, ["query", "doc_id"]).where("norm > 0").select("query", "doc_id", "term", (F.col("w") / F.col("norm")).alias("weight"))


def doc_pairs(vectors: DataFrame) -> DataFrame:
    """``query, d1, d2, dsim`` with d1 <= d2, once per page pair however many facets share it."""
    a = vectors.select("query", "term", F.col("doc_id").alias("d1"), F.col("weight").alias("w1"))
    b = vectors.select("query", "term", F.col("doc_id").alias("d2"), F.col("weight").alias("w2"))
    return a.join(b, ["query", "term"]).where("d1 <= d2").groupBy("query", "d1", "d2").agg(F.sum(F.col("w1") * F.col("w2")).alias("dsim"))


def facet_sim(hits: DataFrame, vectors: DataFrame, method: str = "best_match") -> DataFrame:
    """``query, a, b, sim`` for facet pairs a < b; pairs without any shared word are left out (0).

    best_match: mean over pages of their best match on the other side, averaged over both
    sides. all_pairs: mean over all page pairs. concat: cosine of the summed page vectors.
    """
    if method == "concat":
        return _concat_sim(hits, vectors)
    half = doc_pairs(vectors)
    pairs = half.unionByName(half.where("d1 < d2").select("query", F.col("d2").alias("d1"), F.col("d1").alias("d2"), "dsim"))
    sizes = hits.groupBy("query", "facet").agg(F.count("*").alias("n"))
    # per page and other facet first, so shared pages are matched once
    near = pairs.join(hits.select("query", F.col("facet").alias("b"), F.col("doc_id").alias("d2")), ["query", "d2"]).groupBy("query", "d1", "b")
    near = near.agg((F.max("dsim") if method == "best_match" else F.sum("dsim")).alias("s"))
    toward = hits.select("query", F.col("facet").alias("a"), F.col("doc_id").alias("d1")).join(near, ["query", "d1"]).where("a <> b").groupBy("query", "a", "b").agg(F.sum("s").alias("s"))
    size = lambda side: sizes.select("query", F.col("facet").alias(side), F.col("n").alias(f"n_{side}"))
    sized = toward.join(size("a"), ["query", "a"])
    if method == "all_pairs":
        return sized.where("a < b").join(size("b"), ["query", "b"]).select("query", "a", "b", F.round(F.col("s") / (F.col("n_a") * F.col("n_b")), DIGITS).alias("sim"))
    half = sized.select("query", F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y"), (F.col("s") / (2 * F.col("n_a"))).alias("part"))
    return half.groupBy(F.col("query"), F.col("x").alias("a"), F.col("y").alias("b")).agg(F.round(F.sum("part"), DIGITS).alias("sim"))


def facet_vectors(hits: DataFrame, vectors: DataFrame) -> DataFrame:
    """``query, facet, term, w``: unit sums of the page vectors of each facet."""
    joined = hits.select("query", "facet", "doc_id").join(vectors, ["query", "doc_id"]).groupBy("query", "facet", "term").agg(F.sum("weight").alias("w"))
    norm = joined.groupBy("query", "facet").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return joined.join(norm, ["query", "facet"]).select("query", "facet", "term", (F.col("w") / F.col("norm")).alias("w"))


def _concat_sim(hits: DataFrame, vectors: DataFrame) -> DataFrame:
    unit = facet_vectors(hits, vectors)
    a = unit.select("query", "term", F.col("facet").alias("a"), F.col("w").alias("wa"))
    b = unit.select("query", "term", F.col("facet").alias("b"), F.col("w").alias("wb"))
    return a.join(b, ["query", "term"]).where("a < b").groupBy("query", "a", "b").agg(F.round(F.sum(F.col("wa") * F.col("wb")), DIGITS).alias("sim"))


def word_sim(facets: DataFrame) -> DataFrame:
    """Jaccard of the facets' own words; named as a poor choice, kept for comparison."""
    x = facets.select("query", "facet", F.array_distinct(analyzed(label(F.col("facet")))).alias("t"))
    a, b = x.select("query", F.col("facet").alias("a"), F.col("t").alias("ta")), x.select("query", F.col("facet").alias("b"), F.col("t").alias("tb"))
    value = F.size(F.array_intersect("ta", "tb")) / F.size(F.array_union("ta", "tb"))
    return a.join(b, "query").where("a < b").select("query", "a", "b", F.round(value, DIGITS).alias("sim")).where("sim > 0")
