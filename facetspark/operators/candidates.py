"""Instance-level candidates: refinements and super-strings of seeds, and their scores."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.functions.textkit import instantiate, phrases, residual


def frequency(log: DataFrame) -> DataFrame:
    return log.groupBy("query").agg(F.count("*").alias("freq"))


def sessions_by_gap(log: DataFrame, gap_seconds: int, user: str = "user_id", order: str = "event_id", min_overlap: int = 0) -> DataFrame:
    """Adds ``session_id`` and ``step``: a new session after a pause longer than the gap.

    With ``min_overlap`` a query that shares fewer tokens with the one before it also starts one.
    """
    by_time = W.partitionBy(user).orderBy("ts", order)
    before = F.lag("ts").over(by_time)
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(before.cast("timestamp"))
    fresh = before.isNull() | (seconds > gap_seconds)
    if min_overlap:
        shared = F.size(F.array_intersect(F.split("query", " "), F.split(F.lag("query").over(by_time), " ")))
        fresh = fresh | (shared < min_overlap)
    marked = log.withColumn("fresh", F.coalesce(fresh, F.lit(True)).cast("long"))
    numbered = marked.withColumn("number", F.sum("fresh").over(by_time.rowsBetween(W.unboundedPreceding, 0)))
    in_session = W.partitionBy(user, "number").orderBy("ts", order)
    return numbered.withColumns({"session_id": F.concat_ws("-", F.col(user), "number"), "step": F.row_number().over(in_session).cast("long")}).drop("fresh", "number")


def succession(log: DataFrame, seeds: DataFrame, follow: str = "any_later") -> DataFrame:
    """``query, candidate, sessions``: sessions in which the candidate comes after the seed.

    Seeds come first: sessions without one are never paired, so the work is linear in the
    sessions that hold a seed. A session counts once per pair.
    """
    known = seeds.select("query").distinct()
    if follow == "next":
        after = F.lead("query").over(W.partitionBy("session_id").orderBy("step"))
        pairs = log.select("session_id", "query", after.alias("candidate")).join(known, "query", "left_semi")
        pairs = pairs.where("candidate is not null and candidate <> query").distinct()
    else:
        first = log.join(known, "query", "left_semi").groupBy("session_id", "query").agg(F.min("step").alias("first"))
        last = log.groupBy("session_id", F.col("query").alias("candidate")).agg(F.max("step").alias("last"))
        pairs = first.join(last, "session_id").where("last > first and candidate <> query")
    return pairs.groupBy("query", "candidate").agg(F.count("*").alias("sessions"))


def refinement_scores(counts: DataFrame) -> DataFrame:
    total = F.sum("sessions").over(W.partitionBy("query"))
    return counts.select("query", "candidate", (F.col("sessions") / total).alias("p_r"))


def superstrings(freq: DataFrame, seeds: DataFrame, match: str = "token") -> DataFrame:
    """``query, candidate, freq``: log queries that contain a seed.

    Token containment is a hash join of seeds with the sub-phrases of log queries; character
    containment is the literal reading, a nested loop over the seeds.
    """
    known = seeds.select("query").distinct()
    if match == "token":
        exploded = freq.select(F.col("query").alias("candidate"), "freq", F.explode(phrases(F.col("query"))).alias("query"))
        return exploded.join(known, "query").select("query", "candidate", "freq")
    pairs = freq.withColumnRenamed("query", "candidate").join(known, F.contains("candidate", "query") & (F.col("candidate") != F.col("query")))
    return pairs.select("query", "candidate", "freq")


def superstring_scores(sup: DataFrame, freq: DataFrame, bound: str = "lower") -> DataFrame:
    own = freq.select("query", F.col("freq").alias("own"))
    joined = sup.join(own, "query", "left").withColumn("own", F.coalesce("own", F.lit(0)))
    if bound == "upper":
        return joined.select("query", "candidate", F.try_divide("freq", "own").alias("p_ss"))
    total = F.col("own") + F.sum("freq").over(W.partitionBy("query"))
    return joined.select("query", "candidate", (F.col("freq") / total).alias("p_ss"))


def instance_scores(p_r: DataFrame, p_ss: DataFrame, sources: tuple[str, ...] = ("refine", "super")) -> DataFrame:
    """``query, candidate, p_inst``: the larger score, normalized to one per seed."""
    both = p_r.select("query", "candidate", F.col("p_r").alias("p")) if "refine" in sources else None
    if "super" in sources:
        other = p_ss.select("query", "candidate", F.col("p_ss").alias("p"))
        both = other if both is None else both.unionByName(other)
    best = both.groupBy("query", "candidate").agg(F.max("p").alias("p"))
    return best.select("query", "candidate", (F.col("p") / F.sum("p").over(W.partitionBy("query"))).alias("p_inst"))


def keyed(instance: DataFrame, seeds: DataFrame, placeholder: bool = True) -> DataFrame:
    """``query, facet, score``: candidates as keys that are comparable across seeds."""
    joined = instance.join(seeds.select("query", "entity"), "query")
    facet = residual(F.col("candidate"), F.col("query"), F.col("entity") if placeholder else None)
    return joined.select("query", facet.alias("facet"), "p_inst").groupBy("query", "facet").agg(F.max("p_inst").alias("score"))


def mine(log: DataFrame, seeds: DataFrame, sources: tuple[str, ...] = ("refine", "super"), match: str = "token", follow: str = "any_later") -> DataFrame:
    """Normalized instance scores of all candidates of all seeds."""
    freq = frequency(log)
    p_r = refinement_scores(succession(log, seeds, follow))
    p_ss = superstring_scores(superstrings(freq, seeds, match), freq)
    return instance_scores(p_r, p_ss, sources)


def posed(facets: DataFrame, seeds: DataFrame) -> DataFrame:
    """Adds ``facet_query``, the text that poses the facet for its seed."""
    joined = facets.join(seeds.select("query", "entity"), "query")
    return joined.withColumn("facet_query", instantiate(F.col("facet"), F.col("query"), F.col("entity"))).drop("entity")


