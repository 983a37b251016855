"""Ranked selection of facets: score against similarity to what is already chosen."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def group_sim(groups: DataFrame, sim: DataFrame) -> DataFrame:
    """``query, a, b, sim`` between groups: the largest similarity of their members, both ways round."""
    m = groups.select("query", "group_label", F.explode("members").alias("facet"))
    both = sim.select("query", "a", "b", "sim").unionByName(sim.select("query", F.col("b").alias("a"), F.col("a").alias("b"), "sim"))
    left = m.select("query", F.col("facet").alias("a"), F.col("group_label").alias("ga"))
    right = m.select("query", F.col("facet").alias("b"), F.col("group_label").alias("gb"))
    return both.join(left, ["query", "a"]).join(right, ["query", "b"]).where("ga <> gb").groupBy("query", F.col("ga").alias("a"), F.col("gb").alias("b")).agg(F.max("sim").alias("sim"))


def greedy(groups: DataFrame, sim: DataFrame, n: int = 8) -> DataFrame:
    """``query, rank, group_label, score, max_sim``: the greedy order, first ``n``.

    First comes the highest score; then, again and again, the largest score divided by the
    largest similarity to a chosen one. Similarity 0 ranks above all positive ones. The fold
    keeps each candidate's running maximum, so a pick costs one pass over a seed's candidates;
    it runs inside one row per seed.
    """
    near = group_sim(groups, sim).groupBy("query", F.col("b").alias("chosen")).agg(F.map_from_entries(F.collect_list(F.struct("a", "sim"))).alias("to"))
    maps = near.groupBy("query").agg(F.map_from_entries(F.collect_list(F.struct("chosen", "to"))).alias("sims"))
    items = groups.groupBy("query").agg(F.array_sort(F.collect_list(F.struct(F.col("group_label").alias("g"), F.round("score", 9).alias("s"), F.lit(0.0).alias("m")))).alias("xs"))
    packed = items.join(maps, "query", "left")
    # one step of the fold: take the best of the rest, then raise the others' running maximum
    step = """
        named_struct(
          'picked', concat(acc.picked, array(named_struct('g', top.g, 's', top.s, 'm', top.m))),
          'rest', transform(filter(acc.rest, x -> x.g <> top.g),
                            x -> named_struct('g', x.g, 's', x.s, 'm', greatest(x.m, coalesce(sims[top.g][x.g], 0D)))))
    """
    best = """
        array_min(transform(acc.rest, x -> named_struct(
          'free', if(size(acc.picked) = 0 or x.m = 0D, 0, 1),
          'gain', -round(if(size(acc.picked) = 0 or x.m = 0D, x.s, x.s / x.m), 9), 'g', x.g, 's', x.s, 'm', x.m)))
    """
    fold = f"""
        aggregate(sequence(1, {int(n)}),
          named_struct('picked', cast(array() as array<struct<g:string,s:double,m:double>>), 'rest', xs),
          (acc, i) -> if(size(acc.rest) = 0, acc, element_at(transform(array({best}), top -> {step}), 1)),
          acc -> acc.picked)
    """
    return packed.select("query", F.posexplode(F.expr(fold)).alias("pos", "x")).select(
        "query", (F.col("pos") + 1).alias("rank"), F.col("x.g").alias("group_label"), F.col("x.s").alias("score"), F.round("x.m", 9).alias("max_sim")
    )


def by_score(groups: DataFrame, n: int = 8) -> DataFrame:
    """Score-only selection."""
    order = F.row_number().over(W.partitionBy("query").orderBy(F.round("score", 9).desc(), "group_label"))
    return groups.withColumn("rank", order).where(F.col("rank") <= n).select("query", "rank", "group_label", F.round("score", 9).alias("score"))


def greedy_rows(rows: list[tuple[str, float]], sim: dict[tuple[str, str], float], n: int) -> list[str]:
    """Plain reference of the greedy order for tests and for one seed at a time."""
    rest, chosen = dict(rows), []
    while rest and len(chosen) < n:
        def gain(g):
            m = max((sim.get((g, c), sim.get((c, g), 0.0)) for c in chosen), default=0.0)
            return (0, -rest[g], g) if not chosen or m == 0 else (1, -round(rest[g] / m, 9), g)
        best = min(rest, key=gain)
        chosen.append(best)
        del rest[best]
    return chosen
