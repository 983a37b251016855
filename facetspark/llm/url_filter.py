"""URL filter: rules first, then a ratio of character language models.

Two variable-order Markov models over characters, one of accepted and one of rejected URLs,
are smoothed by interpolation: an order-k estimate backs off to order k-1 with a weight that
falls with the context's count (Witten-Bell). A URL's score is the mean over its characters
of the log ratio of the two. The threshold is calibrated on rule-decided URLs held out from
training. All of it is DataFrame expressions: grams are counted once over distinct values,
models are joined, never collected, and grow with the corpus.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from facetspark.llm.store import written

RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)


@dataclass(frozen=True)
class UrlModelParams:
    """``alphabet`` is the uniform floor's size; ``holdout`` in every ``folds`` rule URLs calibrate."""

    order: int = 4
    alphabet: int = 256
    folds: int = 5
    digits: int = 9
    bins: int = 1000


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path as the rules read them; both empty without ``://``."""
    text = F.coalesce(url.cast("string"), F.lit(""))
    at = F.instr(text, "://")
    rest = F.when(at > 0, F.substr(text, at + 3)).otherwise("")
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(F.substr(rest, F.length(host) + 1), r"^([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """Name and verdict of the longest rule that fits, null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, h, start in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):  # longer ones come last and win
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(start)
        name, verdict = F.when(fits, h + start).otherwise(name), F.when(fits, kind).otherwise(verdict)
    return name, verdict


def _grams(urls: DataFrame, p: UrlModelParams, *keep: str) -> DataFrame:
    """One row per character of the whole URL: it with up to ``order`` characters before it."""
    padded = F.concat(F.lit("\x02" * p.order), F.col("url"), F.lit("\x03"))
    return (
        urls.select(*keep, padded.alias("s"))
        .select(*keep, "s", F.explode(F.sequence(F.lit(1), F.length("s") - p.order)).alias("i"))
        .select(*keep, F.substring("s", F.col("i"), F.lit(p.order + 1)).alias("gram"))
    )


def log_ratios(counts: DataFrame, p: UrlModelParams) -> DataFrame:
    """``gram, ratio``: log of accepted over rejected probability of each gram's last character.

    ``counts`` has every gram to score, with its training counts ``allow`` and ``block``.
    """
    result = counts.select("gram")
    for model in ("allow", "block"):
        estimate = None
        for k in range(p.order + 1):
            tail = counts.select(F.substring("gram", p.order + 1 - k, k + 1).alias("g"), F.col(model).alias("n"))
            sums = tail.groupBy("g").agg(F.sum("n").alias("n")).withColumn("context", F.substring("g", 1, k))
            by_context = sums.groupBy("context").agg(F.sum("n").alias("total"), F.sum((F.col("n") > 0).cast("long")).alias("kinds"))
            level = sums.join(by_context, "context").withColumn("lower", F.substring("g", 2, k))
            if estimate is None:
                back = level.withColumn("q", F.lit(1.0 / p.alphabet))
            else:
                back = level.join(estimate.select(F.col("g").alias("lower"), F.col("prob").alias("q")), "lower")
            weight = F.when(F.col("total") > 0, F.col("kinds") / (F.col("total") + F.col("kinds"))).otherwise(F.lit(1.0))
            seen = F.when(F.col("total") > 0, F.col("n") / F.col("total")).otherwise(F.lit(0.0))
            estimate = written(back.select("g", ((1 - weight) * seen + weight * F.col("q")).alias("prob")), f"order{k}")
        result = result.join(estimate.select(F.col("g").alias("gram"), F.ln("prob").alias(model)), "gram")
    return result.select("gram", F.round(F.col("allow") - F.col("block"), p.digits).cast("decimal(20,9)").alias("ratio"))


def filter_urls(pages: DataFrame, p: UrlModelParams = UrlModelParams(), rules=RULES) -> DataFrame:
    """One row per input row: ``page_id, host, path, rule, verdict, score``.

    The rules read host and path, the models the whole URL. A null or malformed URL has empty
    host and path; a null one is judged by the model on its end mark alone. Repeated rows get equal results; the models count each row. Without any URL that a
    rule decides, both models are the uniform floor, all scores are 0 and the verdict is allow,
    as it is at and above the threshold.
    """
    host, path = url_parts(F.col("url"))
    split = pages.select(F.col("page_id"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("url"), host.alias("host"), path.alias("path"))
    name, verdict = rule_of(F.col("host"), F.col("path"), rules)
    ruled = split.withColumns({"rule": name, "ruled": verdict, "fold": F.pmod(F.xxhash64("url"), F.lit(p.folds))})
    # equal URLs are folded first: a hot host or page counts by its number
    urls = written(ruled.groupBy("url", "ruled", "fold").agg(F.count("*").alias("n")), "urls")
    trains = F.col("fold") > 0
    weight = lambda kind: F.when(trains & (F.col("ruled") == kind), F.col("n")).otherwise(0)
    grams = _grams(urls.withColumns({"a": weight("allow"), "b": weight("block")}), p, "url", "a", "b")
    # tables are written at each step, so plans stay short however high the order
    counts = written(grams.groupBy("gram").agg(F.sum("a").alias("allow"), F.sum("b").alias("block")), "grams")
    ratios = written(log_ratios(counts, p), "ratios")
    scored = written(
        _grams(urls.select("url"), p, "url")
        .groupBy("url", "gram")
        .agg(F.count("*").alias("times"))
        .join(ratios, "gram")
        .groupBy("url")
        .agg(F.sum(F.col("ratio") * F.col("times")).alias("total"), F.sum("times").alias("chars"))
        .select("url", F.round(F.col("total").cast("double") / F.col("chars"), 6).alias("score")),
        "scored",
    )
    # calibration: the score bin with the best balanced accuracy over held-out rule URLs
    held = scored.join(urls.where("fold = 0 and ruled is not null"), "url")
    bins = held.groupBy(F.floor(F.least(F.greatest(F.col("score"), F.lit(-5.0)), F.lit(5.0)) * (p.bins / 10)).alias("bin")).agg(
        F.sum(F.when(F.col("ruled") == "allow", F.col("n")).otherwise(0)).alias("a"), F.sum(F.when(F.col("ruled") == "block", F.col("n")).otherwise(0)).alias("b")
    )
    up = W.orderBy(F.col("bin").desc()).rowsBetween(W.unboundedPreceding, 0)  # p.bins rows at most
    rates = bins.select("bin", F.sum("a").over(up).alias("kept_a"), F.sum("b").over(up).alias("kept_b"), F.sum("a").over(W.partitionBy()).alias("all_a"), F.sum("b").over(W.partitionBy()).alias("all_b"))
    gain = F.round(F.coalesce(F.try_divide("kept_a", "all_a"), F.lit(0)) - F.coalesce(F.try_divide("kept_b", "all_b"), F.lit(0)), 9)
    threshold = rates.select(gain.alias("gain"), "bin").agg(F.coalesce(F.max(F.struct("gain", "bin"))["bin"] / (p.bins / 10), F.lit(0.0)).alias("threshold"))
    judged = scored.crossJoin(F.broadcast(threshold)).select("url", "score", (F.col("score") >= F.col("threshold")).alias("good"))
    return ruled.join(judged, "url").select(
        "page_id", "host", "path", "rule", F.coalesce("ruled", F.when(F.col("good"), "allow").otherwise("block")).alias("verdict"), "score"
    )
