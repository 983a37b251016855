"""Forward index and exact BM25 retrieval for many queries at once."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark.functions.textkit import analyzed
from facetspark.sources.storage import cut, ship

MARGIN = 1e-6


@dataclass
class Index:
    """``forward (doc_id, len, words: map term -> tf)``, ``terms (term, df, most)``, ``totals (n, avg_len)``.

    ``most`` is a term's largest BM25 part without idf in any document.
    """

    forward: DataFrame
    terms: DataFrame
    totals: DataFrame
    k1: float = 1.2
    b: float = 0.75

    @property
    def postings(self) -> DataFrame:
        """``term, doc_id, tf``."""
        return self.forward.select("doc_id", F.explode("words").alias("term", "tf"))

    def part(self, tf: Column) -> Column:
        """BM25 part without idf, beside columns ``len`` and ``avg_len``."""
        return tf * (self.k1 + 1) / (tf + self.k1 * (1 - self.b + self.b * F.col("len") / F.col("avg_len")))


def build_index(corpus: DataFrame, fields: tuple[str, ...] = ("head", "snippet"), k1: float = 1.2, b: float = 0.75) -> Index:
    """Index of the named fields; the body is read only where it is asked for.

    Each row is counted where it is read. Only numbers are shuffled, to find documents of several rows, which are merged.
    """
    read = corpus.select("doc_id", analyzed(F.concat_ws(" ", *fields)).alias("tokens")).where(F.size("tokens") > 0)
    read = read.withColumn("kinds", F.array_distinct("tokens"))
    once = F.map_from_arrays("kinds", F.array_repeat(F.lit(1).cast("long"), F.size("kinds")))
    counts = F.map_from_arrays("kinds", F.transform("kinds", lambda k: F.size(F.filter("tokens", lambda t: t == k)).cast("long")))
    packed = read.select("doc_id", F.size("tokens").cast("long").alias("len"), F.when(F.size("kinds") == F.size("tokens"), once).otherwise(counts).alias("words"))
    forward = cut(packed, "documents")
    several = cut(forward.groupBy("doc_id").agg(F.count("*").alias("rows")).where("rows > 1").select("doc_id"), "several")
    if not several.isEmpty():
        terms = forward.join(several, "doc_id").select("doc_id", F.explode("words").alias("term", "tf")).groupBy("doc_id", "term").agg(F.sum("tf").alias("tf"))
        merged = terms.groupBy("doc_id").agg(F.sum("tf").alias("len"), F.map_from_entries(F.collect_list(F.struct("term", "tf"))).alias("words"))
        forward = cut(forward.join(several, "doc_id", "left_anti").unionByName(merged), "documents")
    index = Index(forward, forward, cut(forward.agg(F.count("*").alias("n"), F.avg("len").alias("avg_len")), "totals"), k1, b)
    counted = forward.select("len", F.explode("words").alias("term", "tf")).groupBy("term", "tf", "len").agg(F.count("*").alias("n_docs")).crossJoin(F.broadcast(index.totals))  # one row of totals
    index.terms = cut(counted.groupBy("term").agg(F.sum("n_docs").alias("df"), F.max(index.part(F.col("tf"))).alias("most")), "terms")
    return index


ALIKE = "doc_id long, len long, mark long, ids array<int>, tfs array<int>"


def _asked_parts(terms: list[str]):
    """Of each document the counts of the asked terms, in one order; documents without any are left out."""
    names = [x.split()[0] for x in ALIKE.split(", ")]

    def run(batches):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        wanted = pa.array(terms, pa.string())
        for batch in batches:
            words = batch.column(2)
            offsets = np.asarray(words.offsets)
            inside = slice(int(offsets[0]), int(offsets[-1]))
            found = np.asarray(pc.fill_null(pc.index_in(words.keys[inside], value_set=wanted), -1)).astype(np.int64)
            doc = np.repeat(np.arange(batch.num_rows), np.diff(offsets))
            kept = np.flatnonzero(found >= 0)
            kept = kept[np.argsort(doc[kept] * len(terms) + found[kept], kind="stable")]
            counts = np.bincount(doc[kept], minlength=batch.num_rows)
            rows = np.flatnonzero(counts)
            ids, tfs = found[kept], np.asarray(words.items[inside])[kept]
            ends = np.concatenate([[0], np.cumsum(counts[rows])]).astype(np.int32)
            mixed = (ids + 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ tfs.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
            mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
            mark = np.add.reduceat(mixed, ends[:-1]) if len(rows) else np.zeros(0, np.uint64)
            lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(v.astype(np.int32))) for v in (ids, tfs)]
            at = pa.array(rows)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array(mark.view(np.int64)), *lists], names)

    return run


def _alike(index: Index, terms: list[str], m: int) -> DataFrame:
    """Documents by length and counts of the asked terms: those with the same ones have the same score for every text.

    ``kind`` is the smallest document of its like, ``at`` counts from it; beyond the ``m``-th none can be among the best ``m``.
    """
    ship(index.forward.sparkSession)
    rows = index.forward.select("doc_id", "len", "words").mapInArrow(_asked_parts(terms), ALIKE)
    like = W.partitionBy("mark", "len", "ids", "tfs").orderBy("doc_id")
    return rows.withColumn("at", F.row_number().over(like)).where(F.col("at") <= m).withColumn("kind", F.first("doc_id").over(like))


def _scored(pairs: DataFrame, kinds: DataFrame, m: int) -> DataFrame:
    """The best ``m`` of candidate rows ``query_text, ts, doc_id``; ties go to the smaller document."""
    score = F.aggregate("ts", F.lit(0.0), lambda total, t: total + t["idf"] * F.coalesce(F.try_element_at("parts", t["term"]), F.lit(0.0)))
    return _best(pairs.join(kinds, "doc_id").select("query_text", "doc_id", F.round(score, 9).alias("relevance")), m)


def _best(scored: DataFrame, m: int) -> DataFrame:
    rank = F.row_number().over(W.partitionBy("query_text").orderBy(F.col("relevance").desc(), "doc_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= m)


def top_hits(queries: DataFrame, index: Index, m: int = 8) -> DataFrame:
    """``query_text, rank, doc_id, relevance``: the best ``m`` documents of every distinct text.

    Documents that no text tells apart are scored once, as their smallest one: the best ``m`` documents are of the best
    ``m`` kinds. Terms are ordered by the most that they can add to a score. First come the kinds that hold
    a text's two strongest terms: their m-th best score is a floor. Where neither of the two terms
    can be missing from a document above the floor, these are the best. The other texts
    look at every kind with one of the terms that a document above their floor cannot do without.
    """
    asked = queries.select("query_text").distinct().select("query_text", F.explode(F.array_distinct(analyzed(F.col("query_text")))).alias("term"))
    weighted = asked.join(index.terms, "term").crossJoin(F.broadcast(index.totals))  # one row of totals
    idf = F.ln(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    strong = F.struct((idf * F.col("most")).alias("bound"), "term", idf.alias("idf"))
    texts = weighted.groupBy("query_text").agg(F.sort_array(F.collect_list(strong), asc=False).alias("ts"))
    total = F.aggregate("ts", F.lit(0.0), lambda x, t: x + t["bound"])
    second = F.get("ts", 1)
    texts = cut(texts.select("query_text", "ts", F.get("ts", 0)["term"].alias("one"), F.coalesce(second["term"], F.get("ts", 0)["term"]).alias("two"), (total - F.least(F.get("ts", 0)["bound"], F.coalesce(second["bound"], F.get("ts", 0)["bound"]))).alias("without")), "texts")

    terms = sorted(r["term"] for r in texts.select(F.explode("ts.term").alias("term")).distinct().collect())
    alike = cut(_alike(index, terms, m), "alike")
    named = F.transform("ids", lambda i: F.get(F.array(*map(F.lit, terms)), i))
    kinds = alike.where("at = 1").crossJoin(F.broadcast(index.totals))  # one row of totals
    kinds = cut(kinds.select("doc_id", F.map_from_arrays(named, F.transform("tfs", index.part)).alias("parts")), "kinds")
    postings = kinds.select(F.explode(F.map_keys("parts")).alias("term"), "doc_id")
    holds = lambda name: postings.join(texts.select(F.col(name).alias("term")).distinct(), "term").select(F.col("term").alias(name), "doc_id")
    both = holds("one").join(holds("two"), "doc_id")
    first = cut(_scored(both.join(texts.select("query_text", "ts", "one", "two"), ["one", "two"]).select("query_text", "ts", "doc_id"), kinds, m), "first-hits")
    floors = first.where(F.col("rank") == m).select("query_text", F.col("relevance").alias("floor"))
    judged = texts.join(floors, "query_text", "left").withColumn("floor", F.coalesce("floor", F.lit(0.0)))
    settled = F.col("floor") > F.col("without") + MARGIN
    # a term is needed while those after it can reach the floor together
    after = lambda i: F.aggregate(F.slice("ts", i + 2, F.size("ts")), F.lit(0.0), lambda x, t: x + t["bound"])
    needed = F.filter(F.transform("ts", lambda t, i: F.struct(t["term"].alias("term"), ((i == 0) | (after(i - 1) >= F.col("floor") - MARGIN)).alias("on"))), lambda x: x["on"])
    rest = judged.where(~settled).select("query_text", "ts", F.explode(needed).alias("x")).select("query_text", "ts", F.col("x.term").alias("term"))
    more = rest.join(postings, "term").select("query_text", "ts", "doc_id").dropDuplicates(["query_text", "doc_id"])
    done = first.join(judged.where(settled).select("query_text"), "query_text", "left_semi")
    best = cut(done.unionByName(_scored(more, kinds, m)).select("query_text", F.col("doc_id").alias("kind"), "relevance"), "best-kinds")
    members = alike.select("kind", "doc_id").join(best, "kind").select("query_text", "doc_id", "relevance")
    return cut(_best(members, m).select("query_text", "rank", "doc_id", "relevance"), "top-hits")


def facet_hits(facets: DataFrame, index: Index, m: int = 8) -> DataFrame:
    """``query, facet, doc_id, rank`` for facets with ``facet_query``."""
    hits = top_hits(facets.select(F.col("facet_query").alias("query_text")), index, m)
    return facets.select("query", "facet", F.col("facet_query").alias("query_text")).join(hits, "query_text").select("query", "facet", "doc_id", "rank")
