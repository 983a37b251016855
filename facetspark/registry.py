"""Queries of the methods, variants, baselines, measures and workloads, with their SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import lru_cache
from math import inf

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetspark import oracles
from facetspark.functions import textkit
from facetspark.operators import baselines, candidates, cluster, group, measures, present, propagate, relops, retrieve, select, similarity, toolbox
from facetspark.plans.pipeline import Commerce, Params, capped
from facetspark.sources import worlds
from facetspark.sources.storage import cut
from facetspark.streaming import logs

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


@lru_cache(maxsize=64)
def _commerce(application: str, folder: str, p: Params) -> Commerce:
    return Commerce(worlds.Tables(SparkSession.active(), folder), p)


def commerce(spark: SparkSession, folder: str, p: Params = Params()) -> Commerce:
    return _commerce(spark.sparkContext.applicationId, folder, p)


def shaped(df: DataFrame) -> DataFrame:
    """Counts as long, measures to six digits: the form in which engines are compared.

    Engines differ in how they round a decimal half that no double holds; floor of the shifted value is the same in all.
    """
    kinds = {"int": "long", "bigint": "long", "double": None}
    out = []
    for name, kind in df.dtypes:
        c = F.col(f"`{name}`")
        six = F.floor(F.round(c, 9) * 1000000 + 0.5) / 1000000
        out.append((c.cast("long") if kinds.get(kind) == "long" else six if kind == "double" else c).alias(name))
    return df.select(*out)


def six_digits(sql: str) -> str:
    """``round(x, 6)`` and ``round(round(x, 9), 6)`` in the form of :func:`shaped`."""
    at = 0
    while (at := sql.find("round(", at)) >= 0:
        depth, end = 1, at + len("round(")
        while depth:
            depth += {"(": 1, ")": -1}.get(sql[end], 0)
            end += 1
        inner = sql[at + len("round(") : end - 1]
        if inner.endswith(", 6"):
            inner = inner[:-3]
            inner = inner if inner.startswith("round(") and inner.endswith(", 9)") else f"round({inner}, 9)"
            made = f"(floor({inner} * 1000000 + 0.5) / 1000000)"
            sql = sql[:at] + made + sql[end:]
            at += len("(floor(round(")
        else:
            at += len("round(")
    return sql


def register(name: str, make: Callable[[Commerce], DataFrame], sql: str | None = None, p: Params = Params(), extra: dict[str, str] | None = None, **params) -> None:
    QUERIES[name] = lambda spark, folder: shaped(make(commerce(spark, folder, p)))
    if sql is not None:
        ORACLES[name] = six_digits(oracles.oracle(sql, extra, **params))


def variant(name: str, make, sql: str, extra: dict[str, str] | None = None, **changes) -> None:
    """A registered query under changed parameters, in both engines alike."""
    p = replace(Params(), **changes)
    names = {"fields": lambda v: {"body": "body" in v}, "strip_seed": lambda v: {"strip": v}}
    given: dict = {}
    for k, v in changes.items():
        given |= names[k](v) if k in names else {k: v}
    register(name, make, sql, p, extra, **given)


R6 = "round(round({0}, 9), 6) AS {0}"  # twice: values half-way between two sixth digits must fall alike


def r6(*names: str) -> str:
    return ", ".join(R6.format(n) for n in names)


# --- logs, sessions, candidates -------------------------------------------------------------
register("world_commerce_log", lambda c: c.log.drop("ts"), "SELECT user_id, session_id, step, query FROM log")
register("world_commerce_counts", lambda c: c.log.groupBy("query").agg(F.count("*").alias("n"), F.count_distinct("session_id").alias("sessions")), "SELECT query, count(*) AS n, count(DISTINCT session_id) AS sessions FROM log GROUP BY query")
register("m01_normalize", lambda c: worlds.dialogue_log(c.t).select("session_id", "step", textkit.normalize(F.col("query")).alias("query")),
    r"""SELECT conv_id AS session_id, turn AS step, array_to_string(list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}_#]+'), lambda t: t <> '')[1:least(1 + turn // 2, 4)], ' ') AS query FROM conversations WHERE role = 'user'""")
CLICKS = """SELECT user_id, event_id, ts, CASE WHEN event_id % 2 = 0 THEN event_type ELSE event_type || ' k' || json_extract_string(props, '$.k') END AS query FROM events"""
GAPS = {"clicks": CLICKS, "gaps": "SELECT *, CASE WHEN date_diff('second', lag(ts) OVER u, ts) <= 28800 THEN 0 ELSE 1 END AS fresh, lag(query) OVER u AS before FROM clicks WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)",
        "cut": "SELECT *, CASE WHEN before IS NULL OR len(list_intersect(list_distinct(string_split(query, ' ')), list_distinct(string_split(before, ' ')))) < 1 THEN 1 ELSE fresh END AS fresh2 FROM gaps"}
register("m02_sessions_by_gap", lambda c: candidates.sessions_by_gap(worlds.click_log(c.t), 8 * 3600).select("user_id", "event_id", "session_id"),
    "SELECT user_id, event_id, user_id || '-' || CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session_id FROM gaps", extra=GAPS)
register("m02a_sessions_by_task", lambda c: candidates.sessions_by_gap(worlds.click_log(c.t), 8 * 3600, min_overlap=1).select("user_id", "event_id", "session_id"),
    "SELECT user_id, event_id, user_id || '-' || CAST(sum(fresh2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session_id FROM cut", extra=GAPS)
register("m03_succession", lambda c: candidates.succession(c.log, c.seeds), "SELECT * FROM succ")
variant_next = lambda c: candidates.succession(c.log, c.seeds, "next")
register("m03a_succession_next", variant_next, "SELECT * FROM succ", follow="next")
register("m04_refinement", lambda c: candidates.refinement_scores(candidates.succession(c.log, c.seeds)), f"SELECT query, candidate, {r6('p_r')} FROM p_r")
register("m05_superstrings_token", lambda c: candidates.superstrings(candidates.frequency(c.log), c.seeds), "SELECT * FROM sup")
register("m05_superstrings_char", lambda c: candidates.superstrings(candidates.frequency(c.log), c.seeds, "char"), "SELECT * FROM sup", match="char")


def _sup(c: Commerce, bound: str) -> DataFrame:
    freq = candidates.frequency(c.log)
    return candidates.superstring_scores(candidates.superstrings(freq, c.seeds), freq, bound)


register("m06_superstring_lower", lambda c: _sup(c, "lower"), f"SELECT query, candidate, {r6('p_ss')} FROM p_ss")
register("m06a_superstring_upper", lambda c: _sup(c, "upper"), "SELECT query, candidate, round(round(upper, 9), 6) AS p_ss FROM p_ss")
register("m07_instance", lambda c: candidates.mine(c.log, c.seeds), f"SELECT query, candidate, {r6('p_inst')} FROM cand")
register("m07a_refinements_only", lambda c: candidates.mine(c.log, c.seeds, ("refine",)), f"SELECT query, candidate, {r6('p_inst')} FROM cand", sources=("refine",))
register("m07a_superstrings_only", lambda c: candidates.mine(c.log, c.seeds, ("super",)), f"SELECT query, candidate, {r6('p_inst')} FROM cand", sources=("super",))
register("m08_segment", lambda c: propagate.segment(c.seeds.select("query"), worlds.membership(c.t)), "SELECT query, entity, property FROM seeds")
register("m09_residual", lambda c: c.instance, f"SELECT query, facet, {r6('score')} FROM inst")

# --- propagation ----------------------------------------------------------------------------
register("m10_classes", lambda c: propagate.classes_of(c.seeds, worlds.membership(c.t), worlds.aliases(c.t), worlds.ambiguous(c.t)), "SELECT query, class, property FROM nodes")
register("m11_graph", lambda c: propagate.graph_edges(c.nodes, 0.1), "SELECT query AS source, class || ' ' || property AS target, 1.0::DOUBLE AS weight FROM nodes UNION ALL SELECT class || ' ' || property, query, 0.1 FROM nodes")
register("m12_class_mean", lambda c: propagate.class_scores(c.instance, c.nodes, "mean"), f"SELECT class, property, facet, {r6('p_class')} FROM cls", mode="mean")
register("m13_class_indicator", lambda c: propagate.class_scores(c.instance, c.nodes), f"SELECT class, property, facet, {r6('p_class')} FROM cls")
SCORED = f"SELECT query, facet, {r6('score')} FROM scored"
register("m14_smooth", lambda c: c.scored, SCORED)
for tag, k in (("0", 0), ("1", 1), ("10", 10), ("100", 100), ("inf", inf)):
    variant(f"m14a_smooth_k{tag}", lambda c: c.scored, SCORED, k=k)
register("m15_iterate", lambda c: propagate.iterate(c.instance, c.nodes, 0.1, cut=lambda d: cut(d, "round"))[0], SCORED, mode="mean")


def _weighted(c: Commerce) -> DataFrame:
    weights = candidates.frequency(c.log).select("query", F.col("freq").cast("double").alias("weight"))
    return propagate.class_scores(c.instance, c.nodes, "mean", weights)


register("m15b_weighted", _weighted, """SELECT class, property, facet, round(round(sum(score * w) / any_value(size), 9), 6) AS p_class FROM (SELECT n.class, n.property, facet, score, coalesce(f.freq, 0) AS w,
    (SELECT sum(coalesce(g.freq, 0)) FROM nodes z LEFT JOIN freq g ON g.query = z.query WHERE z.class = n.class AND z.property = n.property) AS size
    FROM nodes n JOIN inst i ON n.query = i.query LEFT JOIN freq f ON f.query = n.query) GROUP BY class, property, facet""")


def _many_classes(c: Commerce) -> DataFrame:
    """Entities in two classes: scores spread through shared members, so they are iterated until they settle."""
    extra = worlds.seeds(c.t).select("entity", F.concat(F.lit("group"), F.pmod(F.regexp_extract("entity", r"(\d+)$", 1).cast("int"), F.lit(3)).cast("string")).alias("class")).distinct()
    nodes = cut(propagate.classes_of(c.seeds, worlds.membership(c.t).unionByName(extra)), "nodes")
    return propagate.iterate(c.instance, nodes, 0.1, tolerance=1e-12, cut=lambda d: cut(d, "round"))[0]


ROUNDS = 14  # each round contracts by 0.1 / 1.1, so the change falls below 1e-14
TWO = {"twice": "SELECT query, class, property FROM nodes UNION SELECT query, 'group' || CAST(regexp_extract(entity, '(\\d+)$', 1) AS INT) % 3, property FROM seeds",
       "sizes2": "SELECT class, property, count(*) AS size FROM twice GROUP BY ALL", "held2": "SELECT query, count(*) AS classes FROM twice GROUP BY query", "round0": "SELECT query, facet, score FROM inst"}
for _r in range(1, ROUNDS + 1):
    TWO[f"class{_r}"] = f"SELECT t.class, t.property, facet, sum(score) / any_value(size) AS p FROM twice t JOIN round{_r - 1} i ON i.query = t.query JOIN sizes2 z ON z.class = t.class AND z.property = t.property GROUP BY t.class, t.property, facet"
    TWO[f"mean{_r}"] = f"SELECT t.query, facet, sum(p) / any_value(classes) AS p FROM twice t JOIN class{_r} c ON c.class = t.class AND c.property = t.property JOIN held2 h ON h.query = t.query GROUP BY t.query, facet"
    TWO[f"round{_r}"] = f"SELECT coalesce(i.query, m.query) AS query, coalesce(i.facet, m.facet) AS facet, (coalesce(score, 0) + 0.1::DOUBLE * coalesce(p, 0)) / 1.1::DOUBLE AS score FROM inst i FULL JOIN mean{_r} m ON m.query = i.query AND m.facet = i.facet"
register("m15c_multiclass", _many_classes, f"SELECT query, facet, {r6('score')} FROM round{ROUNDS}", extra=TWO)

# --- retrieval, similarity, clusters --------------------------------------------------------
register("m16_hits", lambda c: c.hits, "SELECT query, facet, doc_id, rank FROM hits")
variant("m16a_whole_page", lambda c: c.hits, "SELECT query, facet, doc_id, rank FROM hits", fields=("body",))
register("m17_doc_cosine", lambda c: similarity.doc_pairs(c.vectors), f"SELECT query, d1, d2, {r6('dsim')} FROM pairs WHERE d1 <= d2")
SIM = f"SELECT query, a, b, {r6('sim')} FROM sim"
register("m18_best_match", lambda c: c.sim, SIM)
for tag, method in (("m18a_all_pairs", "all_pairs"), ("m18b_concat", "concat"), ("m18c_words", "words")):
    variant(tag, lambda c: c.sim, SIM, method=method)
register("m19_edges", lambda c: cluster.threshold_edges(c.sim), "SELECT query, a, b FROM edges")
register("m20_components", lambda c: c.clusters.select("query", "facet", "component"), "SELECT query, facet, component FROM comp")
register("m21_labels", lambda c: c.clusters.select("query", "facet", "cluster_label"), "SELECT query, facet, cluster_label FROM clusters")


def _star(c: Commerce) -> DataFrame:
    return cluster.star_cover(c.pool, cluster.threshold_edges(c.sim, 0.35))


register("m22_star", _star)
GROUPS = f"SELECT query, group_label, kind, {r6('score')}, members FROM groups"
grouped = lambda c: c.groups.withColumn("members", F.array_join("members", ","))
register("m23_group", grouped, GROUPS)
variant("m23c_group_vote", grouped, GROUPS, ambiguity="vote")
register("m23d_group_labels", lambda c: group.member_label(c.groups).select("query", "group_label", "shown"),
    "SELECT query, group_label, CASE WHEN kind = 'single' THEN trim(replace(group_label, '<q>', '')) ELSE trim(replace(split_part(members, ',', 1), '<q>', '')) || ' (and ' || (len(string_split(members, ',')) - 1) || ' more)' END AS shown FROM groups")

# --- selection, presentation ----------------------------------------------------------------
RANKED = f"SELECT query, rank, group_label, {r6('score', 'max_sim')} FROM ranked"
register("m24_greedy", lambda c: c.ranked, RANKED)
variant("m24_greedy_without_groups", lambda c: c.ranked, RANKED, grouping=False)
SETS = "SELECT query, rank, trim(replace(group_label, '<q>', '')) AS facet FROM ranked"
register("m25_pipeline", lambda c: c.ranked.select("query", "rank", textkit.label(F.col("group_label")).alias("facet")), SETS)
register("m26_related_list", lambda c: present.related_list(c.ranked), "SELECT query, string_agg(trim(replace(group_label, '<q>', '')), ' | ' ORDER BY rank) AS related FROM ranked GROUP BY query")
register("m29_facet_sets", lambda c: present.facet_sets(c.ranked, c.groups, c.clusters), "SELECT r.query, r.rank, c.facet FROM ranked r JOIN placed p ON p.query = r.query AND p.group_label = r.group_label JOIN clusters c ON c.query = p.query AND c.cluster_label = p.facet")


def _seed_hits(c: Commerce, n: int) -> DataFrame:
    hits = retrieve.top_hits(c.seeds.select(F.col("query").alias("query_text")), c.index, n)
    return hits.withColumnRenamed("query_text", "query")




def _seed_sql(n: int) -> dict[str, str]:
    numbered = "SELECT query AS text, row_number() OVER (ORDER BY query) AS tid FROM seeds"
    return {"numbered_seeds": numbered, "seed_hits": f"SELECT text AS query, doc_id, relevance, rank FROM ({oracles.found('numbered_seeds', n)}) f"}


def _categorize(c: Commerce) -> DataFrame:
    seed = _seed_hits(c, 20)
    pages = c.hits.join(c.ranked.select("query", F.col("group_label").alias("facet")), ["query", "facet"], "left_semi")
    both = c.hits.select("query", "doc_id").unionByName(seed.select("query", "doc_id")).distinct()
    return present.categorize(seed, pages, similarity.doc_pairs(similarity.doc_vectors(both, c.index)))


register("m27_categorize", _categorize, """SELECT query, doc_id, facet FROM (SELECT s.query, s.doc_id, h.facet, round(max(p.dsim), 9) AS fit FROM seed_hits s JOIN pairs2 p ON p.query = s.query AND p.d1 = s.doc_id
    JOIN hits h ON h.query = s.query AND h.doc_id = p.d2 JOIN ranked r ON r.query = h.query AND r.group_label = h.facet GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY query, doc_id ORDER BY fit DESC, facet) = 1""",
    extra=_seed_sql(20) | {"pages2": "SELECT query, doc_id FROM hits UNION SELECT query, doc_id FROM seed_hits",
        "vectors2": oracles.expressions()["vectors"].replace("(SELECT DISTINCT query, doc_id FROM hits)", "(SELECT query, doc_id FROM pages2)"),
        "pairs2": oracles.expressions()["pairs"].replace("FROM vectors a JOIN vectors b", "FROM vectors2 a JOIN vectors2 b")})


def _triggers(c: Commerce) -> DataFrame:
    rules = c.t.spark.createDataFrame([("economy", "price"), ("gizmo", "images"), ("type", "filter"), ("anvil", "images")], "keyword string, gadget string")
    return present.triggers(c.ranked, rules)


register("m28_triggers", _triggers, "SELECT DISTINCT query, gadget FROM (SELECT query, unnest(string_split(trim(replace(group_label, '<q>', '')), ' ')) AS keyword FROM ranked) JOIN (VALUES ('economy', 'price'), ('gizmo', 'images'), ('type', 'filter'), ('anvil', 'images')) r(keyword, gadget) USING (keyword)")

# --- baselines ------------------------------------------------------------------------------
TOP = "SELECT query, rank, group_label, round(round(score, 9), 6) AS score FROM (SELECT query, {label} AS group_label, {score} AS score, row_number() OVER (PARTITION BY query ORDER BY round({score}, 9) DESC, {label}) AS rank FROM {table}) WHERE rank <= 8"
register("b01_related", lambda c: baselines.related(candidates.mine(c.log, c.seeds)), TOP.format(label="candidate", score="p_inst", table="cand"))
register("b01a_related_refinements", lambda c: baselines.related(candidates.mine(c.log, c.seeds, ("refine",))), TOP.format(label="candidate", score="p_inst", table="cand"), sources=("refine",))
register("b01b_related_superstrings", lambda c: baselines.related(candidates.mine(c.log, c.seeds, ("super",))), TOP.format(label="candidate", score="p_inst", table="cand"), sources=("super",))


def _cluster_labels(c: Commerce) -> DataFrame:
    own = c.seeds.select("query", F.explode(F.array_distinct(textkit.analyzed(F.col("query")))).alias("term"))
    return baselines.cluster_labels(_seed_hits(c, 500), c.index, own)


register("b02_cluster_labels", _cluster_labels, TOP.format(label="term", score="s", table="worded2"), extra=_seed_sql(500) | {"worded2": f"SELECT query, term, count(*) * ln((1 + any_value(n)) / (1 + any_value(df))) AS s FROM seed_hits JOIN postings USING (doc_id) JOIN terms USING (term), totals WHERE NOT list_contains({oracles.folded('query')}, term) GROUP BY query, term"})


def _navigational(c: Commerce) -> DataFrame:
    supported = c.t.region.where("r_regionkey <= 1").select(F.lower("r_name").alias("class"))
    return baselines.navigational(propagate.class_scores(c.instance, c.nodes), c.nodes, supported)


NAV = {"plain": "SELECT facet FROM cls GROUP BY facet HAVING count(*) > 0.8 * (SELECT count(*) FROM (SELECT DISTINCT class, property FROM cls))",
       "led": "SELECT n.query, c.facet, p_class FROM nodes n JOIN cls c USING (class, property) WHERE n.class IN (SELECT lower(r_name) FROM region WHERE r_regionkey <= 1) AND c.facet NOT IN (SELECT facet FROM plain)"}
register("b03_navigational", _navigational, TOP.format(label="facet", score="p_class", table="led"), extra=NAV)
ATTR = {"attrs": "SELECT class, attribute, count(*) AS n FROM (SELECT lower(r_name) AS class, lower(c_mktsegment) AS attribute FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT split_part(lower(p_name), ' ', 2), lower(p_brand) FROM part UNION ALL SELECT split_part(lower(p_name), ' ', 2), lower(p_type) FROM part) GROUP BY ALL",
        "attr_seed": "SELECT query, attribute, n::DOUBLE AS n FROM nodes JOIN attrs USING (class)"}
register("b04_kb_attributes", lambda c: baselines.kb_attributes(c.nodes, worlds.attributes(c.t)), TOP.format(label="attribute", score="n", table="attr_seed"), extra=ATTR)
register("b05_seed_results", lambda c: _seed_hits(c, 500).select("query", "rank", "doc_id"), "SELECT query, rank, doc_id FROM seed_hits", extra=_seed_sql(500))
BY_SCORE = "SELECT query, rank, group_label, round(round(score, 9), 6) AS score FROM (SELECT query, group_label, score, row_number() OVER (PARTITION BY query ORDER BY round(score, 9) DESC, group_label) AS rank FROM groups) WHERE rank <= 8"
register("b06_by_score", lambda c: select.by_score(c.groups), BY_SCORE)
variant("b07_no_propagation", lambda c: c.ranked, RANKED, k=0)
variant("b08_no_dedupe", lambda c: c.ranked, RANKED, dedupe=False)
variant("b09_no_grouping", lambda c: c.ranked.select("query", "group_label"), "SELECT query, group_label FROM ranked", grouping=False)
variant("b10_whole_page_ranked", lambda c: c.ranked, RANKED, fields=("body",))

# --- measures and workloads -----------------------------------------------------------------
register("x01_tsim", lambda c: _centroid_sims(c), "SELECT a.label AS a, b.label AS b, round(array_cosine_similarity(a.c, b.c), 6) AS sim FROM cents a, cents b WHERE a.label < b.label", extra={"cents": "SELECT label, list(x ORDER BY i)::DOUBLE[64] AS c FROM (SELECT label, i, avg(embedding[i]::DOUBLE) AS x FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL) GROUP BY label"})


def _centroid_sims(c: Commerce) -> DataFrame:
    x = c.t.embeddings.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("x"))
    v = x.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda e: e["x"]).alias("v"))
    a, b = v.toDF("a", "va"), v.toDF("b", "vb")
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", measures.cosine(F.col("va"), F.col("vb")).alias("sim"))  # ten labels


def _eval_sim(c: Commerce, pages: DataFrame) -> DataFrame:
    pages = cut(pages, "pages")
    return measures.eval_sim(pages, _topics(c, pages.select("doc_id").distinct()))


def _topics(c: Commerce, wanted: DataFrame) -> DataFrame:
    """Topic of a wanted line document: its type, brand and order month, one unit-norm vector per document."""
    x = c.corpus.join(wanted, "doc_id", "left_semi").select("doc_id", F.explode(F.filter(F.split("body", " "), lambda w: w.rlike("^(m[0-9]|brand|z[0-9])"))).alias("topic"))
    return x.distinct().withColumn("share", 1 / F.sqrt(F.count("*").over(W.partitionBy("doc_id")).cast("double")))


TOPICS = {"doc_topic": "SELECT doc_id, topic, 1 / sqrt(count(*) OVER (PARTITION BY doc_id)) AS share FROM (SELECT DISTINCT l_orderkey * 100 + step AS doc_id, unnest([brand, 'z' || p_size, 'm' || strftime(o_orderdate, '%Y%m')]) AS topic FROM lines)",
    "shown": "SELECT h.query, h.facet, h.doc_id FROM hits h JOIN ranked r ON r.query = h.query AND r.group_label = h.facet",
    "centre": "SELECT s.query, s.facet, d.topic, sum(d.share) / any_value(z.n) AS x FROM shown s JOIN doc_topic d ON d.doc_id = s.doc_id JOIN (SELECT query, facet, count(*) AS n FROM shown GROUP BY ALL) z ON z.query = s.query AND z.facet = s.facet GROUP BY s.query, s.facet, d.topic",
    "named": "SELECT DISTINCT query, facet FROM shown",
    "esim": "SELECT p.query, p.facet AS a, q.facet AS b, coalesce((SELECT sum(u.x * v.x) FROM centre u JOIN centre v ON u.topic = v.topic WHERE u.query = p.query AND v.query = p.query AND u.facet = p.facet AND v.facet = q.facet), 0) AS sim FROM named p JOIN named q ON p.query = q.query AND p.facet <= q.facet"}


def _shown(c: Commerce, ranked: DataFrame | None = None) -> DataFrame:
    return c.hits.join((c.ranked if ranked is None else ranked).select("query", F.col("group_label").alias("facet")), ["query", "facet"], "left_semi").select("query", "facet", "doc_id")


register("x02_eval_sim", lambda c: _eval_sim(c, _shown(c)), f"SELECT query, a, b, {r6('sim')} FROM esim", extra=TOPICS)
NSIM = f"SELECT query, {r6('asim', 'isim', 'nsim')} FROM (SELECT query, avg(CASE WHEN a < b THEN sim END) AS asim, avg(CASE WHEN a = b THEN sim END) AS isim, avg(CASE WHEN a < b THEN sim END) / avg(CASE WHEN a = b THEN sim END) AS nsim FROM esim GROUP BY query)"
register("x05_nsim", lambda c: measures.orthogonality(_eval_sim(c, _shown(c))), NSIM, extra=TOPICS)
BY_SCORE_SHOWN = TOPICS | {"by_score": BY_SCORE, "shown": TOPICS["shown"].replace("JOIN ranked r", "JOIN by_score r")}
register("w16_nsim_by_score", lambda c: measures.orthogonality(_eval_sim(c, _shown(c, select.by_score(c.groups)))), NSIM, extra=BY_SCORE_SHOWN)
variant("w16_nsim_without_grouping", lambda c: measures.orthogonality(_eval_sim(c, _shown(c))), NSIM, extra=TOPICS, grouping=False)


TEN = Params(n=10)
POPULAR = {"popular30": "SELECT query FROM seeds LEFT JOIN freq USING (query) ORDER BY coalesce(freq, 0) DESC, query LIMIT 30"}


def _popular(c: Commerce, n: int = 30) -> DataFrame:
    freq = candidates.frequency(c.log)
    return c.seeds.select("query").join(freq, "query", "left").orderBy(F.coalesce("freq", F.lit(0)).desc(), "query").limit(n).select("query")


def _selected_hits(c: Commerce) -> DataFrame:
    """Pages of the selected facets; a group's are those of its best member."""
    best = c.ranked.join(c.groups.select("query", "group_label", F.get("members", 0).alias("facet")), ["query", "group_label"])
    return c.hits.join(best.select("query", "facet"), ["query", "facet"], "left_semi")


def _overlaps(c: Commerce, k: int) -> DataFrame:
    """Mean overlap for every N, over all seeds and over the popular ones."""
    seed = cut(_seed_hits(c, 500), "seed-hits")
    hits, popular = cut(_selected_hits(c), "selected"), _popular(c).withColumn("known", F.lit(True))
    out = None
    for n in (10, 50, 100, 200, 500):
        each = measures.overlap(hits, seed, k, n).join(popular, "query", "left")
        row = each.agg(F.lit(k).alias("k"), F.lit(n).alias("n"), F.avg("overlap").alias("overlap"), F.avg(F.when(F.col("known"), F.col("overlap"))).alias("popular"))
        out = row if out is None else out.unionByName(row)
    return out


SELECTED = {"best_member": "SELECT r.query, split_part(g.members, ',', 1) AS facet FROM ranked r JOIN groups g ON g.query = r.query AND g.group_label = r.group_label",
            "chosen_hits": "SELECT h.query, h.facet, h.doc_id, h.rank FROM hits h JOIN best_member b ON b.query = h.query AND b.facet = h.facet"}
OVER = """SELECT {k} AS k, n, round(avg(o), 6) AS overlap, round(avg(CASE WHEN query IN (SELECT query FROM popular30) THEN o END), 6) AS popular FROM (
    SELECT n, query, count(hit) / count(*) AS o FROM (SELECT g.n, h.query, h.doc_id, s.doc_id AS hit FROM (SELECT DISTINCT query, doc_id FROM chosen_hits WHERE rank <= {k}) h
    CROSS JOIN (SELECT unnest([10, 50, 100, 200, 500]) AS n) g LEFT JOIN seed_hits s ON s.query = h.query AND s.doc_id = h.doc_id AND s.rank <= g.n) GROUP BY ALL) GROUP BY n"""
for k in (1, 8):
    register(f"w06_overlap_curve_k{k}", lambda c, k=k: _overlaps(c, k), OVER.format(k=k), TEN, extra=_seed_sql(500) | SELECTED | POPULAR, n=10)
register("x07_new_information", lambda c: measures.overlap(_selected_hits(c), _seed_hits(c, 500), 8, 500).select("query", (1 - F.col("overlap")).alias("new_share")),
    "SELECT h.query, round(1 - count(s.doc_id) / count(*), 6) AS new_share FROM (SELECT DISTINCT query, doc_id FROM chosen_hits) h LEFT JOIN seed_hits s ON s.query = h.query AND s.doc_id = h.doc_id GROUP BY h.query", TEN, extra=_seed_sql(500) | SELECTED, n=10)


def _relevance_sample(c: Commerce) -> DataFrame:
    """What the raters of a seed see: of its facets' first pages two that its 500 results hold and two that they do not, drawn by hash, and its top five."""
    seed = cut(_seed_hits(c, 500), "seed-hits")
    first = _selected_hits(c).where("rank = 1").select("query", "doc_id").distinct()
    held = first.join(seed.select("query", "doc_id", F.lit("covered").alias("role")), ["query", "doc_id"], "left").withColumn("role", F.coalesce("role", F.lit("uncovered")))
    turn = F.row_number().over(W.partitionBy("query", "role").orderBy(F.md5(F.concat_ws("|", "query", "doc_id")), "doc_id"))
    rated = held.withColumn("turn", turn).where("turn <= 2").select("query", "role", "doc_id")
    return rated.unionByName(seed.where("rank <= 5").select("query", F.lit("context").alias("role"), "doc_id"))


register("w07_relevance_sample", _relevance_sample, """SELECT query, role, doc_id FROM (SELECT query, doc_id, CASE WHEN s.rank IS NULL THEN 'uncovered' ELSE 'covered' END AS role FROM
    (SELECT DISTINCT query, doc_id FROM chosen_hits WHERE rank = 1) h LEFT JOIN seed_hits s USING (query, doc_id)) QUALIFY row_number() OVER (PARTITION BY query, role ORDER BY md5(query || '|' || doc_id), doc_id) <= 2
    UNION ALL SELECT query, 'context', doc_id FROM seed_hits WHERE rank <= 5""", TEN, extra=_seed_sql(500) | SELECTED)
RELEVANT = {"judged": "SELECT lower(p_type) AS domain, l_partkey AS url, p_size <= 25 AS covered, l_linestatus = 'F' AS yes FROM lineitem JOIN part ON l_partkey = p_partkey",
            "per_page": "SELECT covered, domain, url, count_if(yes) AS y, count_if(NOT yes) AS n FROM judged GROUP BY ALL"}
register("x08_relevance_table", lambda c: measures.relevance(worlds.relevance_votes(c.t)), "SELECT covered, domain, CAST(sum(y) AS BIGINT) AS yes, CAST(sum(n) AS BIGINT) AS no, count_if(y > n) AS pages_yes, count_if(y <= n) AS pages_no FROM per_page GROUP BY GROUPING SETS ((covered, domain), (covered))", extra=RELEVANT)
VOTES = {"votes": "SELECT lower(r_name) AS domain, lower(n_name) AS query, CASE l_returnflag WHEN 'R' THEN 'F' WHEN 'N' THEN 'E' ELSE 'A' END AS verdict FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
         "tally": "SELECT domain, query, count_if(verdict = 'F') AS f, count_if(verdict = 'E') AS e, count_if(verdict = 'A') AS a FROM votes GROUP BY ALL"}
register("x09_preference_table", lambda c: measures.preference(worlds.preference_votes(c.t)), "SELECT domain, CAST(sum(f) AS BIGINT) AS f, CAST(sum(e) AS BIGINT) AS e, CAST(sum(a) AS BIGINT) AS a, count_if(f > a) AS qf, count_if(f = a) AS qe, count_if(a > f) AS qa FROM tally GROUP BY ROLLUP (domain)", extra=VOTES)
register("udf_pandas_tail", lambda c: measures.paired_t(worlds.preference_votes(c.t)).select("queries", "mean", "t", toolbox.two_sided_p(F.col("t"), F.col("queries") - 1).alias("p")))
register("x10_paired_t", lambda c: measures.paired_t(worlds.preference_votes(c.t)), "SELECT count(*) AS queries, round(avg(f - a), 6) AS mean, round(avg(f - a) / (stddev_samp(f - a) / sqrt(count(*))), 6) AS t FROM tally", extra=VOTES)


def _gold(c: Commerce) -> DataFrame:
    return worlds.gold_intent(c.pool.select("query", "facet"))


PAIRF = "SELECT round(tp / nullif(made, 0), 6) AS precision, round(tp / nullif(truth, 0), 6) AS recall, round(2 * tp / nullif(made + truth, 0), 6) AS f FROM (SELECT sum(CASE WHEN x.component = y.component AND x.gold = y.gold THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN x.component = y.component THEN 1 ELSE 0 END) AS made, sum(CASE WHEN x.gold = y.gold THEN 1 ELSE 0 END) AS truth FROM golden x JOIN golden y ON x.query = y.query AND x.facet < y.facet)"
GOLD = {"golden": f"SELECT query, facet, component, array_to_string(list_sort({oracles.folded('facet')}), ' ') AS gold FROM comp"}
register("x11_pair_f", lambda c: measures.pair_f(c.clusters, _gold(c)), PAIRF, extra=GOLD)
for method in ("all_pairs", "concat", "words"):
    variant(f"w17_pair_f_{method}", lambda c: measures.pair_f(c.clusters, _gold(c)), PAIRF, extra=GOLD, method=method)
for m in (1, 2, 4, 16):
    variant(f"w18_pair_f_m{m}", lambda c: measures.pair_f(c.clusters, _gold(c)), PAIRF, extra=GOLD, m=m)


def _sigma_sweep(c: Commerce) -> DataFrame:
    grid = c.t.spark.range(1, 20).select((F.col("id") * 5).alias("percent"))
    nodes = c.pool.select("query", "facet").crossJoin(F.broadcast(grid))  # 19 thresholds
    edges = c.sim.crossJoin(F.broadcast(grid)).where(F.col("sim") * 100 > F.col("percent")).select("percent", "query", "a", "b")
    found = cluster.components(nodes, edges).join(c.seeds.select("query", "domain"), "query")
    return measures.pair_f(found, _gold(c), ["percent", "domain"])


SWEEP = {"grid": "SELECT unnest(range(1, 20)) * 5 AS percent",
    "wide": "SELECT percent, query, facet AS a, facet AS b FROM pool, grid UNION SELECT r.percent, r.query, r.a, x.b FROM wide r JOIN (SELECT query, a, b, sim FROM sim UNION SELECT query, b, a, sim FROM sim) x ON x.query = r.query AND x.a = r.b AND x.sim * 100 > r.percent",
    "golden": f"SELECT percent, query, a AS facet, min(b) AS component, array_to_string(list_sort({oracles.folded('a')}), ' ') AS gold FROM wide GROUP BY percent, query, a"}
SWEPT = PAIRF.replace("SELECT round(tp", "SELECT percent, domain, round(tp", 1).replace("SELECT sum(", "SELECT x.percent, s.domain, sum(", 1).replace("x.query = y.query", "x.percent = y.percent AND x.query = y.query").replace("x.facet < y.facet)", "x.facet < y.facet JOIN seeds s ON s.query = x.query GROUP BY x.percent, s.domain)")
register("w14_sigma_sweep", _sigma_sweep, SWEPT, extra=SWEEP)
variant("w14_sigma_sweep_unmasked", _sigma_sweep, SWEPT, extra=SWEEP, strip_seed=False)


def _breadth(c: Commerce) -> DataFrame:
    strata = c.seeds.select("query", F.col("domain").alias("stratum"))
    return measures.breadth(_navigational(c), strata)


register("x12_navigational_breadth", _breadth, "SELECT domain AS stratum, count(*) AS entities, count(CASE WHEN query IN (SELECT query FROM led) THEN 1 END) AS covered FROM seeds GROUP BY ROLLUP (domain)", extra=NAV)
register("x13_class_sparsity", lambda c: measures.sparsity(c.instance, c.nodes), """SELECT n.class, n.property, count(*) AS members, count_if(k >= 8) AS many, count_if(k IS NULL) AS none, any_value((SELECT count(*) FROM (SELECT facet FROM nodes z JOIN inst i ON i.query = z.query WHERE z.class = n.class AND z.property = n.property GROUP BY facet HAVING count(DISTINCT z.query) >= 5))) AS shared
    FROM nodes n LEFT JOIN (SELECT query, count(*) AS k FROM inst GROUP BY query) q ON q.query = n.query GROUP BY n.class, n.property""")


def _ref_super(c: Commerce) -> DataFrame:
    popular = candidates.frequency(c.log).join(c.seeds.select("query"), "query", "left_semi").orderBy(F.col("freq").desc(), "query").limit(10)
    a = candidates.refinement_scores(candidates.succession(c.log, popular)).withColumnRenamed("p_r", "p")
    freq = candidates.frequency(c.log)
    b = candidates.superstring_scores(candidates.superstrings(freq, popular), freq).withColumnRenamed("p_ss", "p")
    return measures.top_overlap(a, b)


register("w03_refine_super_overlap", _ref_super, """SELECT query, count(*) AS shared FROM (SELECT query, candidate FROM p_r QUALIFY row_number() OVER (PARTITION BY query ORDER BY round(p_r, 9) DESC, candidate) <= 10) JOIN
    (SELECT query, candidate FROM p_ss QUALIFY row_number() OVER (PARTITION BY query ORDER BY round(p_ss, 9) DESC, candidate) <= 10) USING (query, candidate) WHERE query IN (SELECT query FROM popular) GROUP BY query""",
    extra={"popular": "SELECT query FROM freq WHERE query IN (SELECT query FROM seeds) ORDER BY freq DESC, query LIMIT 10"})


def _class_vs_kb(c: Commerce) -> DataFrame:
    cls = propagate.class_scores(c.instance, c.nodes).groupBy("class", "facet").agg(F.avg("p_class").alias("s"))
    top = cls.withColumn("r", F.row_number().over(W.partitionBy("class").orderBy(F.round("s", 9).desc(), "facet"))).where("r <= 10").select("class", textkit.label(F.col("facet")).alias("word"))
    kb = worlds.attributes(c.t).select("class", F.col("attribute").alias("word"), F.lit(1).alias("known"))
    return top.join(kb, ["class", "word"], "left").groupBy("class").agg(F.count("*").alias("facets"), F.count("known").alias("in_kb"))


register("w02_class_vs_kb_attributes", _class_vs_kb, "SELECT t.class, count(*) AS facets, count(a.attribute) AS in_kb FROM top10 t LEFT JOIN attrs a ON a.class = t.class AND a.attribute = t.word GROUP BY t.class",
    extra=ATTR | {"cls_mean": "SELECT class, facet, avg(p_class) AS s FROM cls GROUP BY ALL", "top10": "SELECT class, trim(replace(facet, '<q>', '')) AS word FROM cls_mean QUALIFY row_number() OVER (PARTITION BY class ORDER BY round(s, 9) DESC, facet) <= 10"})


def _kb_in_top(c: Commerce) -> DataFrame:
    ent = c.seeds.select("entity", "domain").distinct()
    sup = candidates.superstrings(candidates.frequency(c.log), ent.select(F.col("entity").alias("query")))
    top = sup.withColumn("r", F.row_number().over(W.partitionBy("query").orderBy(F.col("freq").desc(), "candidate"))).where("r <= 10")
    words = top.select(F.col("query").alias("entity"), "candidate", F.explode(F.split("candidate", " ")).alias("attribute")).join(ent, "entity")
    kb = worlds.attributes(c.t).select(F.col("class").alias("domain"), "attribute")
    return words.join(kb, ["domain", "attribute"]).groupBy("entity").agg(F.count_distinct("candidate").alias("hits"))


register("w20_kb_in_top_queries", _kb_in_top, """SELECT entity, count(DISTINCT query) AS hits FROM (SELECT s.entity, s.domain, f.query, unnest(string_split(f.query, ' ')) AS w FROM (SELECT DISTINCT entity, domain FROM seeds) s JOIN freq f ON contains(' ' || f.query || ' ', ' ' || s.entity || ' ') AND f.query <> s.entity
    QUALIFY row_number() OVER (PARTITION BY s.entity ORDER BY f.freq DESC, f.query) <= 10) x JOIN attrs a ON a.class = x.domain AND a.attribute = x.w GROUP BY entity""", extra=ATTR)


def _pair(a: float, b: float) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        top = lambda k: capped(commerce(spark, folder, Params(k=k)).scored, 8).select("query", F.row_number().over(W.partitionBy("query").orderBy(F.round("score", 9).desc(), "facet")).alias("rank"), F.col("facet").alias("group_label"))
        return shaped(measures.same_list(top(a), top(b)).select(F.lit(float(a)).alias("k1"), F.lit(float(b)).alias("k2"), "seeds", "same"))

    return run


def _top_sql(k: float) -> str:
    e = oracles.expressions(k=k)
    return e["scored"]


for a, b in ((0, 0.1), (0, 1), (0.1, 1), (0.1, 10), (1, 10), (1, 100), (10, 100)):
    name = f"w13_k_pair_{a}_{b}".replace(".", "p")
    QUERIES[name] = _pair(a, b)
    lists = "SELECT query, list(facet ORDER BY r) AS facets FROM (SELECT query, facet, row_number() OVER (PARTITION BY query ORDER BY round(score, 9) DESC, facet) AS r FROM {0}) WHERE r <= 8 GROUP BY query"
    ORACLES[name] = oracles.oracle(f"SELECT {float(a)}::DOUBLE AS k1, {float(b)}::DOUBLE AS k2, count(*) AS seeds, count_if(x.facets = y.facets) AS same FROM listed_a x JOIN listed_b y USING (query)",
        {"scored_a": _top_sql(a), "scored_b": _top_sql(b), "listed_a": lists.format("scored_a"), "listed_b": lists.format("scored_b")})


def _mode_difference(spark: SparkSession, folder: str) -> DataFrame:
    top = lambda mode: capped(commerce(spark, folder, Params(mode=mode)).scored, 8).select("query", "facet")
    return shaped(top("mean").join(top("indicator"), ["query", "facet"]).groupBy("query").agg(F.count("*").alias("shared")))


QUERIES["w19_class_mode_ablation"] = _mode_difference
_best8 = "SELECT query, facet FROM {0} QUALIFY row_number() OVER (PARTITION BY query ORDER BY round(score, 9) DESC, facet) <= 8"
ORACLES["w19_class_mode_ablation"] = oracles.oracle("SELECT query, count(*) AS shared FROM best_a JOIN best_b USING (query, facet) GROUP BY query", {"cls_a": oracles.expressions(mode="mean")["cls"], "scored_a": oracles.expressions()["scored"].replace("JOIN cls ", "JOIN cls_a "), "best_a": _best8.format("scored_a"), "best_b": _best8.format("scored")})
register("x18_grouped_rate", lambda c: c.groups.groupBy("query").agg(F.max((F.col("kind") == "group").cast("int")).alias("g")).agg(F.count("*").alias("seeds"), F.sum("g").alias("grouped")), "SELECT count(*) AS seeds, CAST(sum(g) AS BIGINT) AS grouped FROM (SELECT query, max(CASE WHEN kind = 'group' THEN 1 ELSE 0 END) AS g FROM groups GROUP BY query)")
variant("x18_grouped_rate_vote", lambda c: c.groups.groupBy("query").agg(F.max((F.col("kind") == "group").cast("int")).alias("g")).agg(F.count("*").alias("seeds"), F.sum("g").alias("grouped")), "SELECT count(*) AS seeds, CAST(sum(g) AS BIGINT) AS grouped FROM (SELECT query, max(CASE WHEN kind = 'group' THEN 1 ELSE 0 END) AS g FROM groups GROUP BY query)", ambiguity="vote")

# --- systems side by side -------------------------------------------------------------------
def _systems(c: Commerce) -> DataFrame:
    """``system, query, rank, facet, posed``: the lists of the engine and of the three baselines."""
    best = c.ranked.join(c.groups.select("query", "group_label", F.get("members", 0).alias("key")), ["query", "group_label"])
    engine = best.join(c.pool.select("query", F.col("facet").alias("key"), "facet_query"), ["query", "key"]).select("query", "rank", textkit.label(F.col("group_label")).alias("facet"), F.col("facet_query").alias("posed"))
    related = baselines.related(candidates.mine(c.log, c.seeds)).select("query", "rank", F.col("group_label").alias("facet"), F.col("group_label").alias("posed"))
    words = _cluster_labels(c).select("query", "rank", F.col("group_label").alias("facet"), F.concat_ws(" ", "query", "group_label").alias("posed"))
    nav = _navigational(c).withColumnRenamed("group_label", "facet")
    nav = candidates.posed(nav, c.seeds).select("query", "rank", textkit.label(F.col("facet")).alias("facet"), F.col("facet_query").alias("posed"))
    out = None
    for name, rows in (("engine", engine), ("related", related), ("clusterlabels", words), ("navigational", nav)):
        rows = rows.select(F.lit(name).alias("system"), "query", "rank", "facet", "posed")
        out = rows if out is None else out.unionByName(rows)
    return out


_instead = lambda text: f"replace(replace({text}, '<q>', s.query), '<e>', s.entity)"
SYSTEMS = NAV | _seed_sql(500) | SELECTED | {
    "worded2": f"SELECT query, term, count(*) * ln((1 + any_value(n)) / (1 + any_value(df))) AS s FROM seed_hits JOIN postings USING (doc_id) JOIN terms USING (term), totals WHERE NOT list_contains({oracles.folded('query')}, term) GROUP BY query, term",
    "list_engine": "SELECT r.query, r.rank, trim(replace(r.group_label, '<q>', '')) AS facet, p.facet_query AS posed FROM ranked r JOIN groups g ON g.query = r.query AND g.group_label = r.group_label JOIN pool p ON p.query = r.query AND p.facet = split_part(g.members, ',', 1)",
    "list_related": f"SELECT query, rank, group_label AS facet, group_label AS posed FROM ({TOP.format(label='candidate', score='p_inst', table='cand')})",
    "list_words": f"SELECT query, rank, group_label AS facet, query || ' ' || group_label AS posed FROM ({TOP.format(label='term', score='s', table='worded2')})",
    "list_nav": f"SELECT t.query, rank, trim(replace(group_label, '<q>', '')) AS facet, {_instead('group_label')} AS posed FROM ({TOP.format(label='facet', score='p_class', table='led')}) t JOIN seeds s ON s.query = t.query",
    "systems": "SELECT 'engine' AS system, * FROM list_engine UNION ALL SELECT 'related', * FROM list_related UNION ALL SELECT 'clusterlabels', * FROM list_words UNION ALL SELECT 'navigational', * FROM list_nav",
}
register("w01_systems_side_by_side", _systems, "SELECT system, query, rank, facet, posed FROM systems", extra=SYSTEMS)


def _nsim_by_system(c: Commerce) -> DataFrame:
    """Mean asim, isim and nsim of each system over the seeds where it has two facets or more."""
    lists = cut(_systems(c), "systems")
    hits = retrieve.top_hits(lists.select(F.col("posed").alias("query_text")), c.index, c.p.m)
    pages = lists.join(hits, lists["posed"] == hits["query_text"]).select(F.concat_ws("|", "system", "query").alias("query"), "facet", "doc_id").distinct()
    each = measures.orthogonality(_eval_sim(c, pages)).where("asim is not null")
    return each.groupBy(F.split_part("query", F.lit("|"), F.lit(1)).alias("system")).agg(F.count("*").alias("seeds"), F.avg("asim").alias("asim"), F.avg("isim").alias("isim"), F.avg("nsim").alias("nsim"))


register("w05_nsim_by_system", _nsim_by_system)


def _suite(c: Commerce) -> DataFrame:
    """Six seed sets, each with its 5 most and 5 least frequent names and 5 of the rest by hash; short sets are whole."""
    freq = candidates.frequency(c.log)
    sets = {"nation": c.t.nation.select(F.lower("n_name")), "part": c.t.part.select(F.lower("p_name")), "brand": c.t.part.select(F.lower("p_brand")), "supplier": c.t.supplier.select(F.lower("s_name")), "segment": c.t.customer.select(F.lower("c_mktsegment")), "nation and segment": c.seeds.select("query")}
    rows = None
    for name, names in sets.items():
        one = names.toDF("query").distinct().select(F.lit(name).alias("domain"), "query")
        rows = one if rows is None else rows.unionByName(one)
    counted = rows.join(freq, "query", "left").withColumn("freq", F.coalesce("freq", F.lit(0)))
    by = lambda *order: F.row_number().over(W.partitionBy("domain").orderBy(*order))
    ends = counted.withColumn("high", by(F.col("freq").desc(), "query")).withColumn("low", by("freq", F.col("query").desc()))
    kind = F.when(F.col("high") <= 5, "frequent").when(F.col("low") <= 5, "rare").otherwise("random")
    drawn = ends.withColumn("stratum", kind).withColumn("turn", F.row_number().over(W.partitionBy("domain", "stratum").orderBy(F.md5("query"), "query")))
    return drawn.where("turn <= 5").select("domain", "query", "stratum", "freq")


SUITE = {"named6": "SELECT 'nation' AS domain, lower(n_name) AS query FROM nation UNION SELECT 'part', lower(p_name) FROM part UNION SELECT 'brand', lower(p_brand) FROM part UNION SELECT 'supplier', lower(s_name) FROM supplier UNION SELECT 'segment', lower(c_mktsegment) FROM customer UNION SELECT 'nation and segment', query FROM seeds",
         "counted6": "SELECT domain, query, coalesce(freq, 0) AS freq, row_number() OVER (PARTITION BY domain ORDER BY coalesce(freq, 0) DESC, query) AS high, row_number() OVER (PARTITION BY domain ORDER BY coalesce(freq, 0), query DESC) AS low FROM named6 LEFT JOIN freq USING (query)",
         "drawn6": "SELECT domain, query, freq, CASE WHEN high <= 5 THEN 'frequent' WHEN low <= 5 THEN 'rare' ELSE 'random' END AS stratum FROM counted6"}
register("w04_test_suite", _suite, "SELECT domain, query, stratum, freq FROM drawn6 QUALIFY row_number() OVER (PARTITION BY domain, stratum ORDER BY md5(query), query) <= 5", extra=SUITE)


def _side_by_side(c: Commerce) -> DataFrame:
    """For each baseline and seed that both have: the two lists, cut to one length, on sides that a hash draws."""
    lists = cut(_systems(c), "systems")
    packed = lists.groupBy("system", "query").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "facet"))), lambda x: x["facet"]).alias("items"))
    mine = packed.where("system = 'engine'").select("query", F.col("items").alias("own"))
    pairs = packed.where("system <> 'engine'").join(mine, "query").withColumn("n", F.least(F.size("own"), F.size("items")))
    swap = F.substring(F.md5(F.concat_ws("|", "system", "query")), 1, 1) < "8"
    own, other = F.array_join(F.slice("own", 1, F.col("n")), " | "), F.array_join(F.slice("items", 1, F.col("n")), " | ")
    return pairs.select(F.col("system").alias("baseline"), "query", F.when(swap, "right").otherwise("left").alias("engine_side"), F.when(swap, other).otherwise(own).alias("left"), F.when(swap, own).otherwise(other).alias("right"))


register("w08_side_by_side_lists", _side_by_side, """SELECT baseline, query, CASE WHEN swap THEN 'right' ELSE 'left' END AS engine_side, array_to_string(CASE WHEN swap THEN o ELSE e END, ' | ') AS left, array_to_string(CASE WHEN swap THEN e ELSE o END, ' | ') AS right FROM (
    SELECT b.system AS baseline, b.query, left(md5(b.system || '|' || b.query), 1) < '8' AS swap, b.items[1:least(len(a.items), len(b.items))] AS o, a.items[1:least(len(a.items), len(b.items))] AS e FROM packed6 a JOIN packed6 b ON a.query = b.query WHERE a.system = 'engine' AND b.system <> 'engine')""",
    extra=SYSTEMS | {"packed6": "SELECT system, query, list(facet ORDER BY rank, facet) AS items FROM systems GROUP BY ALL"})


def _all_breadth(c: Commerce) -> DataFrame:
    """Entities with a class-level facet over all classes, by frequency stratum and in total (null)."""
    every = c.t.region.select(F.lower("r_name").alias("class"))
    nav = baselines.navigational(propagate.class_scores(c.instance, c.nodes), c.nodes, every)
    counted = c.seeds.select("query").join(candidates.frequency(c.log), "query", "left").withColumn("freq", F.coalesce("freq", F.lit(0)))
    third = F.ntile(3).over(W.orderBy(F.col("freq").desc(), "query"))  # of the seeds, 125 names
    return measures.breadth(nav, counted.select("query", F.element_at(F.array(F.lit("popular"), F.lit("middle"), F.lit("rare")), third).alias("stratum")))


register("w11_navigational_breadth", _all_breadth, "SELECT stratum, count(*) AS entities, count(CASE WHEN query IN (SELECT query FROM led) THEN 1 END) AS covered FROM thirds GROUP BY ROLLUP (stratum)",
    extra=NAV | {"led": NAV["led"].replace(" WHERE r_regionkey <= 1", ""), "thirds": "SELECT query, ['popular', 'middle', 'rare'][ntile(3) OVER (ORDER BY coalesce(freq, 0) DESC, query)] AS stratum FROM seeds LEFT JOIN freq USING (query)"})


def _grouping_effect(spark: SparkSession, folder: str) -> DataFrame:
    """For each seed that groups: entries of its list with and without grouping, and the entries in both."""
    on, off = commerce(spark, folder), commerce(spark, folder, Params(grouping=False))
    some = on.groups.where("kind = 'group'").select("query").distinct()
    a, b = on.ranked.join(some, "query", "left_semi"), off.ranked.join(some, "query", "left_semi").select("query", "group_label", F.lit(1).alias("kept"))
    return shaped(a.join(b, ["query", "group_label"], "full_outer").groupBy("query").agg(F.count("rank").alias("grouped"), F.count("kept").alias("plain"), F.count(F.when(F.col("rank").isNotNull() & F.col("kept").isNotNull(), 1)).alias("shared")))


QUERIES["w15_grouping_effect"] = _grouping_effect
register("w18_page_pairs", lambda c: similarity.doc_pairs(c.vectors).groupBy("query").agg(F.count("*").alias("pairs")), "SELECT query, count(*) AS pairs FROM pairs WHERE d1 <= d2 GROUP BY query")


def _cost_counters(c: Commerce) -> DataFrame:
    """Rows that each stage hands on: scored candidates, capped facets, pages, compared page pairs."""
    out = None
    for stage, rows in (("candidates", c.instance), ("facets", c.pool), ("pages", c.hits), ("page_pairs", similarity.doc_pairs(c.vectors))):
        row = rows.agg(F.lit(stage).alias("stage"), F.count("*").alias("rows"))
        out = row if out is None else out.unionByName(row)
    return out


register("x19_cost_counters", _cost_counters, "SELECT 'candidates' AS stage, count(*) AS rows FROM inst UNION ALL SELECT 'facets', count(*) FROM pool UNION ALL SELECT 'pages', count(*) FROM hits UNION ALL SELECT 'page_pairs', count(*) FROM pairs WHERE d1 <= d2")
register("m22_kmeans", lambda c: cluster.kmeans_by_query(similarity.facet_vectors(c.hits, c.vectors)))
register("m22_spectral", lambda c: cluster.spectral_by_query(c.pool, c.sim))


def _clusterers(c: Commerce) -> DataFrame:
    """Pairwise precision, recall and F of each way to cluster the facets."""
    gold, out = _gold(c), None
    ways = {"components": c.clusters, "star": cluster.star_cover(c.pool, cluster.threshold_edges(c.sim)).withColumnRenamed("center", "component"),
            "kmeans": cluster.kmeans_by_query(similarity.facet_vectors(c.hits, c.vectors)).withColumnRenamed("cluster", "component"), "spectral": cluster.spectral_by_query(c.pool, c.sim).withColumnRenamed("cluster", "component")}
    for name, found in ways.items():
        row = measures.pair_f(found.select("query", "facet", "component"), gold).select(F.lit(name).alias("clusterer"), "precision", "recall", "f")
        out = row if out is None else out.unionByName(row)
    return out


register("b11_clusterers", _clusterers)

# --- relational operators -------------------------------------------------------------------

for _name, (_make, _sql) in relops.OPERATORS.items():
    QUERIES[_name] = lambda spark, folder, make=_make: make(worlds.Tables(spark, folder))
    ORACLES[_name] = _sql
for _name, (_make, _sql) in toolbox.OPERATORS.items():
    QUERIES[_name] = lambda spark, folder, make=_make: make(worlds.Tables(spark, folder))
    if _sql:
        ORACLES[_name] = _sql
for _name, _make in relops.SKETCHES.items():
    QUERIES[_name] = lambda spark, folder, make=_make: make(worlds.Tables(spark, folder))

# --- streams --------------------------------------------------------------------------------
STREAMS = {
    "stream_incremental_counts": (logs.query_counts, f"SELECT query, count(*) AS freq FROM ({CLICKS}) GROUP BY query"),
    "stream_tumbling": (logs.daily_counts, "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1"),
    "stream_dedupe": (logs.distinct_events, f"SELECT query, count(*) AS n FROM ({CLICKS}) GROUP BY query"),
    "stream_session": (logs.closed_sessions, None),
    "stream_sliding": (logs.sliding_counts, "SELECT strftime(time_bucket(INTERVAL 6 HOURS, ts) - k * INTERVAL 6 HOURS, '%Y-%m-%d %H') AS start, count(*) AS n FROM events, range(0, 4) g(k) GROUP BY 1"),
    "stream_static_join": (lambda spark, path: logs.segment_counts(spark, path, spark.read.parquet(path.replace("events.parquet", "customer.parquet"))), "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1"),
    "stream_interval_join": (logs.followed_events, f"SELECT a.event_id AS a, b.event_id AS b FROM {relops.EV} a JOIN {relops.EV} b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR WHERE a.k < 50 AND b.k >= 50"),
    "stream_pairs": (logs.next_queries, f"SELECT query, next, count(*) AS n FROM (SELECT query, lead(query) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next FROM ({CLICKS})) WHERE next <> query GROUP BY ALL"),
    "stream_late": (logs.late_rows, "SELECT count(*) AS counted, 3 AS dropped FROM events"),
}
for _name, (_make, _sql) in STREAMS.items():
    QUERIES[_name] = lambda spark, folder, make=_make: make(spark, f"{folder}/events.parquet")
    if _sql:
        ORACLES[_name] = _sql


def _plain_counts(sql: str) -> str:
    """``count_if(x)`` as ``count(nullif(x, false))``, which DuckDB counts in 64 bits."""
    while (at := sql.find("count_if(")) >= 0:
        depth, end = 1, at + len("count_if(")
        while depth:
            depth += {"(": 1, ")": -1}.get(sql[end], 0)
            end += 1
        sql = f"{sql[:at]}count(nullif({sql[at + len('count_if(') : end - 1]}, false)){sql[end:]}"
    return sql


ORACLES = {name: _plain_counts(sql) for name, sql in ORACLES.items()}
