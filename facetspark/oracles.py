"""DuckDB SQL of the methods, built from named table expressions.

``oracle(select, ...)`` returns the select with the expressions that it needs, for given
parameters. The SQL is written independently of the DataFrame code: no shared text.
"""

from __future__ import annotations

import re

TOK = r"regexp_split_to_array(lower({0}), '[^\p{{L}}\p{{N}}_#]+')"
FOLDED = "list_transform(list_filter(" + TOK + ", lambda t: t <> ''), lambda t: CASE WHEN length(t) > 3 AND regexp_matches(t, '[^s]s$') THEN left(t, length(t) - 1) ELSE t END)"


def folded(text: str) -> str:
    return FOLDED.format(text)


def found(numbered: str, m: int) -> str:
    """The best documents of numbered texts."""
    return f"""SELECT text, doc_id, relevance, rank FROM (SELECT tid, doc_id, relevance, row_number() OVER (PARTITION BY tid ORDER BY relevance DESC, doc_id) AS rank FROM (
      SELECT tid, doc_id, round(sum(w), 9) AS relevance FROM (SELECT tid, unnest(list_distinct({folded("text")})) AS term FROM {numbered}) a JOIN weighted USING (term) GROUP BY tid, doc_id)
      QUALIFY rank <= {m}) x JOIN {numbered} y USING (tid)"""


def expressions(*, k=0.1, mode="indicator", sources=("refine", "super"), follow="any_later", match="token", cap=30, m=8, n=8, sigma=0.35, method="best_match", body=False, strip=True, ambiguity="drop", grouping=True, dedupe=True) -> dict[str, str]:
    e: dict[str, str] = {}
    e["lines"] = """SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, o_custkey, o_orderdate, p_size,
      row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) AS step,
      lower(n_name) AS ent, lower(c_mktsegment) AS prop, lower(p_name) AS name, split_part(lower(p_name), ' ', 1) AS adj, split_part(lower(p_name), ' ', 2) AS noun,
      lower(p_type) AS type, lower(p_brand) AS brand, lower(s_name) AS supp, lower(o_orderpriority) AS priority
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
      JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"""
    e["log"] = """SELECT o_custkey AS user_id, l_orderkey AS session_id, step, o_orderdate + to_minutes(step) AS ts,
      CASE WHEN step = 1 THEN ent WHEN step = 2 THEN CASE WHEN l_orderkey % 7 = 0 THEN prop ELSE ent || ' ' || prop END
        WHEN step % 4 = 3 THEN ent || ' ' || prop || ' ' || noun || CASE WHEN l_linenumber % 2 = 1 THEN 's' ELSE '' END
        WHEN step % 4 = 0 THEN ent || ' ' || prop || ' ' || type
        WHEN step % 4 = 1 THEN ent || ' ' || CASE WHEN l_linenumber % 2 = 0 THEN noun || ' ' || adj ELSE name END
        WHEN l_suppkey % 4 = 0 THEN name WHEN l_suppkey % 4 = 1 THEN brand WHEN l_suppkey % 4 = 2 THEN brand || ' ' || noun ELSE supp END AS query FROM lines"""
    e["seeds"] = """SELECT lower(n_name) || ' ' || s.property AS query, lower(n_name) AS entity, s.property, lower(r_name) AS domain
      FROM nation JOIN region ON n_regionkey = r_regionkey, (SELECT DISTINCT lower(c_mktsegment) AS property FROM customer) s"""
    e["freq"] = "SELECT query, count(*) AS freq FROM log GROUP BY query"
    if follow == "next":
        e["succ"] = """SELECT query, candidate, count(*) AS sessions FROM (SELECT DISTINCT session_id, query, candidate FROM
          (SELECT session_id, query, lead(query) OVER (PARTITION BY session_id ORDER BY step) AS candidate FROM log) WHERE candidate <> query AND query IN (SELECT query FROM seeds)) GROUP BY ALL"""
    else:
        e["succ"] = """SELECT a.query, b.query AS candidate, count(DISTINCT a.session_id) AS sessions FROM log a JOIN log b
          ON a.session_id = b.session_id AND b.step > a.step AND a.query <> b.query WHERE a.query IN (SELECT query FROM seeds) GROUP BY ALL"""
    e["p_r"] = "SELECT query, candidate, sessions / sum(sessions) OVER (PARTITION BY query) AS p_r FROM succ"
    inside = "contains(' ' || f.query || ' ', ' ' || s.query || ' ')" if match == "token" else "contains(f.query, s.query)"
    e["sup"] = f"SELECT s.query, f.query AS candidate, f.freq FROM seeds s JOIN freq f ON {inside} AND f.query <> s.query"
    e["p_ss"] = """SELECT s.query, s.candidate, s.freq / (coalesce(f.freq, 0) + sum(s.freq) OVER (PARTITION BY s.query)) AS p_ss, s.freq / nullif(coalesce(f.freq, 0), 0) AS upper
      FROM sup s LEFT JOIN freq f ON f.query = s.query"""
    union = " UNION ALL ".join(x for x, on in (("SELECT query, candidate, p_r AS p FROM p_r", "refine" in sources), ("SELECT query, candidate, p_ss AS p FROM p_ss", "super" in sources)) if on)
    e["cand"] = f"SELECT query, candidate, max(p) / sum(max(p)) OVER (PARTITION BY query) AS p_inst FROM ({union}) GROUP BY query, candidate"
    e["inst"] = """SELECT query, facet, max(p_inst) AS score FROM (SELECT c.query, p_inst,
      CASE WHEN contains(' ' || candidate || ' ', ' ' || c.query || ' ') THEN '<q> ' || trim(replace(' ' || candidate || ' ', ' ' || c.query || ' ', ' '))
           WHEN contains(' ' || candidate || ' ', ' ' || entity || ' ') THEN trim(replace(' ' || candidate || ' ', ' ' || entity || ' ', ' <e> ')) ELSE candidate END AS facet
      FROM cand c JOIN seeds s ON c.query = s.query) GROUP BY query, facet"""
    e["members"] = """SELECT lower(n_name) AS entity, lower(r_name) AS class FROM nation JOIN region ON n_regionkey = r_regionkey
      UNION SELECT lower(p_name), split_part(lower(p_name), ' ', 2) FROM part UNION SELECT split_part(lower(p_name), ' ', 1), 'adjective' FROM part
      UNION SELECT lower(p_type), 'type' FROM part UNION SELECT lower(p_brand), 'brand' FROM part UNION SELECT lower(c_mktsegment), 'segment' FROM customer
      UNION SELECT lower(s_name), lower(n_name) FROM supplier JOIN nation ON s_nationkey = n_nationkey"""
    e["unsure"] = "SELECT entity FROM members GROUP BY entity HAVING count(*) > 1"
    e["alias"] = """SELECT DISTINCT split_part(lower(p_name), ' ', 2) || ' ' || split_part(lower(p_name), ' ', 1) AS alias, lower(p_name) AS entity FROM part
      UNION SELECT split_part(lower(p_name), ' ', 2) || 's', split_part(lower(p_name), ' ', 2) FROM part UNION SELECT replace(lower(n_name), 'nation_', 'n'), lower(n_name) FROM nation"""
    e["nodes"] = "SELECT DISTINCT query, class, property FROM seeds JOIN members USING (entity)"
    value = "score" if mode == "mean" else "CASE WHEN score > 0 THEN 1.0 ELSE 0 END"
    e["cls"] = f"""SELECT class, property, facet, sum(v) / any_value(size) AS p_class FROM (SELECT n.class, n.property, facet, {value} AS v,
      (SELECT count(*) FROM nodes z WHERE z.class = n.class AND z.property = n.property) AS size FROM nodes n JOIN inst i ON n.query = i.query) GROUP BY ALL"""
    if k == 0:
        e["scored"] = "SELECT query, facet, score FROM inst"
    else:
        mixed = "coalesce(c.p_class, 0)" if k == float("inf") else f"(coalesce(i.score, 0) + {float(k)} * coalesce(c.p_class, 0)) / {1 + float(k)}"
        e["scored"] = f"""SELECT coalesce(i.query, c.query) AS query, coalesce(i.facet, c.facet) AS facet, {mixed} AS score
          FROM inst i FULL JOIN (SELECT n.query, facet, p_class FROM nodes n JOIN cls USING (class, property)) c ON i.query = c.query AND i.facet = c.facet WHERE {mixed} > 0"""
    e["pool"] = f"""SELECT s.query, s.facet, s.score, replace(replace(s.facet, '<q>', s.query), '<e>', entity) AS facet_query FROM scored s JOIN seeds USING (query)
      QUALIFY row_number() OVER (PARTITION BY s.query ORDER BY round(s.score, 9) DESC, s.facet) <= {cap}"""
    snippet = "ent || ' ' || prop || ' ' || type || ' ' || brand || ' s' || l_suppkey || ' z' || p_size || ' ' || split_part(priority, '-', 2)"
    text = snippet + " || ' c' || o_custkey || ' p' || l_partkey || ' m' || strftime(o_orderdate, '%Y%m')" if body else "name || ' ' || " + snippet
    e["postings"] = f"SELECT term, doc_id, count(*) AS tf FROM (SELECT l_orderkey * 100 + step AS doc_id, unnest({folded(text)}) AS term FROM lines) GROUP BY ALL"
    e["docs"] = "SELECT doc_id, sum(tf) AS len FROM postings GROUP BY doc_id"
    e["terms"] = "SELECT term, count(*) AS df FROM postings GROUP BY term"
    e["totals"] = "SELECT count(*) AS n, avg(len) AS avg_len FROM docs"
    e["weighted"] = """SELECT p.term, p.doc_id, ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len / avg_len)) AS w
      FROM postings p JOIN terms USING (term) JOIN docs d ON d.doc_id = p.doc_id, totals"""
    e["numbered"] = "SELECT text, row_number() OVER (ORDER BY text) AS tid FROM asked"
    e["found"] = found("numbered", m)
    e["asked"] = "SELECT DISTINCT facet_query AS text FROM pool"
    e["hits"] = "SELECT query, facet, doc_id, rank FROM pool JOIN found ON text = facet_query"
    own = f"AND NOT list_contains({folded('query')}, term)" if strip else ""
    e["vectors"] = f"""SELECT query, doc_id, term, w / sqrt(sum(w * w) OVER (PARTITION BY query, doc_id)) AS weight FROM (
      SELECT query, h.doc_id, term, tf * ln((1 + n) / (1 + df)) AS w FROM (SELECT DISTINCT query, doc_id FROM hits) h JOIN postings USING (doc_id) JOIN terms USING (term), totals WHERE true {own})"""
    e["pairs"] = "SELECT a.query, a.doc_id AS d1, b.doc_id AS d2, sum(a.weight * b.weight) AS dsim FROM vectors a JOIN vectors b ON a.query = b.query AND a.term = b.term GROUP BY ALL"
    e["sizes"] = "SELECT query, facet, count(*) AS n FROM hits GROUP BY ALL"
    e["near"] = f"SELECT p.query, d1, facet AS b, {'sum' if method == 'all_pairs' else 'max'}(dsim) AS s FROM pairs p JOIN hits h ON h.query = p.query AND h.doc_id = p.d2 GROUP BY ALL"
    e["toward"] = "SELECT n.query, h.facet AS a, n.b, sum(s) AS s FROM near n JOIN hits h ON h.query = n.query AND h.doc_id = n.d1 WHERE h.facet <> n.b GROUP BY ALL"
    if method == "best_match":
        e["sim"] = """SELECT t.query, least(a, b) AS a, greatest(a, b) AS b, round(sum(s / (2 * n)), 9) AS sim FROM toward t JOIN sizes z ON z.query = t.query AND z.facet = t.a GROUP BY t.query, least(a, b), greatest(a, b)"""
    elif method == "all_pairs":
        e["sim"] = "SELECT t.query, a, b, round(s / (x.n * y.n), 9) AS sim FROM toward t JOIN sizes x ON x.query = t.query AND x.facet = a JOIN sizes y ON y.query = t.query AND y.facet = b WHERE a < b"
    elif method == "concat":
        e["joined"] = "SELECT query, facet, term, w / sqrt(sum(w * w) OVER (PARTITION BY query, facet)) AS w FROM (SELECT h.query, facet, term, sum(weight) AS w FROM hits h JOIN vectors v ON v.query = h.query AND v.doc_id = h.doc_id GROUP BY ALL)"
        e["sim"] = "SELECT a.query, a.facet AS a, b.facet AS b, round(sum(a.w * b.w), 9) AS sim FROM joined a JOIN joined b ON a.query = b.query AND a.term = b.term AND a.facet < b.facet GROUP BY ALL"
    else:
        e["worded"] = f"SELECT query, facet, list_distinct({folded("trim(replace(facet, '<q>', ''))")}) AS t FROM pool"
        e["sim"] = """SELECT a.query, a.facet AS a, b.facet AS b, round(len(list_intersect(a.t, b.t)) / len(list_distinct(list_concat(a.t, b.t))), 9) AS sim
          FROM worded a JOIN worded b ON a.query = b.query AND a.facet < b.facet WHERE len(list_intersect(a.t, b.t)) > 0"""
    e["edges"] = f"SELECT query, a, b FROM sim WHERE sim > {sigma if dedupe else 9}"
    e["reach"] = """SELECT query, facet AS a, facet AS b FROM pool UNION SELECT r.query, r.a, x.b FROM reach r JOIN (SELECT query, a, b FROM edges UNION SELECT query, b, a FROM edges) x ON x.query = r.query AND x.a = r.b"""
    e["comp"] = "SELECT query, a AS facet, min(b) AS component FROM reach GROUP BY ALL"
    e["clusters"] = """SELECT c.query, c.facet, component, first_value(c.facet) OVER (PARTITION BY c.query, component ORDER BY round(score, 9) DESC, c.facet) AS cluster_label, score FROM comp c JOIN pool p ON p.query = c.query AND p.facet = c.facet"""
    e["labels"] = "SELECT query, facet, score FROM clusters WHERE facet = cluster_label"
    e["subs"] = """SELECT DISTINCT query, facet, array_to_string(t[i:j], ' ') AS phrase FROM (SELECT query, facet, t, i, unnest(range(i, len(t) + 1)) AS j FROM (
      SELECT query, facet, string_split(trim(replace(facet, '<q>', '')), ' ') AS t, unnest(range(1, len(string_split(trim(replace(facet, '<q>', '')), ' ')) + 1)) AS i FROM labels))"""
    e["senses"] = """SELECT DISTINCT query, facet, entity, class FROM (SELECT s.query, s.facet, m.entity, m.class, length(phrase) AS size, max(length(phrase)) OVER (PARTITION BY s.query, s.facet) AS most
      FROM subs s LEFT JOIN alias a ON a.alias = s.phrase JOIN members m ON m.entity = coalesce(a.entity, s.phrase)) WHERE size = most"""
    if ambiguity == "vote":
        e["matched"] = "SELECT query, facet, entity, class FROM (SELECT s.*, (SELECT count(DISTINCT z.facet) FROM senses z WHERE z.query = s.query AND z.class = s.class) AS v FROM senses s) QUALIFY row_number() OVER (PARTITION BY query, facet ORDER BY v DESC, class, entity) = 1"
    else:
        e["matched"] = "SELECT query, facet, entity, class FROM senses WHERE entity NOT IN (SELECT entity FROM unsure) QUALIFY row_number() OVER (PARTITION BY query, facet ORDER BY class, entity) = 1"
    big = "SELECT query, class FROM matched GROUP BY ALL HAVING count(DISTINCT entity) >= 2" if grouping else "SELECT query, class FROM matched WHERE false"
    e["placed"] = f"""SELECT l.query, l.facet, l.score, coalesce(b.class, l.facet) AS group_label, CASE WHEN b.class IS NULL THEN 'single' ELSE 'group' END AS kind
      FROM labels l LEFT JOIN matched m ON m.query = l.query AND m.facet = l.facet LEFT JOIN ({big}) b ON b.query = m.query AND b.class = m.class"""
    e["groups"] = "SELECT query, group_label, kind, max(score) AS score, array_to_string(list(facet ORDER BY round(score, 9) DESC, facet), ',') AS members FROM placed GROUP BY query, group_label, kind"
    e["gsim"] = """SELECT x.query, p.group_label AS a, q.group_label AS b, max(sim) AS sim FROM (SELECT query, a, b, sim FROM sim UNION ALL SELECT query, b, a, sim FROM sim) x
      JOIN placed p ON p.query = x.query AND p.facet = x.a JOIN placed q ON q.query = x.query AND q.facet = x.b WHERE p.group_label <> q.group_label GROUP BY ALL"""
    done = "SELECT NULL::VARCHAR AS query, 0 AS rank, NULL::VARCHAR AS g, 0.0::DOUBLE AS s, 0.0::DOUBLE AS m WHERE false"
    for r in range(1, n + 1):
        gain = "s" if r == 1 else "CASE WHEN m = 0 THEN s ELSE s / m END"
        e[f"pick{r}"] = f"""SELECT query, {r} AS rank, g, s, m FROM (SELECT i.query, i.group_label AS g, round(i.score, 9) AS s, coalesce(max(z.sim), 0) AS m FROM groups i
          LEFT JOIN ({done}) d ON d.query = i.query LEFT JOIN gsim z ON z.query = i.query AND z.a = i.group_label AND z.b = d.g
          WHERE (i.query, i.group_label) NOT IN (SELECT (query, g) FROM ({done})) GROUP BY i.query, i.group_label, i.score)
          QUALIFY row_number() OVER (PARTITION BY query ORDER BY CASE WHEN {r} = 1 OR m = 0 THEN 0 ELSE 1 END, round({gain}, 9) DESC, g) = 1"""
        done = " UNION ALL ".join(f"SELECT query, rank, g, s, m FROM pick{i}" for i in range(1, r + 1))
    e["ranked"] = f"SELECT query, rank, g AS group_label, s AS score, round(m, 9) AS max_sim FROM ({done})"
    return e


def with_expressions(select: str, e: dict[str, str]) -> str:
    """The select, preceded by the expressions that it names, in the order of definition."""
    needed: set[str] = set()
    todo = [select]
    while todo:
        text = todo.pop()
        for name in set(re.findall(r"(?:FROM|JOIN|,)\s+(\w+)", text)) & e.keys() - needed:
            needed.add(name)
            todo.append(e[name])
    order = _sorted({n: e[n] for n in needed})
    # written down once, however many expressions name them; only those that name themselves recur
    own = lambda n: re.search(rf"(?:FROM|JOIN|,)\s+{n}\b", e[n])
    parts = ", ".join(f"{n} AS {'' if own(n) else 'MATERIALIZED '}({e[n]})" for n in order)
    return f"WITH RECURSIVE {parts} {select}" if parts else select


def _sorted(e: dict[str, str]) -> list[str]:
    order: list[str] = []

    def visit(n):
        if n in order:
            return
        for other in re.findall(r"(?:FROM|JOIN|,)\s+(\w+)", e[n]):
            if other in e and other != n:
                visit(other)
        order.append(n)

    for n in e:
        visit(n)
    return order


def oracle(select: str, extra: dict[str, str] | None = None, **params) -> str:
    return with_expressions(select, expressions(**params) | (extra or {}))
