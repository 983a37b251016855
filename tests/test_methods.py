"""Worked examples with results computed by hand, and invariants."""

import itertools
import random

import pytest

from facetspark.operators import candidates, cluster, measures, propagate, select, similarity


def rows(df, *cols):
    return {tuple(r[c] for c in cols[:-1]): r[cols[-1]] for r in df.collect()}


@pytest.fixture(scope="module")
def inst(spark):
    p_r = candidates.refinement_scores(spark.createDataFrame([("q", "a", 3), ("q", "b", 1)], "query string, candidate string, sessions long"))
    freq = spark.createDataFrame([("q", 6), ("q a", 4), ("q c", 2)], "query string, freq long")
    sup = spark.createDataFrame([("q", "a", 4), ("q", "c", 2)], "query string, candidate string, freq long")
    return p_r, candidates.superstring_scores(sup, freq), candidates.superstring_scores(sup, freq, "upper")


def test_instance_scores(inst):
    p_r, p_ss, upper = inst
    assert rows(p_r, "candidate", "p_r") == {("a",): 0.75, ("b",): 0.25}
    assert rows(p_ss, "candidate", "p_ss") == pytest.approx({("a",): 4 / 12, ("c",): 2 / 12})
    assert rows(upper, "candidate", "p_ss") == pytest.approx({("a",): 4 / 6, ("c",): 2 / 6})
    assert rows(candidates.instance_scores(p_r, p_ss), "candidate", "p_inst") == pytest.approx({("a",): 0.642857, ("b",): 0.214286, ("c",): 0.142857}, abs=1e-6)


@pytest.mark.parametrize("mode, expected", [("mean", (0.613636, 0.029221)), ("indicator", (0.629870, 0.045455))])
def test_propagation(spark, inst, mode, expected):
    own = candidates.instance_scores(*inst[:2]).selectExpr("query", "candidate facet", "p_inst score")
    nodes = spark.createDataFrame([("q", "k", "p"), ("r", "k", "p")], "query string, class string, property string")
    got = rows(propagate.propagate(own, nodes, 0.1, mode), "query", "facet", "score")
    assert (got["q", "a"], got["r", "a"]) == pytest.approx(expected, abs=1e-6)


def test_two_rounds_are_a_fixed_point(spark, inst):
    own = candidates.instance_scores(*inst[:2]).selectExpr("query", "candidate facet", "p_inst score")
    nodes = spark.createDataFrame([("q", "k", "p"), ("r", "k", "p")], "query string, class string, property string")
    settled, rounds = propagate.iterate(own, nodes, 0.1)
    assert rounds == 2
    assert rows(settled, "query", "facet", "score") == pytest.approx(rows(propagate.propagate(own, nodes, 0.1, "mean"), "query", "facet", "score"))


def test_succession_counts_sessions_once(spark):
    log = spark.createDataFrame([(1, 1, "q"), (1, 2, "a"), (1, 3, "a"), (1, 4, "q"), (2, 1, "b"), (2, 2, "q")], "session_id long, step long, query string")
    seeds = spark.createDataFrame([("q",)], "query string")
    assert rows(candidates.succession(log, seeds), "candidate", "sessions") == {("a",): 1}


def test_facet_similarity(spark):
    hits = spark.createDataFrame([("q", "a", 1, 1), ("q", "a", 2, 2), ("q", "b", 3, 1)], "query string, facet string, doc_id long, rank int")
    # unit vectors whose dot products are .8 and .2
    v = [("q", 3, "t", 1.0), ("q", 1, "t", 0.8), ("q", 1, "u", 0.6), ("q", 2, "t", 0.2), ("q", 2, "v", 0.96**0.5)]
    vectors = spark.createDataFrame(v, "query string, doc_id long, term string, weight double")
    assert similarity.facet_sim(hits, vectors).first()["sim"] == pytest.approx(0.65)
    assert similarity.facet_sim(hits, vectors, "all_pairs").first()["sim"] == pytest.approx(0.5)


def test_components_are_strict_and_transitive(spark):
    sim = spark.createDataFrame([("q", "a", "b", 0.5), ("q", "b", "c", 0.36), ("q", "a", "c", 0.1), ("q", "c", "d", 0.35)], "query string, a string, b string, sim double")
    nodes = spark.createDataFrame([("q", x) for x in "abcd"], "query string, facet string")
    assert rows(cluster.components(nodes, cluster.threshold_edges(sim)), "facet", "component") == {("a",): "a", ("b",): "a", ("c",): "a", ("d",): "d"}
    centers = rows(cluster.star_cover(nodes, cluster.threshold_edges(sim)), "facet", "center")
    assert centers == {("a",): "b", ("b",): "b", ("c",): "b", ("d",): "d"}


def test_pair_f(spark):
    got = spark.createDataFrame([("q", x, "1") for x in "abc"], "query string, facet string, component string")
    gold = spark.createDataFrame([("q", "a", "x"), ("q", "b", "x"), ("q", "c", "y")], "query string, facet string, gold string")
    assert tuple(measures.pair_f(got, gold).first()) == pytest.approx((1 / 3, 1, 0.5))


def test_overlap(spark):
    facets = spark.createDataFrame([("q", d, 1) for d in (1, 2, 3, 4)], "query string, doc_id long, rank int")
    seed = spark.createDataFrame([("q", d, 1) for d in (2, 4, 9)], "query string, doc_id long, rank int")
    assert measures.overlap(facets, seed, 1, 3).first()["overlap"] == 0.5


def test_greedy_order_and_brute_force(spark):
    assert select.greedy_rows([("1", 0.5), ("2", 0.3), ("3", 0.2)], {("1", "2"): 0.9, ("1", "3"): 0.3, ("2", "3"): 0.1}, 3) == ["1", "3", "2"]
    rng = random.Random(5)
    names = [f"f{i:02d}" for i in range(12)]
    score = {n: round(rng.random(), 3) for n in names}
    sim = {(a, b): round(rng.random(), 3) if rng.random() < 0.7 else 0.0 for a, b in itertools.combinations(names, 2)}
    groups = spark.createDataFrame([("q", n, "single", s, [n]) for n, s in score.items()], "query string, group_label string, kind string, score double, members array<string>")
    sims = spark.createDataFrame([("q", a, b, s) for (a, b), s in sim.items() if s], "query string, a string, b string, sim double")
    got = [r["group_label"] for r in select.greedy(groups, sims, 12).orderBy("rank").collect()]
    assert got == select.greedy_rows(list(score.items()), sim, 12) and sorted(got) == names


def test_preference_compares_for_and_against(spark):
    votes = [("d", "q", "F")] * 3 + [("d", "q", "E")] * 8 + [("d", "q", "A")] * 4 + [("e", "r", "F")] * 6 + [("e", "r", "E")] * 3 + [("e", "r", "A")] * 6
    got = {r["domain"]: (r["qf"], r["qe"], r["qa"]) for r in measures.preference(spark.createDataFrame(votes, "domain string, query string, verdict string")).collect()}
    assert got == {"d": (0, 0, 1), "e": (0, 1, 0), None: (0, 1, 1)}


def test_t_tail():
    assert measures.t_tail(2.0, 10) == pytest.approx(0.07338803, abs=1e-7)
    assert measures.t_tail(0.0, 5) == 1.0
