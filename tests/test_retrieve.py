"""Retrieval by floors against scoring every document."""

import math
import random
from collections import Counter

import pytest

from facetspark.operators import retrieve


@pytest.mark.parametrize("seed", range(2))
def test_best_documents(spark, seed):
    rng = random.Random(seed)
    common, rare = [f"c{i}" for i in range(4)], [f"r{i}" for i in range(30)]
    texts = {i: " ".join([*rng.sample(common, 2), *rng.choices(rare, k=rng.choice((1, 3, 6))), *rng.choices(common, k=rng.choice((0, 0, 3)))]) for i in range(250)}
    asked = [" ".join([*rng.sample(common, rng.choice((0, 1, 2))), *rng.sample(rare, rng.choice((0, 1, 2, 3)))]) for _ in range(40)] + ["c0", "unknown", ""]
    docs = {i: Counter(t.split()) for i, t in texts.items()}
    df = Counter(w for d in docs.values() for w in d)
    mean = sum(sum(d.values()) for d in docs.values()) / len(docs)

    def score(words, d):
        size = sum(d.values())
        return round(sum(math.log(1 + (len(docs) - df[w] + 0.5) / (df[w] + 0.5)) * d[w] * 2.2 / (d[w] + 1.2 * (0.25 + 0.75 * size / mean)) for w in words if w in d), 9)

    want = {}
    for q in asked:
        found = sorted((-s, i) for i, d in docs.items() if (s := score(set(q.split()), d)) > 0)[:8]
        if found:
            want[q] = [(i, -s) for s, i in found]
    index = retrieve.build_index(spark.createDataFrame([(i, t) for i, t in texts.items()], "doc_id long, head string"), ("head",))
    got = {}
    for r in retrieve.top_hits(spark.createDataFrame([(q,) for q in asked], "query_text string"), index).orderBy("query_text", "rank").collect():
        got.setdefault(r["query_text"], []).append((r["doc_id"], r["relevance"]))
    assert got.keys() == want.keys()
    assert all([i for i, _ in got[q]] == [i for i, _ in want[q]] and all(abs(a - b) < 1e-8 for (_, a), (_, b) in zip(got[q], want[q], strict=True)) for q in want)


def test_alike_documents_are_scored_once(spark, monkeypatch):
    """Texts tell four kinds of documents apart; a document of two rows is one."""
    kinds = ["red anvil", "red gizmo", "blue anvil", "red red anvil"]
    rows = [(i, f"{kinds[i % 4]} own{i}") for i in range(400)] + [(7, "anvil")]
    pairs, scored = [], retrieve._scored
    monkeypatch.setattr(retrieve, "_scored", lambda found, *rest: pairs.append(found.count()) or scored(found, *rest))
    index = retrieve.build_index(spark.createDataFrame(rows, "doc_id long, head string"), ("head",))
    got = retrieve.top_hits(spark.createDataFrame([("red anvil",), ("gizmo",)], "query_text string"), index).orderBy("query_text", "rank").collect()
    assert [r["doc_id"] for r in got if r["query_text"] == "gizmo"] == [1, 5, 9, 13, 17, 21, 25, 29]
    assert [r["doc_id"] for r in got if r["query_text"] == "red anvil"] == [7, 3, 11, 15, 19, 23, 27, 31]
    assert {r["doc_id"]: r["words"] for r in index.forward.where("doc_id = 7").collect()} == {7: {"red": 2, "anvil": 2, "own7": 1}}
    assert sum(pairs) <= 2 * 2 * 5
