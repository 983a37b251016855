"""Open windows meet one confirmed partner, not every document with a word run in common."""

import random

import numpy as np

from facetspark.llm import repeated_passages
from facetspark.llm.repeated_passages import PassageParams, matched_stretches


def texts(n, rng):
    return [f"w{rng.randrange(10**9)}" for _ in range(n)]


def test_links_grow_with_the_documents(spark, monkeypatch):
    """A line just too short for a passage stands in all documents; two of them share a passage around it."""
    rng = random.Random(8)
    line = texts(45, rng)
    rows = [texts(60, rng) + line + texts(60, rng) for _ in range(80)]
    rows[70][50:112] = rows[30][50:112]
    links = []
    solve = repeated_passages._passages_of

    def counted(docs, found, p):
        links.append(found.count())
        return solve(docs, found, p)

    monkeypatch.setattr(repeated_passages, "_passages_of", counted)
    table = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    got = repeated_passages.repeated_passages(table).collect()
    assert {(r["doc_id"], r["ref_id"]) for r in got} == {(70, 30)}
    assert sum(links) < 12 * len(rows)


def test_sequences_of_a_stretch_that_differs_too_much_as_one():
    rng = np.random.default_rng(1)
    here = rng.integers(1, 2**62, 71)
    there = here.copy()
    for x in (20, 46):  # one changed word each
        there[x : x + 5] = rng.integers(1, 2**62, 5)
    p = PassageParams()
    assert {x for first, last, _ in matched_stretches(here, there, p) for x in range(first, last + 1)} == set(range(71))
    assert not list(matched_stretches(here[:40], there, p))
