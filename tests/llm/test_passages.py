"""Passages that stand at several places, and references that hold a part of one."""

import random

import pytest

from facetspark.llm import repeated_passages

LENGTH = 60


def texts(n, rng):
    return [f"w{rng.randrange(10**9)}" for _ in range(n)]


def covered(rows, doc, places):
    """Whether the rows of ``doc`` cover ``LENGTH`` words from each place."""
    held = {w for r in rows if r["doc_id"] == doc for w in range(r["first_word"], r["last_word"] + 1)}
    return [all(p + k in held for k in range(LENGTH)) for p in places]


@pytest.mark.parametrize("turn", range(3))
def test_passage_at_two_places(spark, turn):
    rng = random.Random(turn)
    passage = texts(LENGTH, rng)
    first = texts(80, rng) + passage + texts(80, rng)
    # the later document repeats the passage, and single shingles of it stand earlier in both
    strays = [w for k in range(0, LENGTH - 4, 7) for w in passage[k : k + 5] + texts(60, rng)]
    later = strays + passage + texts(90, rng) + passage + texts(30, rng)
    rows = [(1, " ".join(strays + first)), (2, " ".join(later)), (3, " ".join(texts(200, rng)))]
    got = repeated_passages.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert covered(got, 2, [len(strays), len(strays) + LENGTH + 90]) == [True, True]
    assert {r["doc_id"] for r in got} == {2}
    assert len({(r["first_word"], r["ref_id"]) for r in got}) == len(got)


@pytest.mark.parametrize("quoters", [1, 9])
def test_reference_with_a_part_of_the_passage(spark, quoters):
    rng = random.Random(quoters)
    rows, want, many = [], {}, 40 if quoters == 1 else 12
    for _ in range(many):
        passage = texts(LENGTH, rng)
        for _ in range(quoters):
            rows.append(texts(60, rng) + passage[:29] + texts(60, rng))
        for last in (False, True):
            start = texts(70, rng)
            rows.append(start + passage + texts(50, rng))
            if last:
                want[len(rows) - 1] = len(start)
    table = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    got = repeated_passages.repeated_passages(table).collect()
    assert {r["doc_id"] for r in got} == set(want)
    assert all(covered(got, i, [at]) == [True] for i, at in want.items())
    assert sorted(got) == sorted(repeated_passages.repeated_passages(table.repartition(5)).collect())


def test_partner_that_is_neither_first_nor_previous(spark):
    """Near copies, each among documents that share much of the passage but too little of any 50 words."""
    rng = random.Random(5)
    rows, want = [], {}

    def add(passage, *changed):
        words = list(passage)
        for i in changed:
            words[i] = texts(1, rng)[0]
        start = texts(60, rng)
        rows.append(start + words + texts(60, rng))
        return len(start)

    for _ in range(40):
        passage = texts(55, rng)
        for turn in range(2):
            for _ in range(7):
                add(passage, rng.randrange(6, 20), rng.randrange(35, 49))
            at = add(passage, *([27] if turn else []))
        want[len(rows) - 1] = (len(rows) - 9, at)
    table = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    got = repeated_passages.repeated_passages(table).collect()
    assert {r["doc_id"]: r["ref_id"] for r in got if r["doc_id"] in want} == {d: ref for d, (ref, _) in want.items()}
