"""Rows that stand twice in a table are one document, not copies of each other."""

import random

from facetspark.llm import near_duplicates, repeated_bytes, repeated_passages


def test_repeated_rows_keep_one_copy(spark):
    rng = random.Random(2)
    text = " ".join(f"w{rng.randrange(10**6)}" for _ in range(60))
    mixed = " ".join(f"v{rng.randrange(10**6)}" for _ in range(40)) + " " + text
    rows = [(1, text), (1, text), (2, "short"), (3, mixed), (3, mixed), (4, text)]
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted((r["doc_id"], r["n_bytes"] - r["n_removed"]) for r in repeated_bytes.remove_repeated_bytes(table).collect())
    own = len(mixed.encode()) - len(text.encode())
    assert got == [(1, len(text)), (1, len(text)), (2, 5), (3, own), (3, own), (4, 0)]
    assert {r["doc_id"] for r in repeated_passages.repeated_passages(table).collect()} == {3, 4}


def test_texts_of_one_id_hold_their_copies_together(spark):
    rng = random.Random(4)
    word = lambda: f"w{rng.randrange(10**6)}"
    a, b = [word() for _ in range(90)], [word() for _ in range(90)]
    rows = [(1, " ".join(a)), (1, " ".join(b)), (2, " ".join([*a[:-1], "x"])), (3, " ".join([*b[:-1], "y"])), (4, "alone of all")]
    got = {(r["doc_id"], r["component_id"]) for r in near_duplicates.near_duplicate_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {(1, 1), (2, 1), (3, 1), (4, 4)}
