"""Items indexed in parts give the rows of one index."""

import random

from facetspark.llm import decontaminate


def test_parts_equal_one_index(spark):
    rng = random.Random(5)
    word = lambda: f"w{chr(97 + min(int(rng.expovariate(0.2)), 25))}{chr(97 + rng.randrange(3))}"
    items = [(i, " ".join(word() for _ in range(rng.randint(4, 40))) + ". " + word()) for i in range(60)]
    docs = []
    for i, t in items:
        w = t.split(" ")
        docs.append((i, " ".join(word() for _ in range(20)) + " " + " ".join(x if rng.random() < 0.75 else word() for x in w) + " " + " ".join(word() for _ in range(30))))
    docs, items = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    one = sorted(decontaminate.retrieved_items(docs, items).collect())
    parts = sorted(decontaminate.retrieved_items(docs, items, decontaminate.LeakParams(index_bytes=400)).collect())
    assert one and one == parts
