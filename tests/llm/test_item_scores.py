"""The item search against scoring every passage with every item."""

import math
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from facetspark.llm import flat
from facetspark.llm.decontaminate import ItemIndex, LeakParams
from facetspark.llm.quality_model import LETTERS


def words(text):
    return re.findall(r"[a-z0-9]+", text.lower())


def every_score(items, texts, p):
    """(document, item) to the best score of any passage, from the definition of BM25."""
    held = [(i, Counter(words(t))) for i, t in items]
    df = Counter(w for _, c in held for w in c)
    mean = sum(sum(c.values()) for _, c in held) / len(held)
    window = max(sum(c.values()) for _, c in held)
    best = {}
    for i, c in held:
        norm = p.k1 * (1 - p.b + p.b * sum(c.values()) / mean)
        impact = {w: math.log(1 + (len(held) - df[w] + 0.5) / (df[w] + 0.5)) * f * (p.k1 + 1) / (f + norm) for w, f in c.items()}
        total = sum(impact.values())
        for d, text in enumerate(texts):
            t = words(text)
            for at in range(0, len(t), window):
                score = sum(impact[w] for w in set(t[at : at + 2 * window]) & set(impact)) / total
                best[d, i] = max(best.get((d, i), 0), score)
    return best


@pytest.mark.parametrize("threshold", [0.3, 0.6])
@pytest.mark.parametrize("cells", [1, 32_000_000])
def test_search_finds_all_above_threshold(threshold, cells):
    draw = random.Random(5)
    vocabulary = [f"w{k}" for k in range(120)]
    weights = [1 / (k + 1) for k in range(120)]
    some = lambda n: " ".join(draw.choices(vocabulary, weights, k=n))
    items = [(10 * k, some(draw.randint(3, 14)) + "? " + some(2)) for k in range(45)]
    texts = [some(draw.randint(0, 90)) for _ in range(60)] + [some(30) + " " + t + " " + some(9) for _, t in items[::4]] + [""]
    p = LeakParams(threshold=threshold, table_cells=cells)
    s = flat.Slice(pa.array(texts))
    start, end, bounds = s.spans(LETTERS)
    found = {(d, i) for d, _, _, i, *_ in ItemIndex(items, p).search(s.hashes(s.prefix(), start, end), bounds)}
    scores = every_score(items, texts, p)
    assert {k for k, v in scores.items() if v > threshold + 1e-9} <= found <= {k for k, v in scores.items() if v > threshold - 1e-9}
    assert len(found) >= 11 and np.isfinite(list(scores.values())).all()
