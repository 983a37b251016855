"""Fragments carry their anchor's place, so that cutting them looks for no anchor again."""

import random

import pyarrow as pa

from facetspark.llm import flat, repeated_bytes
from facetspark.llm.repeated_bytes import PLACE_SHIFT, RepeatParams


def test_places_of_cut_fragments(monkeypatch):
    rng = random.Random(6)
    texts = ["".join(rng.choice("abc ") for _ in range(700)), "x" * 400, "é" * 90 + "ab" * 80]
    p = RepeatParams()
    batch = pa.RecordBatch.from_arrays([pa.array([1, 2, 3]), pa.array(texts)], ["doc_id", "text"])
    (routed,) = repeated_bytes._routed(p)([batch])
    rows = list(zip(*(routed.column(k).to_pylist() for k in (3, 4, 5)), strict=True))
    for doc, start, packed in rows:
        raw = texts[doc - 1].encode()[start : start + (packed & ((1 << PLACE_SHIFT) - 1))]
        alone = repeated_bytes.anchored(flat.Slice(pa.array([raw], pa.large_binary())), p)
        assert packed >> PLACE_SHIFT == alone["place"][0]
    monkeypatch.setattr(repeated_bytes, "anchored", None)
    starts, widths = ([[r[k] for r in rows if r[0] == d] for d in (1, 2, 3)] for k in (1, 2))
    asked = pa.RecordBatch.from_arrays([pa.array([1, 2, 3]), pa.array(texts), pa.array(starts), pa.array(widths)], ["doc_id", "text", "start", "width"])
    (cut,) = repeated_bytes._cut(p)([asked])
    held = {(d, s + k) for d, s, t in zip(*(cut.column(k).to_pylist() for k in (1, 2, 3)), strict=True) for k in range(len(t) - p.length + 1)}
    assert held == {(i + 1, x) for i, t in enumerate(texts) for x in range(len(t.encode()) - p.length + 1)}
