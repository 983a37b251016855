"""Whole comparisons only for places that can share a passage; texts that are asked often are read once."""

import numpy as np
import pyarrow as pa

from facetspark.llm import flat
from facetspark.llm.repeated_passages import PassageParams, Places, _fetched, _merged

P = PassageParams()
WIDE = 2 * (P.window - 1 + P.slack) + 1


def places(near):
    n = len(near)
    ids = np.arange(n)
    columns = [np.zeros(n, np.int64), np.zeros(n, np.int64), ids, np.full(n, WIDE), np.full(n, WIDE // 2), np.zeros(n, np.int64), np.ones(n, bool), ids]
    return Places(P, columns, np.full(n, WIDE // 2), near)


def test_places_with_a_short_run_in_common_are_not_compared(monkeypatch):
    rng = np.random.default_rng(3)
    near = rng.integers(1, 2**32, (120, WIDE), dtype=np.uint32)
    middle = WIDE // 2
    near[:, middle - 24 : middle + 12] = near[0, middle - 24 : middle + 12]
    near[90, middle - 30 : middle + 20] = near[40, middle - 30 : middle + 20]
    compared = []
    real = Places._share
    monkeypatch.setattr(Places, "_share", lambda self, a, b: compared.append(len(a)) or real(self, a, b))
    found = [(int(a), int(b)) for x, y in places(near).links(every=False) for a, b in zip(x, y, strict=True)]
    assert found == [(90, 40)]
    assert sum(compared) < len(near)


def test_filter_loses_no_pair():
    rng = np.random.default_rng(4)
    near = np.tile(rng.integers(1, 2**32, WIDE, dtype=np.uint32), (60, 1))
    for row in near:
        changed = rng.integers(0, WIDE, rng.integers(1, 14))
        row[changed] = rng.choice(np.append(near[0, :9], rng.integers(1, 2**32, 3, dtype=np.uint32)), len(changed))
    group = places(near)
    found = {(int(a), int(b)) for x, y in group.links(every=True) for a, b in zip(x, y, strict=True)}
    a, b = np.tril_indices(len(near), -1)
    good = group._share(a, b)
    assert found == set(zip(a[good].tolist(), b[good].tolist(), strict=True))
    assert 100 < len(found) < len(a)


def test_texts_that_are_asked_often_are_read_once(monkeypatch):
    texts = [" ".join(f"{c}{i}" for i in range(90)) for c in "ab"]
    kind = pa.list_(pa.struct([("pair", pa.int64()), ("side", pa.int32()), ("first", pa.int64()), ("stop", pa.int64()), ("ref_id", pa.int64())]))
    ask = lambda pair: {"pair": pair, "side": 0, "first": pair, "stop": pair + 50, "ref_id": 0}
    rows = [(1, texts[0], [ask(0), ask(1)]), (1, texts[0], [ask(2)]), (1, texts[1], [ask(3)]), (2, texts[1], [ask(4)]), (2, texts[1], [ask(5), ask(6)])]
    batch = pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), kind), strict=True)], ["doc_id", "text", "asks"])
    assert _merged(batch).num_rows == 3
    alone = [r for i in range(len(rows)) for b in _fetched(P)([batch.slice(i, 1)]) for r in b.to_pylist()]
    read = []
    real = flat.Slice.__init__
    monkeypatch.setattr(flat.Slice, "__init__", lambda self, column, lower=False: read.append(len(column)) or real(self, column, lower))
    assert [r for b in _fetched(P)([batch]) for r in b.to_pylist()] == alone
    assert sum(read) == 3
