"""The operators against brute force on small rows: nulls, empty and long texts, copies, ties."""

import hashlib
import math
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from facetspark.llm import decontaminate, license_scan, near_duplicates, pieces, quality_model, quality_rules, repeated_bytes, repeated_passages, url_filter, warc

SPACES = "[^\x20\x09-\x0d]+"


def corpus():
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(2, 6)))
    texts = [" ".join(word() for _ in range(rng.choice((0, 1, 3, 4, 60, 150)))) for _ in range(60)]
    base = [word() for _ in range(120)]
    texts += [" ".join(base)] * 4
    for k in range(12):
        w = list(base)
        for i in rng.sample(range(len(w)), 1 + k % 4):
            w[i] = word()
        texts.append(" ".join(w))
    passage = " ".join(word() for _ in range(70))
    texts += [f"{t}\n{passage}\n{word()}" for t in texts[:20]]
    texts += [None, "", "   ", "Ab ab\tAB", "x" * 5000, "a b " * 400, "same line\nsame line\nother"]
    return list(enumerate(texts))


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "x", "clash") for i, t in corpus()], "doc_id long, text string, source string, component_id string")


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_near_duplicates(docs):
    sets = {}
    for i, t in corpus():
        w = re.findall(SPACES, re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[k : k + 4]) for k in range(len(w) - 3)} if len(w) > 3 else {tuple(w)} if w else set()
    top = {i: i for i in sets}
    find = lambda x: x if top[x] == x else find(top[x])
    for a in sets:
        for b in sets:
            n = len(sets[a] & sets[b])
            if a < b and n and 100 * n >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                top[y] = x
    got = by_id(near_duplicates.near_duplicate_groups(docs))
    assert {i: (r["n_shingles"], r["component_id"], r["kept"]) for i, r in got.items()} == {i: (len(sets[i]), find(i), find(i) == i) for i in sets}


def test_posterior_bound_grows_and_never_asks_all():
    steps = [near_duplicates.least_matches(n, 0.8, 1e-6) for n in (24, 48, 72, 96)]
    assert steps == sorted(steps) and all(s < 0.8 * n for s, n in zip(steps, (24, 48, 72, 96), strict=True))


@pytest.mark.parametrize("rows_per_batch", [10_000, 7])
def test_repeated_bytes(spark, docs, rows_per_batch):
    seen, want = set(), {}
    for i, t in corpus():
        raw = (t or "").encode()
        mark = bytearray(len(raw))
        for k in range(len(raw) - 99):
            if raw[k : k + 100] in seen:
                mark[k : k + 100] = b"\1" * 100
            seen.add(raw[k : k + 100])
        kept = bytes(x for x, m in zip(raw, mark, strict=True) if not m)
        want[i] = (len(raw), sum(mark), len(re.findall(b"\1+", bytes(mark))), hashlib.sha256(kept).hexdigest())
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows_per_batch)
    try:
        got = by_id(repeated_bytes.remove_repeated_bytes(docs))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert {i: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for i, r in got.items()} == want


def test_quality_counts(docs):
    want = {}
    for i, t in corpus():
        t = t or ""
        w = re.findall(SPACES, t)
        seen = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        again = {j for k in range(len(w) - 2) if seen[tuple(w[k : k + 3])] > 1 for j in (k, k + 1, k + 2)}
        lines = [x for x in t.split("\n") if re.search(SPACES, x)]
        want[i] = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(again), len(w) < 50 or 100 * len(again) > 50 * len(w))
    got = by_id(quality_rules.quality_votes(docs))
    assert {i: tuple(r[c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")) for i, r in got.items()} == want
    assert all(not r["kept"] for r in got.values() if r["base_failed"])


def test_label_model_follows_rules_that_agree():
    """Three rules see one defect, a fourth errs at random: its vote alone does not condemn a text."""
    rng = random.Random(8)
    patterns, truth = Counter(), []
    for _ in range(4000):
        bad = rng.random() < 0.15
        votes = tuple(-1 if rng.random() < (0.8 if bad else 0.02) else 1 for _ in range(3)) + (-1 if rng.random() < 0.1 else 1,)
        patterns[votes] += 1
        truth.append((bad, votes))
    good, rate = quality_rules.estimate(sorted(patterns.items()), 4)
    assert abs(good - 0.85) < 0.03 and np.abs(rate[0, :3, 0] - 0.8).max() < 0.06 and np.abs(rate[1, :3, 0] - 0.02).max() < 0.02
    posterior = lambda v: 1 / (1 + (1 - good) / good * math.prod(rate[0, j, x + 1] / rate[1, j, x + 1] for j, x in enumerate(v)))
    assert posterior((1, 1, 1, -1)) > 0.9 and posterior((-1, 1, 1, 1)) > 0.5 and posterior((-1, -1, 1, 1)) < 0.5
    assert sum((posterior(v) < 0.5) != bad for bad, v in truth) < 0.05 * len(truth)


def test_ordinal_model_orders_grades(spark):
    texts = ["good plain words here " * 5] * 40 + ["good plain idiot words " * 5] * 40 + ["### $$$ %%% !!! " * 9] * 40
    grades = [2] * 40 + [0] * 40 + [1] * 40
    documents = spark.createDataFrame(list(enumerate([*texts, None, ""])), "doc_id long, text string")
    labels = spark.createDataFrame([*enumerate(grades), (7000, 1), (3, None)], "doc_id long, grade int")
    model = quality_model.train(documents, labels, grade=F.col("grade"))
    tail = model.at_least(model.scores(pa.array([texts[0], texts[40], texts[80], None])))
    assert tail[0, 1] > 0.9 and tail[1, 1] < 0.1 and tail[2, 1] < 0.5 and model.thresholds[0] <= model.thresholds[1]
    assert quality_model.score_quality(documents.where("false"), model).count() == 0
    unlabelled = quality_model.score_quality(documents, quality_model.train(documents, labels.where("false"), grade=F.col("grade")))
    assert unlabelled.where("accepted").count() == 122


def test_ordinal_likelihood():
    rng = np.random.default_rng(5)
    p = quality_model.OrdinalParams(ridge=0.01)
    row, col, dense, y = np.repeat(np.arange(30), 2), rng.integers(0, 4, 60), rng.normal(size=(30, 2)), rng.integers(0, 3, 30)
    loss = quality_model.likelihood(row, col, 4, dense, y, p)
    x = rng.normal(size=8)
    value, grad = loss(x)
    for i in range(8):  # the gradient against differences
        step = np.eye(8)[i] * 1e-6
        assert abs((loss(x + step)[0] - loss(x - step)[0]) / 2e-6 - grad[i]) < 1e-5
    total = 0.0  # the likelihood from its definition
    for i in range(30):
        score = sum(x[c] for r, c in zip(row, col, strict=True) if r == i) + dense[i] @ x[4:6]
        edges = [-math.inf, x[6], x[6] + math.exp(x[7]), math.inf]
        below = [1 / (1 + math.exp(score - e)) if abs(e) < math.inf else float(e > 0) for e in edges]
        total -= math.log(below[y[i] + 1] - below[y[i]])
    assert abs(total / 30 + 0.005 * (x[:6] @ x[:6]) - value) < 1e-9
    best = quality_model.minimise(loss, x, 400)
    assert np.abs(loss(best)[1]).max() < 1e-3


def test_repeated_passages(docs):
    words = {i: re.findall(SPACES, re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) for i, t in corpus()}
    first, want = {}, set()
    for i, w in words.items():
        runs = {tuple(w[k : k + 50]) for k in range(len(w) - 49)}
        if any(r in first for r in runs):
            want.add(i)
        for r in runs:
            first.setdefault(r, i)
    got = repeated_passages.repeated_passages(docs).collect()
    assert want <= {r["doc_id"] for r in got}
    assert all(r["ref_id"] < r["doc_id"] and r["last_word"] - r["first_word"] >= 49 for r in got)
    kept = repeated_passages.remove_repeated_passages(docs)
    assert kept.columns == docs.columns and not {i for i, t in corpus() if i < 60} - set(by_id(kept))


def test_benchmark_leaks(spark, docs):
    items = spark.createDataFrame([(1, "the first question asks for much. forty two"), (2, "another plain item. answer"), (3, ""), (4, None)], "item_id long, text string")
    more = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(900, "bla THE first question asks for much. Forty two bla"), (901, "the first question asks for little else"), (902, None)], "doc_id long, text string"))
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(more, items).collect()} == {(900, 1)}
    assert decontaminate.leaks(more, items.where("false")).count() == 0
    tiny = decontaminate.LeakParams(index_bytes=30)
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(more, items, tiny).collect()} == {(900, 1)}


def test_pieces_are_lossless_and_reproducible(docs):
    a = by_id(pieces.encode(docs))
    b = by_id(pieces.encode(docs.repartition(7)))
    assert all(r["lossless"] for r in a.values()) and {i: r["piece_ids"] for i, r in a.items()} == {i: r["piece_ids"] for i, r in b.items()}
    text = dict(corpus())
    assert {i: r["text"] for i, r in by_id(pieces.decode(pieces.encode(docs))).items()} == text


def test_warc_round_trip(spark):
    pages = [(5, "http://a/", "x"), (3, None, "x"), (9, "http://b\r\nc", None), (11, "u", ""), (2, "u", "é" * 900)]
    got = {r["page_id"]: r for r in warc.archive_and_read(spark.createDataFrame(pages, "page_id long, url string, html string"), warc.WarcParams(roll_bytes=600, shard_bytes=1000)).collect()}
    assert {i: (r["payload_bytes"], r["record_type"], r["refers_to"]) for i, r in got.items()} == {5: (1, "revisit", 3), 3: (1, "response", None), 9: (0, "response", None), 11: (0, "revisit", 9), 2: (1800, "response", None)}
    assert got[2]["payload_digest"] == warc.payload_digest(("é" * 900).encode())
    assert warc.archive_and_read(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_url_rules(spark):
    urls = ["http://A.Example.com/en/71?x", "http://example.com/en/8", "https://b.net/de/8", "https://example.net/de/8", "http://x.org", "no scheme", None, "http://x.org/es/#a"]
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")).collect()}
    assert got[0] == ("a.example.com", "/en/71", "example.com/en/7", "allow") and got[1][2:] == ("com/en/", "block")
    assert got[2][2:] == ("net/de/", "allow") and got[3][2:] == ("example.net/de/8", "block") and got[7][2:] == ("org/es/", "block")
    assert got[4][:3] == ("x.org", "", None) and got[5][:3] == got[6][:3] == ("", "", None)


def test_license_scan(spark):
    texts = ["a b\nLicensed under the Apache License, Version 2.0.\nc", "released under the mit licence", None, "", "License " * 200, license_scan.TEMPLATES["MIT text"]]
    got = [r["licenses"] for r in license_scan.scan_licenses(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).orderBy("doc_id").collect()]
    assert got[0] == ["Apache-2.0 notice"] and got[2:5] == [[], [], []] and got[5] == ["MIT text"]


def test_empty_tables(docs):
    none = docs.where("false")
    for run in (near_duplicates.near_duplicate_groups, repeated_bytes.remove_repeated_bytes, quality_rules.quality_votes, repeated_passages.repeated_passages, pieces.encode, license_scan.scan_licenses):
        assert run(none).count() == 0
