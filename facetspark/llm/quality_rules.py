"""Quality rules as weak supervision.

Counts of a text feed rules that vote good (1), bad (-1) or abstain (0). How often a rule
is right is unknown; expectation maximisation estimates it, and the share of good texts,
from how the rules agree over all texts. The verdict is the posterior of "good".

The votes of all texts reduce to counts per vote pattern (3**rules at most, whatever the
input), so estimation costs one aggregation; the posterior is a plain column expression.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import ship, written

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
NEWLINE = np.zeros(256, bool)
NEWLINE[10] = True
CONTINUES = (np.arange(256) & 0xC0) == 0x80
UPPER = np.zeros(256, bool)
UPPER[65:91] = True
LETTER = UPPER.copy()
LETTER[97:123] = True
MARK = np.zeros(256, bool)  # ASCII marks
MARK[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True
SPOKEN = LETTER.copy()  # bytes of letters, and of all characters beyond ASCII
SPOKEN[128:] = True
ENDING = np.zeros(256, bool)
ENDING[list(b".!?\"')")] = True

COUNTS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, n_ended_lines long, n_letters long, n_upper long, n_distinct long, n_marks long, n_mute_words long"
NAMES = [x.split()[0] for x in COUNTS.split(", ")]


@dataclass(frozen=True)
class Rule:
    """Votes on ``top / bottom``: good inside ``good`` and bad outside ``fair``, both [low, high]."""

    name: str
    top: str
    bottom: str
    good: tuple[float, float]
    fair: tuple[float, float]

    def vote(self) -> Column:
        x = F.col(self.top) / F.when(F.col(self.bottom) > 0, F.col(self.bottom))
        bad = (x < self.fair[0]) | (x > self.fair[1])
        return F.coalesce(F.when(bad, -1).when((x >= self.good[0]) & (x <= self.good[1]), 1), F.lit(0)).cast("int")


RULES = (
    Rule("symbols", "n_symbols", "n_words", (0, 0.02), (0, 0.1)),
    Rule("marks", "n_marks", "word_chars", (0, 0.06), (0, 0.1)),
    Rule("mute_words", "n_mute_words", "n_words", (0, 0.1), (0, 0.3)),
    Rule("word_length", "word_chars", "n_words", (3, 9), (2, 14)),
    Rule("repeated_lines", "n_dup_lines", "n_lines", (0, 0.05), (0, 0.3)),
    Rule("repeated_words", "n_repeat_words", "n_words", (0, 0.1), (0, 0.3)),
    Rule("capitals", "n_upper", "n_letters", (0.002, 0.15), (0, 0.4)),
    Rule("ended_lines", "n_ended_lines", "n_lines", (0.6, 1), (0.1, 1)),
    Rule("vocabulary", "n_distinct", "n_words", (0.3, 1), (0.1, 1)),
)


def _distinct(doc: np.ndarray, h: np.ndarray, docs: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values per document, and for each element whether its value occurs twice."""
    key = (doc.astype(np.uint64) << np.uint64(52)) | (h >> np.uint64(12))
    order = np.argsort(key)
    sorted_key = key[order]
    fresh = np.ones(len(key), bool)
    fresh[1:] = sorted_key[1:] != sorted_key[:-1]
    alone = fresh.copy()
    alone[:-1] &= fresh[1:]
    twice = np.zeros(len(key), bool)
    twice[order] = ~alone
    return np.bincount((sorted_key[fresh] >> np.uint64(52)).astype(np.int64), minlength=docs), twice


def count_text(column: pa.Array) -> dict[str, np.ndarray]:
    """The counts of ``NAMES`` for every text of a slice."""
    s = flat.Slice(column)
    per_doc = lambda mask: np.diff(np.concatenate([[0], np.cumsum(mask)])[s.at])
    start, end, bounds = s.words()
    n_words = np.diff(bounds)
    prefix = s.prefix()
    h = s.hashes(prefix, start, end)
    doc = np.repeat(np.arange(s.docs), n_words)
    n_distinct, _ = _distinct(doc, h, s.docs)
    windows, fits = flat.shingles(h, bounds, 3)
    first = np.flatnonzero(fits)
    _, twice = _distinct(doc[first], windows[first], s.docs)
    covered = np.zeros(len(h) + 1, np.int64)
    np.add.at(covered, first[twice], 1)
    np.add.at(covered, first[twice] + 3, -1)
    repeated = np.concatenate([[0], np.cumsum(np.cumsum(covered)[:-1] > 0)])
    l_start, l_end, _ = s.spans(NEWLINE)
    worded = np.searchsorted(start, l_end) > np.searchsorted(start, l_start)
    l_start, l_end = l_start[worded], l_end[worded]
    l_doc = np.searchsorted(s.at, l_start, "right") - 1
    lines = np.bincount(l_doc, minlength=s.docs)
    distinct_lines, _ = _distinct(l_doc, s.hashes(prefix, l_start, l_end), s.docs)
    last_word = end[np.searchsorted(start, l_end) - 1] - 1
    ended = np.bincount(l_doc[ENDING[s.buf[last_word]]], minlength=s.docs)
    in_word = ~flat.IS_SPACE[s.buf]
    spoken = np.concatenate([[0], np.cumsum(SPOKEN[s.buf])])
    return dict(
        n_words=n_words,
        word_chars=per_doc(in_word & ~CONTINUES[s.buf]),
        n_symbols=per_doc(SYMBOLS[s.buf]),
        n_dup_lines=lines - distinct_lines,
        n_repeat_words=np.diff(repeated[bounds]),
        n_lines=lines,
        n_ended_lines=ended,
        n_letters=per_doc(LETTER[s.buf]),
        n_upper=per_doc(UPPER[s.buf]),
        n_distinct=n_distinct,
        n_marks=per_doc(MARK[s.buf]),
        n_mute_words=np.bincount(doc[spoken[end] == spoken[start]], minlength=s.docs),
    )


def _counted(batches):
    for batch in batches:
        for part in flat.slices(batch, "text"):
            counts = count_text(part.column(1))
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(counts[n].astype(np.int64)) for n in NAMES)], ["doc_id", *NAMES])


def estimate(patterns: list[tuple[tuple[int, ...], int]], rules: int, rounds: int = 500, tolerance: float = 1e-10) -> tuple[float, np.ndarray]:
    """Share of good texts, and per class, rule and vote how often that vote is cast.

    Returns ``(good, rate)`` with ``rate[c, j, v + 1]`` for class c (0 bad, 1 good), by expectation
    maximisation without bounds; half a vote of each kind keeps rates off zero. The start says
    only that rules accuse bad texts more often than good ones. The classes follow the defect
    that several rules see together; a defect that one rule alone sees does not make a class.
    """
    rate = np.empty((2, rules, 3))
    rate[0], rate[1] = (0.35, 0.15, 0.5), (0.02, 0.08, 0.9)
    good = 0.8
    if not patterns:
        return good, rate
    votes = np.array([p for p, _ in patterns], int).reshape(-1, rules) + 1
    weight = np.array([n for _, n in patterns], float)
    cast = np.stack([votes == v for v in range(3)], axis=2)
    for _ in range(rounds):
        like = np.exp(np.log(rate)[:, np.arange(rules), votes].sum(2)) * np.array([1 - good, good])[:, None]
        post = like[1] / like.sum(0)
        sizes = np.stack([(1 - post) * weight, post * weight])
        fresh = np.einsum("cp,pjv->cjv", sizes, cast) + 0.5
        fresh /= fresh.sum(2, keepdims=True)
        new_good = (sizes[1].sum() + 1) / (weight.sum() + 2)
        moved = max(np.abs(fresh - rate).max(), abs(new_good - good))
        good, rate = float(new_good), fresh
        if moved < tolerance:
            break
    return good, rate


def quality_votes(documents: DataFrame, rules: tuple[Rule, ...] = RULES, threshold: float = 0.5) -> DataFrame:
    """One row per input row: counts, votes, ``base_failed``, ``posterior`` and ``kept``.

    ``base_failed`` is the hard base rule (under 50 words, or over half of the words inside
    repeated three-word windows); the others are kept if the posterior reaches ``threshold``.
    A null text counts as empty and fails the base rule. Rows without ``doc_id`` and rows
    that repeat one are judged like any other. An empty table gives an empty result.
    """
    ship(documents.sparkSession)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    counted = texts.mapInArrow(_counted, f"doc_id long, {COUNTS}")
    voted = written(counted.select("*", *(r.vote().alias(f"vote_{r.name}") for r in rules)), "votes")
    columns = [f"vote_{r.name}" for r in rules]
    patterns = voted.groupBy(*columns).count().collect()  # 3**rules rows at most
    good, rate = estimate([(tuple(r[c] for c in columns), r["count"]) for r in sorted(patterns, key=tuple)], len(rules))
    weights = np.log(rate[1] / rate[0])
    odds = F.lit(log(good / (1 - good)))
    for c, (bad, none, yes) in zip(columns, weights.tolist(), strict=True):
        odds = odds + F.when(F.col(c) < 0, bad).when(F.col(c) > 0, yes).otherwise(none)
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return (
        voted.withColumn("base_failed", failed)
        .withColumn("posterior", F.round(1 / (1 + F.exp(-odds)), 9))
        .withColumn("kept", ~F.col("base_failed") & (F.col("posterior") >= threshold))
    )
