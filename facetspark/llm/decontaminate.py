"""Benchmark decontamination: every training passage queries a BM25 index of test items.

The index holds the test items. BM25 impacts are divided by the item's own total, so a score
is the share of an item's weight that a passage holds. Items lie in blocks; each term keeps
its largest impact per block. As in block-max WAND, the common terms whose impacts together
cannot reach the threshold start no candidate: a passage looks at a block only when one of
the block's other terms occurs in it, and is scored only when the block bound reaches the
threshold. All items at or above it are retrieved, and verified by the overlap of their
question and answer parts. The scan of the corpus shuffles nothing.

The index goes to every task, so its size is checked: items beyond ``index_bytes`` of text
are indexed in several parts, one scan each.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.quality_model import LETTERS
from facetspark.llm.store import ship


@dataclass(frozen=True)
class LeakParams:
    threshold: float = 0.6
    overlap: float = 0.7
    gram: int = 5
    k1: float = 1.2
    b: float = 0.75
    block: int = 8
    index_bytes: int = 16_000_000
    table_bits: int = 20
    table_cells: int = 32_000_000


def parts_of_item(text: str) -> tuple[str, str]:
    """Question and answer of an item: all but its last sentence or line, and that one."""
    cuts = [m.end() for m in re.finditer(r"[.?!:]\s+|\n+", text.strip())]
    if not cuts:
        return text, text
    return text.strip()[: cuts[-1]], text.strip()[cuts[-1] :]


def _words(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, flat.Slice]:
    s = flat.Slice(pc.utf8_lower(pa.array(texts, pa.string())))
    start, end, bounds = s.spans(LETTERS)
    return s.hashes(s.prefix(), start, end), bounds, start, end, s


def _grams(words: np.ndarray, n: int) -> np.ndarray:
    n = min(n, len(words))
    return np.unique(flat.shingles(words, np.array([0, len(words)]), n)[0][: len(words) - n + 1]) if n else np.zeros(0, np.uint64)


def _ranges(bounds: np.ndarray, k: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All places of the ranges ``k``, each with the place in ``k`` it belongs to; bounds as one array or as starts and ends."""
    start, end = bounds if bounds.ndim == 2 else (bounds[:-1], bounds[1:])
    n = end[k] - start[k]
    which = np.repeat(np.arange(len(k)), n)
    return which, np.arange(len(which)) - np.repeat(np.cumsum(n) - n - start[k], n)


@dataclass(frozen=True)
class ItemStatistics:
    """Of all test items, however many parts they are indexed in."""

    n: int
    words: int
    longest: int
    terms: np.ndarray
    df: np.ndarray

    @classmethod
    def of(cls, texts: list[str]) -> ItemStatistics:
        h, bounds, *_ = _words([t for t in texts if t])
        lengths = np.diff(bounds)
        terms, term = np.unique(h, return_inverse=True)
        pairs = np.unique((term.astype(np.int64) << 32) | np.repeat(np.arange(len(lengths)), lengths))
        return cls(int((lengths > 0).sum()), int(lengths.sum()), int(lengths.max(initial=1)), terms, np.bincount(pairs >> 32, minlength=len(terms)))

    def __add__(self, other: ItemStatistics) -> ItemStatistics:
        terms, at = np.unique(np.concatenate([self.terms, other.terms]), return_inverse=True)
        df = np.zeros(len(terms), np.int64)
        np.add.at(df, at, np.concatenate([self.df, other.df]))
        return ItemStatistics(self.n + other.n, self.words + other.words, max(self.longest, other.longest), terms, df)


class ItemIndex:
    """BM25 postings of test items in blocks of items, with block maxima per term."""

    def __init__(self, items: list[tuple[int, str]], p: LeakParams, whole: ItemStatistics | None = None):
        self.p = p
        whole = whole or ItemStatistics.of([t for _, t in items])
        items = [(i, t) for i, t in items if t and _words([t])[1][-1]]
        self.ids = np.array([i for i, _ in items], np.int64)
        h, bounds, *_ = _words([t for _, t in items])
        n = len(items)
        lengths = np.diff(bounds)
        mean = max(whole.words / whole.n, 1) if whole.n else 1
        item = np.repeat(np.arange(n), lengths)
        terms, term = np.unique(h, return_inverse=True)
        key, tf = np.unique((term.astype(np.int64) << 32) | item, return_counts=True)
        term, item = key >> 32, key & 0xFFFFFFFF
        df = whole.df[np.searchsorted(whole.terms, terms)]
        idf = np.log(1 + (whole.n - df + 0.5) / (df + 0.5))
        impact = idf[term] * tf * (p.k1 + 1) / (tf + p.k1 * (1 - p.b + p.b * lengths[item] / mean))
        impact /= np.bincount(item, impact, minlength=n)[item]
        # terms that start no candidate: an item's commonest terms, while their impacts stay below the threshold
        order = np.lexsort((-df[term], item))
        running = np.cumsum(impact[order])
        first = np.searchsorted(item[order], item[order])
        starts = np.ones(len(term), bool)
        starts[order] = running - running[first] + impact[order][first] >= p.threshold - 1e-9
        self.terms = terms
        by_item = np.argsort(item, kind="stable")
        self.item_terms, self.item_impacts = term[by_item], impact[by_item]
        self.items_from = np.searchsorted(item[by_item], np.arange(n + 1))
        block = item // p.block
        self.blocks = -(-n // p.block)
        lead = np.unique((term[starts] << 32) | block[starts])
        self.lead_block = lead & 0xFFFFFFFF
        self.lead_from = np.searchsorted(lead >> 32, np.arange(len(terms) + 1))
        bkey, binv = np.unique((term << 32) | block, return_inverse=True)
        most = np.zeros(len(bkey))
        np.maximum.at(most, binv, impact)
        # bounds: largest impact of each lead term in a block, and the most that an item's other terms give
        self.lead_most = most[np.searchsorted(bkey, lead)]
        self.rest_most = np.zeros(self.blocks)
        rest = np.bincount(item, np.where(starts, 0, impact), minlength=n)
        np.maximum.at(self.rest_most, np.arange(n) // p.block, rest)
        # block maxima of all terms, block by block
        by_block = np.argsort(bkey & 0xFFFFFFFF, kind="stable")
        self.block_terms, self.block_most = bkey[by_block] >> 32, most[by_block]
        self.blocks_from = np.searchsorted((bkey & 0xFFFFFFFF)[by_block], np.arange(self.blocks + 1))
        self.slot = np.zeros(1 << p.table_bits, bool)
        self.slot[(terms >> np.uint64(64 - p.table_bits)).astype(np.int64)] = True
        self.window = whole.longest
        self.parts = []
        for _, text in items:
            words = _words([text])[0]
            question, answer = (_words([x])[0] for x in parts_of_item(text))
            self.parts.append([_grams(x if len(x) else words, p.gram) for x in (question, answer)])

    def term_of(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of the words that the index knows, and their term numbers."""
        maybe = np.flatnonzero(self.slot[(h >> np.uint64(64 - self.p.table_bits)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.terms, h[maybe]), max(len(self.terms) - 1, 0))
        hit = self.terms[at] == h[maybe] if len(self.terms) else np.zeros(len(maybe), bool)
        return maybe[hit], at[hit]

    def candidates(self, term: np.ndarray, passage: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Passages and blocks whose lead terms, with the most of the others, may reach the threshold; terms are distinct by passage."""
        which, posting = _ranges(self.lead_from, term)
        key, inverse = np.unique(passage[which] * self.blocks + self.lead_block[posting], return_inverse=True)
        passage, block = np.divmod(key, self.blocks)
        may = np.bincount(inverse, self.lead_most[posting], minlength=len(key)) + self.rest_most[block] >= self.p.threshold - 1e-9
        return passage[may], block[may]

    def scored(self, term: np.ndarray, passage: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Passages, items and scores of all at or above the threshold, in the order of passages and items.

        Candidates are taken some at a time, as many as a table of their passages' terms has room for.
        """
        p = self.p
        where, block = self.candidates(term, passage)
        few = max(1, min(512, p.table_cells // max(len(self.terms), 1)))
        local = np.zeros(len(self.terms), np.int32)
        for k in range(0, len(where), few):
            own, row = np.unique(where[k : k + few], return_inverse=True)
            b = block[k : k + few]
            from_, to = np.searchsorted(passage, own), np.searchsorted(passage, own, "right")
            which, at = _ranges(np.stack([from_, to]), np.arange(len(own)))
            seen, column = np.unique(term[at], return_inverse=True)
            local[seen] = np.arange(1, len(seen) + 1)
            holds = np.zeros((len(own), len(seen) + 1), bool)
            holds[which, column + 1] = True
            # block maxima of the terms that the passage holds, then the items of the blocks left
            which, at = _ranges(self.blocks_from, b)
            most = np.where(holds[row[which], local[self.block_terms[at]]], self.block_most[at], 0)
            left = np.flatnonzero(np.bincount(which, most, minlength=len(b)) >= p.threshold - 1e-9)
            if len(left):
                item = (b[left, None] * p.block + np.arange(p.block)).ravel()
                row = np.repeat(row[left], p.block)
                row, item = row[item < len(self.ids)], item[item < len(self.ids)]
                which, at = _ranges(self.items_from, item)
                score = np.bincount(which, np.where(holds[row[which], local[self.item_terms[at]]], self.item_impacts[at], 0), minlength=len(item))
                hit = score >= p.threshold
                yield own[row[hit]], item[hit], score[hit]
            local[seen] = 0

    def search(self, h: np.ndarray, bounds: np.ndarray):
        """Yields ``(document, first word, last word, item, score, question, answer)``."""
        p = self.p
        if not len(self.ids):
            return
        place, term = self.term_of(h)
        doc = np.searchsorted(bounds, place, "right") - 1
        step = (place - bounds[doc]) // self.window
        # passages are numbered through; one begins at every step and is two steps long
        base = np.concatenate([[0], np.cumsum(-(-np.diff(bounds) // self.window))])
        passage = base[doc] + step
        key = np.unique(np.concatenate([passage * len(self.terms) + term, (passage[step > 0] - 1) * len(self.terms) + term[step > 0]]))
        passage, term = np.divmod(key, len(self.terms))
        best: dict[tuple[int, int], tuple] = {}
        for places, items, scores in self.scored(term, passage):
            at = -1
            for q, item, score in zip(places.tolist(), items.tolist(), scores.tolist(), strict=True):
                if q != at:
                    at, grams_of = q, {}
                    d = int(np.searchsorted(base, q, "right")) - 1
                    first = bounds[d] + (q - base[d]) * self.window
                    last = min(first + 2 * self.window, bounds[d + 1])
                    words = h[first:last]
                overlaps = []
                for grams in self.parts[item]:
                    # a part shorter than a gram is one gram of its own length
                    short = len(grams) == 1
                    if short not in grams_of:
                        sizes = range(1 if short else p.gram, p.gram + 1)
                        grams_of[short] = np.concatenate([_grams(words, k) for k in sizes])
                    overlaps.append(float(np.isin(grams, grams_of[short]).mean()))
                found = (score, *overlaps)
                old = best.get((d, item))
                if old is None or (min(overlaps), score) > (min(old[3:]), old[2]):
                    best[d, item] = (int(first - bounds[d]), int(last - bounds[d]), *found)
        for (d, item), row in sorted(best.items()):
            yield d, row[0], row[1], int(self.ids[item]), *row[2:]


LEAKS = "doc_id long, item_id long, first_word long, last_word long, score double, question_overlap double, answer_overlap double, leaked boolean"


def retrieved_items(documents: DataFrame, benchmark: DataFrame, p: LeakParams = LeakParams()) -> DataFrame:
    """One row per document and test item at or above the score threshold in some passage.

    ``leaked`` tells whether question and answer overlap reach ``p.overlap``. Null and empty
    texts and items match nothing, nor do rows without ``doc_id``; repeated rows are each
    searched. With an empty table on either side the result is empty.
    """
    spark = documents.sparkSession
    ship(spark)
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null").distinct()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = -(-size // p.index_bytes) or 1
    texts = documents.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    names = [x.split()[0] for x in LEAKS.split(", ")]
    out = None
    part_of = lambda k: sorted((r[0], r[1]) for r in items.where(F.pmod(F.xxhash64("item_id"), F.lit(parts)) == k).collect())  # noqa: E731  about index_bytes of text
    # scores and passages are those of one index: its statistics are summed over the parts first
    whole = None
    for k in range(parts if parts > 1 else 0):
        one = ItemStatistics.of([t for _, t in part_of(k)])
        whole = one if whole is None else whole + one
    for k in range(parts):
        held = spark.sparkContext.broadcast(ItemIndex(part_of(k), p, whole))

        def run(batches, held=held):
            index = held.value
            for batch in batches:
                for part in flat.slices(batch, "text"):
                    s = flat.Slice(pc.utf8_lower(part.column(1)))
                    start, end, bounds = s.spans(LETTERS)
                    ids = np.asarray(part.column(0))
                    rows = [(int(ids[d]), item, a, b, round(sc, 9), q, w, q >= p.overlap and w >= p.overlap) for d, a, b, item, sc, q, w in index.search(s.hashes(s.prefix(), start, end), bounds)]
                    kinds = [pa.int64()] * 4 + [pa.float64()] * 3 + [pa.bool_()]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 8, kinds, strict=True)], names)

        found = texts.mapInArrow(run, LEAKS)
        out = found if out is None else out.unionByName(found)
    return out


def leaks(documents: DataFrame, benchmark: DataFrame, p: LeakParams = LeakParams()) -> DataFrame:
    """The verified rows of :func:`retrieved_items`."""
    return retrieved_items(documents, benchmark, p).where("leaked").drop("leaked")


def without_leaks(documents: DataFrame, benchmark: DataFrame, p: LeakParams = LeakParams()) -> DataFrame:
    """The documents, all columns, that hold no verified test item; rows without id stay."""
    bad = leaks(documents, benchmark, p).select(F.col("doc_id").alias("leaked__")).distinct()
    return documents.join(bad, documents["doc_id"] == bad["leaked__"], "left_anti")
