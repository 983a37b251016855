"""Removal of bytes that repeat earlier in the corpus, judged on strings of a fixed length.

Three steps keep the work near the repeats, and lose none of them:

* Every ``length``-byte window has an anchor: its ``anchor``-byte substring of least hash,
  the leftmost among equals. Equal windows have equal anchors at equal offsets. Consecutive
  windows with one anchor form a fragment, so each window lies in exactly one fragment.
  Fragments are routed by anchor hash, without text. Of equal fragments only the first can
  hold a first occurrence, so each task already settles all but its first, and a passage
  that a third of the corpus shares costs one row per input batch.
* An anchor with a single fragment repeats nothing. Distinct fragments that share an anchor
  are cut from their texts and routed by anchor and half of its context, which splits
  anchors that stand in many contexts.
* There the windows of many fragments go through a column-wise multi-string construction.
  Each round puts one more symbol in front of every suffix, as a collection's
  Burrows-Wheeler transform is extended: the order file is dealt stably by the new symbol
  column, and the common-prefix file records which neighbours still agree. Rounds end at
  the window length. Suffixes that agree with neither neighbour leave between rounds. Files
  are read and rewritten sequentially, and lie on disk when they pass ``spill_rows``.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import ship, written


@dataclass(frozen=True)
class RepeatParams:
    length: int = 100
    anchor: int = 32
    bundle_bytes: int = 4_000_000
    spill_rows: int = 8_000_000


POSITION_BITS = np.uint64(28)
#: Until fragments are cut, a width has its anchor's place above these bits.
PLACE_SHIFT = 16
FRAGMENTS = "route long, anchor long, content long, doc_id long, start long, width int, settled boolean"


def anchored(s: flat.Slice, p: RepeatParams) -> dict[str, np.ndarray]:
    """Fragments of a slice: document, start byte, width, anchor place, and hashes."""
    n = len(s.buf)
    empty = {k: np.zeros(0, np.int64) for k in ("doc", "start", "width", "place")} | {k: np.zeros(0, np.uint64) for k in ("anchor", "content")}
    if n < p.length:
        return empty
    prefix = s.prefix()
    at = np.arange(n - p.anchor + 1)
    gram = s.hashes(prefix, at, at + p.anchor)
    low = np.uint64((1 << int(POSITION_BITS)) - 1)
    least = (gram & ~low) | at.astype(np.uint64)
    span, have = p.length - p.anchor + 1, 1
    while have < span:
        step = min(have, span - have)
        least = np.minimum(least[: len(least) - step], least[step:])
        have += step
    windows = np.flatnonzero(np.repeat(s.at[1:], np.diff(s.at))[: n - p.length + 1] - np.arange(n - p.length + 1) >= p.length)
    if not len(windows):
        return empty
    place = (least[windows] & low).astype(np.int64)
    doc = np.searchsorted(s.at, windows, "right") - 1
    first = np.ones(len(windows), bool)
    first[1:] = (place[1:] != place[:-1]) | (doc[1:] != doc[:-1])
    begin = np.flatnonzero(first)
    end = np.concatenate([begin[1:], [len(windows)]]) - 1
    start, stop = windows[begin], windows[end] + p.length
    return dict(doc=doc[begin], start=start, width=stop - start, place=place[begin], anchor=gram[place[begin]], content=s.hashes(prefix, start, stop))


def _routed(p: RepeatParams):
    def run(batches):
        for batch in batches:
            parts = []
            for part in flat.slices(batch, "text"):
                s = flat.Slice(part.column(1))
                f = anchored(s, p)
                ids = np.asarray(part.column(0).fill_null(0)).astype(np.int64)[f["doc"]]
                parts.append((f["anchor"], f["content"], ids, f["start"] - s.at[f["doc"]], f["width"] | ((f["place"] - f["start"]) << PLACE_SHIFT)))
            if not parts:
                continue
            anchor, content, ids, start, width = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.lexsort((start, ids, content, anchor))
            anchor, content, ids, start, width = (x[order] for x in (anchor, content, ids, start, width))
            twin = ~_runs(anchor, content, ids, start)  # rows that repeat id and text
            anchor, content, ids, start, width = (x[~twin] for x in (anchor, content, ids, start, width))
            settled = np.zeros(len(anchor), bool)
            settled[1:] = (anchor[1:] == anchor[:-1]) & (content[1:] == content[:-1])
            route = np.where(settled, flat.mix(ids.astype(np.uint64) + start.astype(np.uint64)), flat.mix(anchor))
            yield pa.RecordBatch.from_arrays(
                [pa.array(x.view(np.int64)) for x in (route, anchor, content, ids, start)] + [pa.array(width.astype(np.int32)), pa.array(settled)],
                [x.split()[0] for x in FRAGMENTS.split(", ")],
            )

    return run


def _runs(*keys: np.ndarray) -> np.ndarray:
    new = np.ones(len(keys[0]), bool)
    new[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    return new


def _judged(batches) -> Iterator[pa.RecordBatch]:
    """Sorted fragments in; repeated ones out as removed, first ones of shared anchors as open.

    An anchor may span batches: the last one read, and its first fragment while that is the
    only one, are carried over.
    """
    names = ["doc_id", "start", "width", "open"]
    held = None  # (anchor, content, doc, start, width, written out already)
    for batch in batches:
        anchor, content, ids, start = (np.asarray(batch.column(k)) for k in (1, 2, 3, 4))
        width, settled = np.asarray(batch.column(5)), np.asarray(batch.column(6).to_numpy(zero_copy_only=False), bool)
        out = [(ids[settled], start[settled], width[settled], np.zeros(settled.sum(), bool))]
        anchor, content, ids, start, width = (x[~settled] for x in (anchor, content, ids, start, width))
        if len(anchor):
            if held:
                anchor, content, ids, start, width = (np.concatenate([[h], x]) for h, x in zip(held[:5], (anchor, content, ids, start, width), strict=True))
            new_anchor, new_content = _runs(anchor), _runs(anchor, content)
            group = np.cumsum(new_anchor) - 1
            kinds = np.bincount(group, weights=new_content)
            shared = kinds[group] > 1
            is_open = new_content & shared
            # a row that repeats the first one is that very place, not a later copy
            gone = ~new_content
            lead = np.flatnonzero(new_content)[np.cumsum(new_content) - 1]
            gone &= (ids != ids[lead]) | (start != start[lead])
            last = np.flatnonzero(new_content & (group == group[-1]))
            skip = np.zeros(len(anchor), bool)
            if held:
                gone[0] = False
                if held[5]:
                    skip[0] = True
                    # the anchor was open before: its further fragments are open too
                    same = (group == 0) & new_content
                    is_open |= same
            alone = len(last) == 1 and not (held and held[5] and group[-1] == 0)
            if alone:
                is_open[last[0]] = False
            is_open &= ~skip
            out += [(ids[gone], start[gone], width[gone], np.zeros(gone.sum(), bool)), (ids[is_open], start[is_open], width[is_open], np.ones(is_open.sum(), bool))]
            k = last[-1]
            held = (anchor[k], content[k], ids[k], start[k], width[k], not alone)
        ids, start, width, is_open = (np.concatenate(x) for x in zip(*out, strict=True))
        width = np.where(is_open, width, width & ((1 << PLACE_SHIFT) - 1))
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(start), pa.array(width.astype(np.int32)), pa.array(is_open)], names)


def _cut(p: RepeatParams):
    half = (p.length - p.anchor) // 2

    def run(batches):
        for batch in batches:
            key, ids, begins, texts = [], [], [], []
            for doc, text, starts, widths in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                raw = (text or "").encode()
                for start, width in zip(starts, widths, strict=True):
                    place, width = width >> PLACE_SHIFT, width & ((1 << PLACE_SHIFT) - 1)
                    last = width - p.length
                    left = min(last, place - half)  # windows up to here hold the half before the anchor
                    for a, b, c in ((0, left, (place - half, place + p.anchor)), (max(left + 1, 0), last, (place, place + p.anchor + half))):
                        if a <= b:
                            key.append(int.from_bytes(hashlib.blake2b(raw[start + c[0] : start + c[1]], digest_size=8).digest(), "little", signed=True))
                            ids.append(doc)
                            begins.append(start + a)
                            texts.append(raw[start + a : start + b + p.length])
            yield pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), pa.array(ids, pa.int64()), pa.array(begins, pa.int64()), pa.array(texts, pa.binary())], ["key", "doc_id", "start", "text"])

    return run


class SequentialFile:
    """An array that is rewritten once a round; on disk where it is long."""

    def __init__(self, folder: str | None, name: str):
        self.path = folder and Path(folder) / name
        self.data = None

    def write(self, values: np.ndarray) -> None:
        if self.path is None:
            self.data = values
        else:
            self.path.with_suffix(".new").write_bytes(values.tobytes())
            self.path.with_suffix(".new").replace(self.path)
            self.dtype = values.dtype

    def read(self) -> np.ndarray:
        return self.data if self.path is None else np.fromfile(self.path, self.dtype)


def equal_windows(buf: np.ndarray, starts: np.ndarray, length: int, spill_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows ``buf[x:x+length]`` that equal another one: their starts in suffix order, and
    whether each agrees over the whole length with the one before it.

    Column-wise construction: after round t the order file holds the windows sorted by their
    last t symbols, and the agreement file the places where t symbols are shared with the
    neighbour before.
    """
    with tempfile.TemporaryDirectory() as folder:
        on_disk = folder if len(starts) > spill_rows else None
        order, agree = SequentialFile(on_disk, "order"), SequentialFile(on_disk, "agree")
        order.write(starts)
        agree.write(np.concatenate([[False], np.ones(max(len(starts) - 1, 0), bool)]))
        for t in range(1, length + 1):
            now, same = order.read(), agree.read()
            if len(now) < 2:
                return now[:0], same[:0]
            symbol = buf[now + length - t]
            dealt = np.argsort(symbol, kind="stable")
            name = np.cumsum(~same)[dealt]  # neighbours with one name share t-1 symbols
            symbol = symbol[dealt]
            same = np.zeros(len(now), bool)
            same[1:] = (symbol[1:] == symbol[:-1]) & (name[1:] == name[:-1])
            now = now[dealt]
            keep = same.copy()
            keep[:-1] |= same[1:]
            if not keep.all():
                now, same = now[keep], same[keep]
            order.write(now)
            agree.write(same)
        return order.read(), agree.read()


def _first_in_bundle(p: RepeatParams):
    names = ["doc_id", "start", "width"]

    def solve(ids, begins, texts):
        buf = np.frombuffer(b"".join(texts), np.uint8)
        lengths = np.array([len(x) for x in texts])
        at = np.concatenate([[0], np.cumsum(lengths)])
        per = lengths - p.length + 1
        text_of = np.repeat(np.arange(len(texts)), per)
        starts = np.arange(per.sum()) - np.repeat(np.concatenate([[0], np.cumsum(per)[:-1]]), per) + at[:-1][text_of]
        found, same = equal_windows(buf, starts, p.length, p.spill_rows)
        if not len(found):
            return
        which = np.searchsorted(at, found, "right") - 1
        doc, begin = np.asarray(ids)[which], np.asarray(begins)[which] + found - at[which]
        group = np.cumsum(~same)
        order = np.lexsort((begin, doc, group))
        doc, begin, fresh = doc[order], begin[order], _runs(group[order])
        lead = np.flatnonzero(fresh)[np.cumsum(fresh) - 1]
        later = ~fresh & ((doc != doc[lead]) | (begin != begin[lead]))
        doc, begin = doc[later], begin[later]
        if not len(doc):
            return
        order = np.lexsort((begin, doc))
        doc, begin = doc[order], begin[order]
        fresh = np.ones(len(doc), bool)
        fresh[1:] = (doc[1:] != doc[:-1]) | (begin[1:] > begin[:-1] + 1)
        first = np.flatnonzero(fresh)
        last = np.concatenate([first[1:], [len(doc)]]) - 1
        yield pa.RecordBatch.from_arrays([pa.array(doc[first]), pa.array(begin[first]), pa.array((begin[last] - begin[first] + p.length).astype(np.int32))], names)

    def run(batches):
        group, held_bytes, bundle = [], 0, []
        key = None
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if row[0] != key:
                    if len(group) > 1:
                        bundle += group
                        if held_bytes > p.bundle_bytes:
                            yield from solve(*map(list, zip(*bundle, strict=True)))
                            bundle, held_bytes = [], 0
                    elif group:
                        held_bytes -= len(group[0][2])
                    key, group = row[0], []
                group.append(row[1:])
                held_bytes += len(row[3])
        if len(group) > 1:
            bundle += group
        if bundle:
            yield from solve(*map(list, zip(*bundle, strict=True)))

    return run


def _assembled(batches):
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"]
    for batch in batches:
        rows = []
        for doc, text, spans in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            raw = (text or "").encode()
            merged: list[list[int]] = []
            for x in sorted((x["start"], x["start"] + x["width"]) for x in spans or ()):
                if merged and x[0] <= merged[-1][1]:
                    merged[-1][1] = max(merged[-1][1], x[1])
                else:
                    merged.append(list(x))
            kept, at = [], 0
            for a, b in merged:
                kept.append(raw[at:a])
                at = b
            kept.append(raw[at:])
            kept = b"".join(kept)
            rows.append((doc, len(raw), len(raw) - len(kept), len(merged), hashlib.sha256(kept).hexdigest(), merged))
        columns = list(zip(*rows, strict=True)) if rows else [[]] * 6
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.list_(pa.int64()))]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)


def repeated_spans(documents: DataFrame, p: RepeatParams = RepeatParams()) -> DataFrame:
    """Byte ranges ``(doc_id, start, width)`` whose strings start earlier too; they may overlap."""
    if p.length >= 1 << (PLACE_SHIFT - 1):
        raise ValueError("strings are too long")
    ship(documents.sparkSession)
    texts = documents.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    routed = texts.where(F.octet_length("text") >= p.length).mapInArrow(_routed(p), FRAGMENTS)
    judged = written(
        routed.repartition("route").sortWithinPartitions("route", "anchor", "content", "doc_id", "start").mapInArrow(_judged, "doc_id long, start long, width int, open boolean"),
        "judged",
    )
    lists = judged.where("open").groupBy("doc_id").agg(F.collect_list(F.struct("start", "width")).alias("f"))
    cut = texts.join(lists, "doc_id").select("doc_id", "text", "f.start", "f.width").mapInArrow(_cut(p), "key long, doc_id long, start long, text binary")
    again = cut.repartition("key").sortWithinPartitions("key").mapInArrow(_first_in_bundle(p), "doc_id long, start long, width int")
    return judged.where("not open").select("doc_id", "start", "width").unionByName(again)


def remove_repeated_bytes(documents: DataFrame, p: RepeatParams = RepeatParams()) -> DataFrame:
    """One row per input row: ``doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans``.

    A byte goes if a string of ``length`` bytes that covers it also starts earlier: in a
    smaller ``doc_id``, or earlier in its document. ``spans`` are the maximal removed byte
    ranges. A null text is empty. Rows without ``doc_id`` are returned untouched and are
    nobody's earlier copy. Rows that repeat id and text are one document, returned each time;
    rows that repeat an id with another text share their removals. An empty table gives an
    empty result.
    """
    spans = repeated_spans(documents, p).groupBy("doc_id").agg(F.collect_list(F.struct("start", "width")).alias("spans"))
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return (
        texts.join(spans, "doc_id", "left")
        .select("doc_id", "text", "spans")
        .mapInArrow(_assembled, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<array<long>>")
    )
