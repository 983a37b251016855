"""Near-duplicate passages by compact windows.

For each of a few hash functions, a document's word shingles are the leaves of a Cartesian
tree ordered by hash. The node with its minimum at c spans [l, r]: all sequences inside
[l, r] that contain c have that minimum, so nodes of at least the wanted length stand for
all long sequences and their min-hash. Trees are built level by level for all documents of a
slice at once.

Windows of one function and value form a group. Every window of a member is linked with
every distinct place of the group's first (smallest) document. Windows that no verified
passage holds are open: they are searched among all earlier places of their group, by the rarest
shingles around them, for one that has a whole passage around it; places with equal surroundings
count once, and large groups are dealt over several tasks. One partner settles a window, so the links
grow with the windows; those whose partner is not confirmed meet all the others. Per pair of documents
the links of all functions are joined as intervals along the pair's alignment, and stretches that enough
functions agree on become candidates, which are verified on their shingles.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import discard, release, ship, written


@dataclass(frozen=True)
class PassageParams:
    """``slack`` words of shift inside one passage are aligned together.

    At similarity 0.8 each function agrees with probability 0.8: fewer than two of five agree with
    probability 6.7e-3. Where a third document is in the group, those pairs are found among the open windows.
    Exact copies agree in all functions.
    """

    words: int = 5
    length: int = 50
    hashes: int = 5
    enough: int = 2
    similarity: float = 0.8
    slack: int = 10

    @property
    def window(self) -> int:
        return self.length - self.words + 1

    @property
    def contained(self) -> int:
        """Shingles of a window that must occur on the other side, from the similarity."""
        return ceil(2 * self.similarity / (1 + self.similarity) * self.window)


LOW_BITS = 28
LOW = np.uint64((1 << LOW_BITS) - 1)
SCATTER = np.uint64(0x9E3779B1)
GATHER = np.uint64(pow(0x9E3779B1, -1, 1 << LOW_BITS))


def tree_windows(h: np.ndarray, a: np.ndarray, b: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Nodes ``(l, c, r)`` with r - l >= least of the Cartesian trees over h[a:b] (r excluded).

    Equal hashes are ordered by scattered positions, so trees over repeated text stay flat.
    """
    n = len(h)
    packed = np.append((h & ~LOW) | ((np.arange(n, dtype=np.uint64) * SCATTER) & LOW), np.uint64(0))
    found = []
    keep = b - a >= least
    a, b = a[keep], b[keep]
    while len(a):
        low = np.minimum.reduceat(packed[: b[-1] + 1], np.column_stack([a, b]).ravel())[::2]
        c = (((low & LOW) * GATHER) & LOW).astype(np.int64)
        found.append((a, c, b))
        a, b = np.column_stack([a, c + 1]).ravel(), np.column_stack([c, b]).ravel()
        keep = b - a >= least
        a, b = a[keep], b[keep]
    if not found:
        return (np.zeros(0, np.int64),) * 3
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def word_shingles(s: flat.Slice, words: int):
    start, end, bounds = s.words()
    h, _ = flat.shingles(s.hashes(s.prefix(), start, end), bounds, words)
    return start, end, bounds, h


WINDOWS = "route long, doc_id long, around long, lr long, ck long"
LINKS = "doc_id long, lr long, c long, ref_id long, ref_lr long, ref_c long, hash int"
GROUPED = f"{LINKS}, route long, lead boolean, more boolean, head boolean"
MOST_LINKS = 500_000


def _windows(p: PassageParams):
    """All windows of all documents: ``ck`` holds place and function, ``around`` what a sequence can reach.

    Two places of a document with equal ``around`` are in the same sequences of the wanted length.
    """
    names = [x.split()[0] for x in WINDOWS.split(", ")]

    def run(batches):
        for batch in batches:
            for part in flat.slices(batch, "text"):
                s = flat.Slice(part.column(1), lower=True)
                _, _, bounds, h = word_shingles(s, p.words)
                a, b = bounds[:-1], bounds[1:] - p.words + 1
                fits = b - a >= p.window
                a, b, doc = a[fits], b[fits], np.flatnonzero(fits)
                ids = np.asarray(part.column(0)).astype(np.int64)
                prefix = np.zeros(len(h) + 1, np.uint64)
                np.cumsum(flat.powers(len(h))[0] * h, out=prefix[1:])
                _, inverse = flat.powers(len(h) + 1)
                for k in range(p.hashes):
                    value = flat.mix(h ^ flat.MULTIPLIERS[300 + k])
                    left, c, r = tree_windows(value, a, b, p.window)
                    at = np.searchsorted(a, left, "right") - 1
                    zero = a[at]
                    x, y = np.maximum(c - p.window + 1, zero), np.minimum(c + p.window, b[at])
                    around = flat.mix((prefix[y] - prefix[x]) * inverse[x] + ((c - x) * 4096 + (y - c)).astype(np.uint64))
                    route = flat.mix(value[c] + flat.MULTIPLIERS[320 + k])
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in (route.view(np.int64), ids[doc[at]], around.view(np.int64), ((left - zero) << 32) | (r - zero), ((c - zero) << 6) | k)], names)

    return run


def _linked(batches):
    """Sorted by all columns: every window of a later document meets the first one's distinct places.

    ``lead`` marks one link of each window, ``more`` those with a third or later document,
    ``head`` those of the group's first linked window, which meet each of the places once.
    """
    names = [x.split()[0] for x in GROUPED.split(", ")]
    held = second = None
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = [np.asarray(c) for c in batch.columns]
        if held is not None:
            rows = [np.concatenate(x) for x in zip(held, rows, strict=True)]
        route, ids, around, lr, ck = rows
        fresh = np.ones(len(route), bool)
        fresh[1:] = route[1:] != route[:-1]
        start = np.flatnonzero(fresh)
        group = np.cumsum(fresh) - 1
        first = ids == ids[start][group]
        again = np.zeros(len(route), bool)
        again[1:] = first[1:] & ~fresh[1:] & first[:-1] & (around[1:] == around[:-1])
        refs = np.flatnonzero(first & ~again)
        n = np.bincount(group[refs], minlength=len(start))
        begin = np.cumsum(n) - n
        link = np.flatnonzero(~first)
        ends = np.cumsum(n[group[link]])
        follows, at = np.unique(group[link], return_index=True)
        seconds = ids[start]
        seconds[follows] = ids[link[at]]
        heads = np.zeros(len(route), bool)
        heads[link[at]] = True
        if second is not None and held is not None:
            seconds[0] = second
            heads[group == 0] = False
        x = 0
        while x < len(link):
            y = max(int(np.searchsorted(ends, (ends[x - 1] if x else 0) + MOST_LINKS, "right")), x + 1)
            some = link[x:y]
            times = n[group[some]]
            at = refs[np.repeat(begin[group[some]], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)]
            lead = np.zeros(len(at), bool)
            lead[np.cumsum(times) - times] = True
            some = np.repeat(some, times)
            more, head = ids[some] != seconds[group[some]], heads[some]
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in (ids[some], lr[some], ck[some] >> 6, ids[at], lr[at], ck[at] >> 6, (ck[some] & 63).astype(np.int32), route[some], lead, more, head)], names)
            x = y
        last = refs[group[refs] == group[-1]]
        held = [v[last] for v in rows]
        second = seconds[-1] if seconds[-1] != ids[start[-1]] else None


CONTEXTS = "route long, turns int, doc_id long, lr long, c long, hash int, open boolean, around long, before int, shingles binary"


def _contexts(p: PassageParams):
    """Each asked place with the shingles that a passage around it can hold, and ``slack`` more, as 32-bit numbers.

    ``before`` of them lie before the place; ``around`` is that of :func:`_windows`.
    """
    names = [x.split()[0] for x in CONTEXTS.split(", ")]
    wide = p.window - 1 + p.slack

    def run(batches):
        for batch in batches:
            for part in flat.slices(batch, "text"):
                s = flat.Slice(part.column(1), lower=True)
                _, _, bounds, h = word_shingles(s, p.words)
                asks = part.column(2)
                doc = np.repeat(np.arange(part.num_rows), np.asarray(asks.value_lengths()))
                route, turns, lr, c, k, open_ = (np.asarray(x.to_numpy(zero_copy_only=False)) for x in asks.flatten().flatten())
                low, high = bounds[:-1][doc], bounds[1:][doc] - p.words + 1
                fits = np.flatnonzero(low + c < high)  # rows that repeat a document's number may be shorter
                low, high, at = low[fits], high[fits], (low + c)[fits]
                prefix = np.zeros(len(h) + 1, np.uint64)
                np.cumsum(flat.powers(len(h))[0] * h, out=prefix[1:])
                _, inverse = flat.powers(len(h) + 1)
                x, y = np.maximum(at - p.window + 1, low), np.minimum(at + p.window, high)
                around = flat.mix((prefix[y] - prefix[x]) * inverse[x] + ((at - x) * 4096 + (y - at)).astype(np.uint64))
                short = np.maximum(h >> np.uint64(32), np.uint64(1)).astype(np.uint32)  # zero stands for no shingle
                x, y = np.maximum(at - wide, low), np.minimum(at + wide + 1, high)
                offsets = np.concatenate([[0], np.cumsum(y - x)])
                held = short[np.repeat(x - offsets[:-1], y - x) + np.arange(offsets[-1])]
                shingles = pa.Array.from_buffers(pa.binary(), len(at), [None, pa.py_buffer((4 * offsets).astype(np.int32)), pa.py_buffer(held)])
                columns = (route[fits], turns[fits].astype(np.int32), np.asarray(part.column(0))[doc[fits]], lr[fits], c[fits], k[fits].astype(np.int32), open_[fits].astype(bool), around.view(np.int64), (at - x).astype(np.int32))
                yield pa.RecordBatch.from_arrays([*(pa.array(v) for v in columns), shingles], names)

    return run


MOST_PLACES = 8_000
INDEXED = 65_536
MOST_TESTS = 50_000
PLACE = np.uint64((1 << 24) - 1)
FOLDED = 1024


class Places:
    """Places of whole groups, sorted by group and document, with the shingles around them."""

    def __init__(self, p: PassageParams, columns: list[np.ndarray], before: np.ndarray, near: np.ndarray):
        self.p, self.near, self.before = p, near, before
        route, turn, self.ids, self.lr, self.c, self.k, self.open, self.around = columns
        fresh = _starts(route) | _starts(turn)
        self.group = np.cumsum(fresh) - 1
        self.after = (near > 0).sum(1) - before - 1
        fresh |= _starts(self.ids)
        self.own = np.flatnonzero(fresh)[np.cumsum(fresh) - 1]  # the first place of the same group and document
        self.alike = self._alike()

    def _alike(self) -> np.ndarray:
        """The first place of the same group with equal surroundings."""
        order = np.lexsort((self.around, self.group))
        fresh = _starts(self.group[order]) | _starts(self.around[order])
        out = np.empty(len(order), np.int64)
        out[order] = order[fresh][np.cumsum(fresh) - 1]
        return out

    def keys(self, rows: np.ndarray, shingles: np.ndarray) -> np.ndarray:
        """Shingles of places as numbers that tell groups apart; the low bits are free for a place."""
        return flat.mix(shingles.astype(np.uint64) * flat.MULTIPLIERS[340] + self.group[rows].astype(np.uint64)[:, None]) & ~PLACE

    def links(self, every: bool):
        """Pairs of an open place and an earlier one around which both have a passage.

        The first such place that is found is enough, unless ``every`` one is wanted.
        """
        asks = np.flatnonzero(self.open)
        copies = asks[self.alike[asks] < self.own[asks]]
        yield copies, self.alike[copies]
        if not every:
            asks = asks[self.alike[asks] >= self.own[asks]]
        refs = np.flatnonzero(self.alike == np.arange(len(self.alike)))
        for x in range(0, len(refs), INDEXED):
            for found, partners in self._met(refs[x : x + INDEXED], asks, every):
                if not every:
                    asks = np.setdiff1d(asks, found)
                yield found, partners

    def _met(self, refs: np.ndarray, asks: np.ndarray, every: bool):
        """A passage around a place holds half a length before or behind it, and misses few shingles there.

        So of its rarest shingles in either half, one more than may be missed, the partner has one.
        """
        p, half = self.p, self.p.window // 2
        missing = p.window - p.contained
        asks = asks[(self.own[asks] > refs[0]) & (np.maximum(self.before, self.after)[asks] >= half)]
        held = self.near[refs]
        index = np.sort((self.keys(refs, held) | np.arange(len(refs), dtype=np.uint64)[:, None])[held > 0])
        index = index[_starts(index)]  # a place that repeats a shingle is listed once
        limit = np.searchsorted(refs, self.own[asks]).astype(np.uint64)[:, None]
        starts, stops = [], []
        for step, room in ((-1, self.before[asks]), (1, self.after[asks])):
            inside = room >= half
            at = np.where(inside, self.before[asks], 0)[:, None] + np.where(inside, step, 0)[:, None] * np.arange(1, half + 1)
            key = self.keys(asks, np.take_along_axis(self.near[asks], at, 1))
            start = np.searchsorted(index, key)
            count = np.searchsorted(index, key | PLACE, "right") - start
            rare = np.argsort(count, 1, kind="stable")[:, : missing + 1]
            start, key = np.take_along_axis(start, rare, 1), np.take_along_axis(key, rare, 1)
            stops.append(np.where(inside[:, None], np.searchsorted(index, key | limit), start))
            starts.append(start)
        start, stop = np.concatenate(starts, 1), np.concatenate(stops, 1)
        table, mine = self._folded(held), self._folds(asks)
        most = 4
        while len(asks):
            take = np.minimum(stop - start, most)
            total = np.cumsum(take.sum(1))
            settled = np.zeros(len(asks), bool)
            x = 0
            while x < len(asks):
                y = max(int(np.searchsorted(total, (total[x - 1] if x else 0) + MOST_TESTS, "right")), x + 1)
                times = take[x:y].ravel()
                entry = np.repeat(start[x:y].ravel() - np.cumsum(times) + times, times) + np.arange(times.sum())
                which = np.repeat(np.repeat(np.arange(x, y), take.shape[1]), times)
                pairs = np.sort((which.astype(np.uint64) << np.uint64(24)) | (index[entry] & PLACE))
                pairs = pairs[_starts(pairs)]
                which, place = (pairs >> np.uint64(24)).astype(np.int64), (pairs & PLACE).astype(np.int64)
                near = self._may_share(table, mine, which, place)
                which, place = which[near], refs[place[near]]
                good = self._share(asks[which], place)
                which, place = which[good], place[good]
                if not every:
                    first = _starts(which)
                    which, place = which[first], place[first]
                settled[which] = True
                yield asks[which], place
                x = y
            start = start + take
            rest = (start < stop).any(1) & (every | ~settled)
            asks, start, stop, mine, most = asks[rest], start[rest], stop[rest], mine[rest], most * 8

    def _folded(self, held: np.ndarray) -> np.ndarray:
        """Which remainders the shingles around each place have; the last column stands for no shingle."""
        table = np.zeros((len(held), FOLDED + 1), bool)
        table[np.arange(len(held))[:, None], held % FOLDED] = True
        table[:, FOLDED] = False
        return table

    def _folds(self, rows: np.ndarray) -> np.ndarray:
        """Columns of :meth:`_folded` for the shingles that a sequence of the wanted length around each place can hold."""
        reach = self.p.window - 1
        offset = np.arange(-reach, reach + 1)
        inside = (offset >= -self.before[rows][:, None]) & (offset <= self.after[rows][:, None])
        near = np.take_along_axis(self.near[rows], np.where(inside, self.before[rows][:, None] + offset, 0), 1)
        return np.where(inside, near % FOLDED, FOLDED).astype(np.int32)

    def _may_share(self, table: np.ndarray, mine: np.ndarray, which: np.ndarray, place: np.ndarray) -> np.ndarray:
        """False where :meth:`_share` must fail: equal shingles have equal remainders, so too few of these are too few of those."""
        p, flat_table, out = self.p, table.ravel(), np.zeros(len(which), bool)
        for i in range(0, len(which), 2000):
            hit = flat_table.take(mine[which[i : i + 2000]] + (place[i : i + 2000] * (FOLDED + 1))[:, None])
            some = np.flatnonzero(np.count_nonzero(hit, 1) >= p.contained)
            total = np.zeros((len(some), hit.shape[1] + 1), np.int16)
            np.cumsum(hit[some], 1, out=total[:, 1:])
            out[i + some] = (total[:, p.window :] - total[:, : -p.window] >= p.contained).any(1)
        return out

    def _share(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether sequences of the wanted length around each place of ``a`` are a passage that ``b`` has around it."""
        p, reach = self.p, self.p.window - 1
        out = np.zeros(len(a), bool)
        offset = np.arange(-reach, reach + 1)
        for i in range(0, len(a), 200):
            some, there = a[i : i + 200], self.near[b[i : i + 200]]
            low, high = -np.minimum(self.before[some], reach)[:, None], np.minimum(self.after[some], reach)[:, None]
            inside = (offset >= low) & (offset <= high)
            mine = np.take_along_axis(self.near[some], np.where(inside, self.before[some][:, None] + offset, 0), 1)
            hit = (mine[:, :, None] == there[:, None, :]).any(2) & inside
            total = np.zeros((len(some), 2 * reach + 2), np.int16)
            np.cumsum(hit, 1, out=total[:, 1:])
            good = (total[:, p.window :] - total[:, : -p.window] >= p.contained) & (offset[: reach + 1] >= low) & (offset[reach:] <= high)
            first = good.argmax(1)[:, None] - reach
            last = reach - good[:, ::-1].argmax(1)[:, None]
            run = hit & (offset >= first) & (offset <= last)
            out[i : i + 200] = good.any(1) & (2 * reach - run[:, ::-1].argmax(1) - run.argmax(1) >= reach)
        return out

    def spans(self, rows: np.ndarray) -> np.ndarray:
        """The windows of the places, made as wide as the sequences of the wanted length around them."""
        reach, c = self.p.window - 1, self.c[rows]
        low = np.minimum(self.lr[rows] >> 32, c - np.minimum(self.before[rows], reach))
        high = np.maximum(self.lr[rows] & 0xFFFFFFFF, c + np.minimum(self.after[rows], reach) + 1)
        return (low << 32) | high


def _partners(p: PassageParams, every: bool):
    """Sorted by route, turn and document: open windows are linked with an earlier document, or ``every`` one, that has a passage around their place."""
    names = [x.split()[0] for x in LINKS.split(", ")]
    wide = 2 * (p.window - 1 + p.slack) + 1

    def solve(held):
        *columns, before, near = (np.concatenate(x) for x in zip(*held, strict=True))
        cuts = np.append(np.flatnonzero(_starts(columns[0]) | _starts(columns[1])), len(before))
        large = np.flatnonzero(np.diff(cuts) > INDEXED)  # these alone are indexed in parts
        small = np.ones(len(before), bool)
        for x, y in zip(cuts[large], cuts[large + 1], strict=True):
            small[x:y] = False
        for rows in [np.flatnonzero(small), *(np.arange(cuts[x], cuts[x + 1]) for x in large)]:
            if not len(rows):
                continue
            places = Places(p, [v[rows] for v in columns], before[rows], near[rows])
            for a, b in places.links(every):
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in (places.ids[a], places.spans(a), places.c[a], places.ids[b], places.spans(b), places.c[b], places.k[a].astype(np.int32))], names)

    def run(batches):
        held, rows, last = [], 0, None
        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [np.asarray(x.to_numpy(zero_copy_only=False)) for x in batch.columns[:9]]
            columns[6] = columns[6].astype(bool)
            texts = batch.column(9)
            _, offsets, data = texts.buffers()
            at = np.frombuffer(offsets, np.int32, len(texts) + 1, texts.offset * 4)
            length = np.diff(at) // 4
            near = np.zeros((len(texts), wide), np.uint32)
            near[np.arange(wide) < length[:, None]] = np.frombuffer(data, np.uint8)[at[0] : at[-1]].view(np.uint32)
            cuts = np.flatnonzero(_starts(columns[0]) | _starts(columns[1]))
            if (columns[0][0], columns[1][0]) == last:
                cuts = cuts[1:]
            last = (columns[0][-1], columns[1][-1])
            rows += len(texts)
            if rows >= MOST_PLACES and len(cuts):
                yield from solve([*held, [v[: cuts[-1]] for v in (*columns, near)]])
                held, rows = [], len(texts) - cuts[-1]
                columns, near = [v[cuts[-1] :] for v in columns], near[cuts[-1] :]
            held.append([*columns, near])
        if held:
            yield from solve(held)

    return run


def _starts(x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), bool)
    out[1:] = x[1:] != x[:-1]
    return out


def agreed_stretches(rows: np.ndarray, p: PassageParams) -> list[tuple[int, int, int, int]]:
    """Stretches ``(first, last, shift_low, shift_high)`` of shingles that enough functions link.

    ``rows`` has columns l, r, c, ref_l, ref_r, ref_c, hash for one pair of documents.
    """
    out = []
    shift = rows[:, 2] - rows[:, 5]
    order = np.argsort(shift, kind="stable")
    rows, shift = rows[order], shift[order]
    for part in np.split(np.arange(len(rows)), np.flatnonzero(np.diff(shift) > p.slack) + 1):
        if len(np.unique(rows[part, 6])) < p.enough:
            continue
        low = np.maximum(rows[part, 0], rows[part, 3] + shift[part])
        high = np.minimum(rows[part, 1], rows[part, 4] + shift[part])
        base = low.min()
        cover = np.zeros((p.hashes, high.max() - base + 1), np.int64)
        np.add.at(cover, (rows[part, 6], low - base), 1)
        np.add.at(cover, (rows[part, 6], high - base), -1)
        agreed = np.concatenate([[False], (np.cumsum(cover, 1) > 0).sum(0) >= p.enough, [False]])
        edge = np.flatnonzero(agreed[1:] != agreed[:-1])
        out += [(int(x + base), int(y + base), int(shift[part[0]]), int(shift[part[-1]])) for x, y in zip(edge[::2], edge[1::2], strict=True) if y - x >= p.window - p.slack]
    return out


def _candidates(p: PassageParams):
    names = ["doc_id", "first", "stop", "ref_id", "ref_first", "ref_stop"]

    def solve(pair, chunks, out):
        rows = np.concatenate(chunks)
        if len(np.unique(rows[:, 6])) < p.enough:
            return
        for first, stop, low, high in agreed_stretches(rows, p):
            out.append((pair[0], first, stop, pair[1], max(first - high - p.slack, 0), stop - low + p.slack))

    def run(batches):
        pair, chunks = None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            out = []
            ids, lr, c, ref, ref_lr, ref_c, k = (np.asarray(x) for x in batch.columns)
            rows = np.column_stack([lr >> 32, lr & 0xFFFFFFFF, c, ref_lr >> 32, ref_lr & 0xFFFFFFFF, ref_c, k])
            cuts = np.concatenate([[0], np.flatnonzero((np.diff(ids) != 0) | (np.diff(ref) != 0)) + 1, [len(ids)]])
            for x, y in zip(cuts[:-1], cuts[1:], strict=True):
                here = (int(ids[x]), int(ref[x]))
                if here != pair:
                    if chunks:
                        solve(pair, chunks, out)
                    pair, chunks = here, []
                chunks.append(rows[x:y])
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*out, strict=True) if out else [[]] * 6)], names)
        out = []
        if chunks:
            solve(pair, chunks, out)
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*out, strict=True) if out else [[]] * 6)], names)

    return run


FETCHED = "pair long, side int, doc_id long, first long, ref_id long, shingles array<long>, starts array<int>, ends array<int>"
MOST_FETCHED = 500_000


def _ragged(values: np.ndarray, first: np.ndarray, length: np.ndarray) -> pa.ListArray:
    """The runs ``values[first:first + length]`` as lists."""
    offsets = np.concatenate([[0], np.cumsum(length)])
    at = np.repeat(first - offsets[:-1], length) + np.arange(offsets[-1])
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values[at]))


def _merged(batch: pa.RecordBatch) -> pa.RecordBatch:
    """Rows that follow one another with the same document and text as one row with all their asks."""
    ids, texts, asks = batch.columns
    fresh = np.ones(len(ids), bool)
    fresh[1:] = (np.diff(np.asarray(ids)) != 0) | ~np.asarray(pc.equal(texts[1:], texts[:-1]).fill_null(False))
    if fresh.all():
        return batch
    offsets, rows = np.asarray(asks.offsets), pa.array(np.flatnonzero(fresh))
    asks = pa.ListArray.from_arrays(pa.array(np.append(offsets[:-1][fresh], offsets[-1])), asks.values)
    return pa.RecordBatch.from_arrays([ids.take(rows), texts.take(rows), asks], batch.schema.names)


def _fetched(p: PassageParams):
    """The asked stretches: their shingles and, on the later document's side, where its words lie."""
    names = [x.split()[0] for x in FETCHED.split(", ")]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            for part in flat.slices(_merged(batch), "text"):
                s = flat.Slice(part.column(1), lower=True)
                start, end, bounds, h = word_shingles(s, p.words)
                asks = part.column(2)
                docs = np.repeat(np.arange(part.num_rows), np.asarray(asks.value_lengths()))
                columns = [np.asarray(x) for x in asks.flatten().flatten()]
                base = s.at[:-1][np.searchsorted(s.at, start, "right") - 1] if len(start) else start
                places = [(v - base).astype(np.int32) for v in (start, end)]
                total = np.cumsum(columns[3] - columns[2])
                i = 0
                while i < len(docs):
                    j = max(int(np.searchsorted(total, (total[i - 1] if i else 0) + MOST_FETCHED, "right")), i + 1)
                    doc, (pair, side, first, stop, ref) = docs[i:j], (v[i:j] for v in columns)
                    count = np.maximum(np.diff(bounds)[doc] - p.words + 1, 0)
                    x, y = np.minimum(first, count), np.minimum(stop, count)
                    words = np.where((side == 0) & (y > x), y - x + p.words - 1, 0)
                    at = bounds[:-1][doc] + x
                    spans = [_ragged(v, at, words) for v in places]
                    ids = np.asarray(part.column(0))[doc]
                    yield pa.RecordBatch.from_arrays([*(pa.array(v) for v in (pair, side, ids, first, ref)), _ragged(h.view(np.int64), at, y - x), *spans], names)
                    i = j

    return run


PASSAGES = "doc_id long, first_word long, last_word long, start_byte long, end_byte long, ref_id long, similarity double"


def matched_stretches(here: np.ndarray, there: np.ndarray, p: PassageParams):
    """Yields ``(first, last, similarity)`` of the stretches of ``here`` that ``there`` has, in shingles, both inclusive.

    Where sequences of the wanted length match, but differ too much as one stretch, each of them is judged alone.
    """
    if len(here) < p.window:
        return
    own, other, kinds = _numbered(here, there)
    held = np.zeros(kinds, bool)
    held[other] = True
    hit = held[own]
    total = np.zeros(len(hit) + 1, np.int64)
    hit.cumsum(out=total[1:])
    good = (total[p.window :] - total[: -p.window] >= p.contained).nonzero()[0]
    if not len(good):
        return
    cuts = [0, *((good[1:] - good[:-1] > p.window).nonzero()[0] + 1).tolist(), len(good)]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        run = good[a:b]
        matched = hit[run[0] : run[-1] + p.window].nonzero()[0] + run[0]
        whole = _judged(own, other, kinds, int(matched[0]), int(matched[-1]), p)
        if whole is not None:
            yield whole
        elif len(run) > 1:
            yield from _parts(here, own, other, kinds, run[hit[run] & hit[run + p.window - 1]], p)


def _numbered(here: np.ndarray, there: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Both sides with their distinct shingles numbered from 0, and how many these are."""
    both = np.concatenate([here, there])
    order = both.argsort()
    ordered = both[order]
    number = np.zeros(len(both), np.int64)
    (ordered[1:] != ordered[:-1]).cumsum(out=number[1:])
    out = np.empty(len(both), np.int64)
    out[order] = number
    return out[: len(here)], out[len(here) :], int(number[-1]) + 1


def _parts(here: np.ndarray, own: np.ndarray, other: np.ndarray, kinds: int, starts: np.ndarray, p: PassageParams):
    """Of the sequences at ``starts``, each judged alone, as few as cover all those that pass."""
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(here.view(np.uint64))])
    _, alike, kind = np.unique(total[starts + p.window] - total[starts], return_index=True, return_inverse=True)
    found = [_judged(own, other, kinds, int(x), int(x) + p.window - 1, p) for x in starts[alike]]
    passed = np.flatnonzero(np.array([x is not None for x in found], bool)[kind])
    i = 0
    while i < len(passed):
        first = int(starts[passed[i]])
        yield first, first + p.window - 1, found[kind[passed[i]]][2]
        i = max(i + 1, int(np.searchsorted(starts[passed], first + p.window, "right")) - 1)


def _judged(own: np.ndarray, other: np.ndarray, kinds: int, first: int, last: int, p: PassageParams) -> tuple[int, int, float] | None:
    """The stretch of ``own`` with its similarity, if it is long enough and ``other`` holds it nearly word for word; shingles are numbers below ``kinds``."""
    if last - first + p.words < p.length:
        return None
    mine, n = own[first : last + 1], last - first + 1
    # a whole copy starts, and ends, as the stretch does
    for x in ((other[: max(len(other) - n + 1, 0)] == mine[0]) & (other[n - 1 :] == mine[-1])).nonzero()[0].tolist():
        if (other[x : x + n] == mine).all():
            return first, last, 1.0
    held = np.zeros(kinds, bool)
    held[mine] = True
    where = held[other].nonzero()[0]
    around = np.zeros(kinds, bool)
    around[other[where[0] : where[-1] + 1]] = True
    size, same = int(np.count_nonzero(held)), int(np.count_nonzero(held & around))
    # a stretch elsewhere in the reference may repeat some shingles: containment decides then
    if same / size >= p.contained / p.window:
        return first, last, max(same / (size + int(np.count_nonzero(around)) - same), same / size * p.similarity)
    return None


def _verified(p: PassageParams):
    """Sorted by pair and side: the passages that each pair's stretches share."""
    names = [x.split()[0] for x in PASSAGES.split(", ")]
    kinds = [pa.int64()] * 6 + [pa.float64()]

    def run(batches):
        pair, mine = None, []  # rows that repeat an id give several stretches
        for batch in batches:
            out = []
            pairs, sides, ids, firsts, refs = (np.asarray(c).tolist() for c in batch.columns[:5])
            lists = [(np.asarray(c.offsets).tolist(), np.asarray(c.flatten()), np.asarray(c.offsets)[0]) for c in batch.columns[5:]]
            for i in range(batch.num_rows):
                if pairs[i] != pair:
                    pair, mine = pairs[i], []
                shingles, starts, ends = (values[offsets[i] - low : offsets[i + 1] - low] for offsets, values, low in lists)
                if sides[i] == 0:
                    mine.append((ids[i], firsts[i], refs[i], shingles, starts, ends))
                    continue
                for doc, at, ref, own, begin, end in mine:
                    for first, last, similarity in matched_stretches(own, shingles, p):
                        out.append((doc, at + first, at + last + p.words - 1, int(begin[first]), int(end[last + p.words - 1]), ref, similarity))
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out, strict=True) if out else [[]] * 7, kinds, strict=True)], names)

    return run


def _unsettled(windows: DataFrame, found: DataFrame, p: PassageParams) -> DataFrame:
    """The windows whose min shingle lies in no passage found so far."""
    spans = found.select(F.col("doc_id").alias("of"), "first_word", "last_word").distinct()
    return windows.join(spans, (F.col("doc_id") == F.col("of")) & (F.col("c") >= F.col("first_word")) & (F.col("c") + p.words - 1 <= F.col("last_word")), "left_anti")


def _passages_of(texts: DataFrame, links: DataFrame, p: PassageParams) -> DataFrame:
    """The verified passages of linked windows, as a written table."""
    spread = links.repartition("doc_id", "ref_id").sortWithinPartitions("doc_id", "ref_id")
    found = spread.mapInArrow(_candidates(p), "doc_id long, first long, stop long, ref_id long, ref_first long, ref_stop long").distinct()
    candidates = written(found.withColumn("pair", F.monotonically_increasing_id()), "passages")
    release(texts.sparkSession)
    ask = lambda doc, first, stop, side: F.struct(F.col(doc).alias("doc_id"), F.struct("pair", F.lit(side).cast("int").alias("side"), F.col(first).alias("first"), F.col(stop).alias("stop"), "ref_id").alias("ask"))
    both = candidates.select(F.explode(F.array(ask("doc_id", "first", "stop", 0), ask("ref_id", "ref_first", "ref_stop", 1))).alias("x"))
    # a passage of a reference that many documents repeat is fetched by many asks: split them
    asks = both.select("x.doc_id", "x.ask", F.pmod(F.xxhash64("x.ask.pair"), F.lit(64)).alias("salt"))
    asked = asks.groupBy("doc_id", "salt").agg(F.collect_list("ask").alias("asks")).select("doc_id", "asks")
    fetched = texts.join(asked, "doc_id").select("doc_id", "text", "asks").mapInArrow(_fetched(p), FETCHED)
    out = written(fetched.repartition("pair").sortWithinPartitions("pair", "side").mapInArrow(_verified(p), PASSAGES), "verified")
    discard(candidates)
    release(texts.sparkSession)
    return out


ASKS_PER_TASK = 200_000


def _links_of_open(texts: DataFrame, grouped: DataFrame, asked: DataFrame, p: PassageParams, every: bool) -> DataFrame:
    """Links of the asked windows with earlier documents of their groups, as a written table.

    The open windows of a large group take turns, each of which has all places.
    """
    routes = asked.groupBy("route").agg(F.ceil(F.count("*") / ASKS_PER_TASK).cast("int").alias("turns"))
    place = ["route", "doc_id", "lr", "c", "hash"]
    lead = grouped.where("lead").select(*place, F.lit(False).alias("open"))
    # a group's first document has shared one function only with the open windows
    firsts = grouped.where("head").select("route", F.col("ref_id").alias("doc_id"), F.col("ref_lr").alias("lr"), F.col("ref_c").alias("c"), "hash", F.lit(False).alias("open"))
    # one exchange by route serves the choice of groups and the marks of the open windows
    rows = lead.unionByName(firsts).join(routes, "route", "left_semi").unionByName(asked.select(*place, F.lit(True).alias("open")))
    members = rows.groupBy(*place).agg(F.max("open").alias("open")).join(routes, "route")
    members = written(members, "members", "zstd")
    release(texts.sparkSession)
    asks = members.groupBy("doc_id").agg(F.collect_list(F.struct("route", "turns", "lr", "c", "hash", "open")).alias("asks"))
    contexts = texts.join(asks, "doc_id").select("doc_id", "text", "asks").mapInArrow(_contexts(p), CONTEXTS)
    dealt = contexts.withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("turns") - 1)))
    dealt = dealt.withColumn("open", F.col("open") & (F.col("turn") == F.pmod(F.xxhash64("doc_id", "c"), F.col("turns"))))
    dealt = dealt.select("route", "turn", "doc_id", "lr", "c", "hash", "open", "around", "before", "shingles").repartition("route", "turn")
    links = written(dealt.sortWithinPartitions("route", "turn", "doc_id", "c", "around").mapInArrow(_partners(p, every), LINKS), "partners")
    discard(members)
    release(texts.sparkSession)
    return links


def repeated_passages(documents: DataFrame, p: PassageParams = PassageParams()) -> DataFrame:
    """Passages of ``length`` words or more that an earlier document has too, nearly word for word.

    One row per passage and earlier document: ``doc_id, first_word, last_word, start_byte,
    end_byte, ref_id, similarity``; words count from 0, bytes index the UTF-8 text, ends of
    bytes are exclusive. ``ref_id`` is always a smaller ``doc_id`` with that passage. A passage
    that a document repeats is reported at each place, if an earlier document has it; repeats
    inside one document alone are not. A window counts as settled once its min shingle lies in
    a verified passage, so a passage that crosses the border of a found one may be missed where
    few of its shingles lie beyond.
    Null, empty and short texts have no passage; rows without ``doc_id`` take no part; rows
    that repeat a ``doc_id`` count as one document. An empty table gives an empty result.
    """
    ship(documents.sparkSession)
    texts = documents.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    windows = texts.mapInArrow(_windows(p), WINDOWS)
    grouped = written(windows.repartition("route").sortWithinPartitions("route", "doc_id", "around", "ck").mapInArrow(_linked, GROUPED), "links", "zstd")
    release(documents.sparkSession)
    found = _passages_of(texts, grouped.select(*(x.split()[0] for x in LINKS.split(", "))), p)
    asked = written(_unsettled(grouped.where("lead and more").select("route", "doc_id", "lr", "c", "hash"), found, p), "open")
    if not asked.isEmpty():
        links = _links_of_open(texts, grouped, asked, p, every=False)
        found = found.unionByName(_passages_of(texts, links, replace(p, enough=1)))
        # windows whose partner was not confirmed meet all the others too
        left = written(_unsettled(asked.join(links.select("doc_id", "c", "hash").distinct(), ["doc_id", "c", "hash"], "left_semi"), found, p), "left")
        if not left.isEmpty():
            more = _links_of_open(texts, grouped, left, p, every=True)
            found = found.unionByName(_passages_of(texts, more, replace(p, enough=1)))
            discard(more)
        discard(links, left)
    discard(grouped, asked)
    # several places of a reference, or both steps, may give the same passage
    keys = [x.split()[0] for x in PASSAGES.split(", ")]
    return found.groupBy(*keys[:-1]).agg(F.max("similarity").alias("similarity"))


def _without(batches):
    for batch in batches:
        texts = []
        for text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if spans:
                raw, kept, at = text.encode(), [], 0
                for a, b in sorted((x["start_byte"], x["end_byte"]) for x in spans):
                    if b > at:
                        kept.append(raw[at : max(a, at)])
                        at = b
                kept.append(raw[at:])
                text = b"".join(kept).decode()
            texts.append(text)
        yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()), *batch.columns[2:]], ["text", *batch.schema.names[2:]])


def remove_repeated_passages(documents: DataFrame, p: PassageParams = PassageParams()) -> DataFrame:
    """The documents, all columns, without passages that an earlier document has too.

    ``n_chars`` is set anew where it exists. A document of which no word is left goes; texts
    that held no word before stay.
    """
    spans = repeated_passages(documents, p).groupBy("doc_id").agg(F.collect_list(F.struct("start_byte", "end_byte")).alias("spans__"))
    rest = [c for c in documents.columns if c != "text"]
    joined = documents.join(spans, "doc_id", "left").select("text", "spans__", F.col("spans__").isNotNull().alias("cut__"), *rest)
    kinds = dict(documents.dtypes)
    schema = ", ".join(["text string", "cut__ boolean", *(f"`{c}` {kinds[c]}" for c in rest)])
    out = joined.mapInArrow(_without, schema).where("not cut__ or text rlike '[^\\\\x20\\\\x09-\\\\x0D]'")
    if "n_chars" in rest:
        out = out.withColumn("n_chars", F.when(F.col("cut__"), F.length("text").cast(kinds["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*documents.columns)
