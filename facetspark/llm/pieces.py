"""SentencePiece encoding by sampling, and decoding.

The piece lattice of a text has a node at each byte and an edge for each vocabulary piece
that matches; characters without a piece fall back to byte pieces. Forward filtering adds up
the weights of all segmentations up to each node; backward sampling then draws the last
piece, the one before it, and so on, in exact proportion to the segmentations' weights. The
draws are a hash of seed, row key, place and step, so a row is segmented alike in any
partitioning and on any retry.

No piece runs across the start of a space or past a line end, so the lattice falls apart
into chunks. Forward sums are made once per distinct chunk of a slice, all chunks side by
side; the draws of all chunks of all rows advance together.

Public piece models of the merge kind hold ranks, not probabilities. A piece of rank r gets
the weight ``(r + shift) ** -slope``, a Zipf law; with slopes far above 1 the sample tends to
the best segmentation.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import ship

SPACE, NEWLINE = 0x20, 0x0A


@dataclass(frozen=True)
class PieceParams:
    """``sample=False`` takes the heaviest segmentation; ``byte_log_weight`` is that of a byte piece."""

    sample: bool = True
    seed: int = 17
    slope: float = 1.2
    shift: float = 2.7
    byte_log_weight: float = -16.0
    slice_bytes: int = 1_000_000


def default_model_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class PieceTable:
    """Vocabulary as bytes, with the space mark turned back into a space."""

    def __init__(self, model_path: str, p: PieceParams):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        size = model.vocab_size()
        self.texts = [b""] * size
        self.byte_id = np.full(256, model.unk_id(), np.int32)
        words, ids = [], []
        for i in range(size):
            if model.is_byte(i):
                value = int(model.id_to_piece(i)[3:5], 16)
                self.byte_id[value] = i
                self.texts[i] = bytes([value])
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                self.texts[i] = model.id_to_piece(i).replace("▁", " ").encode()
                words.append(self.texts[i])
                ids.append(i)
        if any(b" " in w.lstrip(b" ") or b"\n" in w for w in words):
            raise ValueError("pieces across spaces or lines are not supported")
        s = flat.Slice(pa.array(words, pa.binary()))
        h = s.hashes(s.prefix(), s.at[:-1], s.at[1:])
        order = np.argsort(h)
        self.hashes, self.ids = h[order], np.array(ids, np.int32)[order]
        rank = np.argsort(np.argsort(ids))[order]
        self.log_weights = -p.slope * np.log(rank + 1 + p.shift)
        self.lengths = sorted({len(w) for w in words})
        self.filter = np.zeros(1 << 20, bool)
        self.filter[(self.hashes >> np.uint64(44)).astype(np.int64)] = True
        self.out_bytes = np.frombuffer(b"".join(self.texts), np.uint8)
        self.out_at = np.concatenate([[0], np.cumsum([len(t) for t in self.texts])])

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        maybe = np.flatnonzero(self.filter[(h >> np.uint64(44)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.hashes, h[maybe]), len(self.hashes) - 1)
        hit = self.hashes[at] == h[maybe]
        return maybe[hit], at[hit]


def with_leading_space(column: pa.Array) -> flat.Slice:
    """The texts, each with one space put before it."""
    s = flat.Slice(column)
    buf = np.empty(len(s.buf) + s.docs, np.uint8)
    at = s.at + np.arange(s.docs + 1)
    inside = np.ones(len(buf), bool)
    inside[at[:-1]] = False
    buf[inside] = s.buf
    buf[at[:-1]] = SPACE
    s.buf, s.at = buf, at
    return s


def lattice(s: flat.Slice, prefix: np.ndarray, start: np.ndarray, end: np.ndarray, table: PieceTable, p: PieceParams):
    """Edges of the lattices of chunks ``buf[start:end]``, by end node.

    Chunk k owns nodes ``base[k] .. base[k] + length``. Returns base, and per edge its two
    nodes, piece id and log weight.
    """
    length = end - start
    base = np.concatenate([[0], np.cumsum(length + 1)])
    where = np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
    byte, node = where + np.repeat(start, length), where + np.repeat(base[:-1], length)
    room = np.repeat(length, length) - where
    begins = (s.buf[byte] & 0xC0) != 0x80
    wide = np.select([s.buf[byte] < 0x80, s.buf[byte] < 0xE0, s.buf[byte] < 0xF0], [1, 2, 3], 4)
    covered = np.zeros(len(byte), bool)
    edges = []
    for n in table.lengths:
        sel = np.flatnonzero(begins & (room >= n))
        if not len(sel):
            continue
        hit, piece = table.find(s.hashes(prefix, byte[sel], byte[sel] + n))
        sel = sel[hit]
        edges.append((node[sel], node[sel] + n, table.ids[piece], table.log_weights[piece]))
        covered[sel[wide[sel] == n]] = True
    lead = np.maximum.accumulate(np.where(begins, np.arange(len(byte)), 0))
    bare = np.flatnonzero(~covered[lead])
    edges.append((node[bare], node[bare] + 1, table.byte_id[s.buf[byte[bare]]], np.full(len(bare), p.byte_log_weight)))
    a, b, piece, weight = (np.concatenate(x) for x in zip(*edges, strict=True))
    order = np.lexsort((a, b))
    return base, a[order], b[order], piece[order], weight[order]


def forward(base: np.ndarray, a: np.ndarray, b: np.ndarray, weight: np.ndarray, sample: bool) -> np.ndarray:
    """Log weight of all (or of the heaviest) segmentations up to each node."""
    total = np.full(base[-1], -np.inf)
    total[base[:-1]] = 0.0
    depth = b - base[np.searchsorted(base, b, "right") - 1]
    order = np.argsort(depth, kind="stable")
    steps = np.searchsorted(depth[order], np.arange(1, (depth.max() if len(depth) else 0) + 2))
    for x, y in zip(steps[:-1], steps[1:], strict=True):
        e = order[x:y]
        if not len(e):
            continue
        value = total[a[e]] + weight[e]
        first = np.flatnonzero(np.concatenate([[True], b[e][1:] != b[e][:-1]]))
        most = np.maximum.reduceat(value, first)
        if sample:
            safe = np.where(np.isfinite(most), most, 0)
            rep = np.repeat(safe, np.diff(np.append(first, len(e))))
            with np.errstate(divide="ignore"):
                most = safe + np.log(np.add.reduceat(np.exp(value - rep), first))
        total[b[e][first]] = most
    return total


def encode_slice(column: pa.Array, keys: np.ndarray, table: PieceTable, p: PieceParams) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of all rows, and the rows' bounds among them."""
    s = with_leading_space(column)
    n = len(s.buf)
    space, line = s.buf == SPACE, s.buf == NEWLINE
    cut = np.zeros(n, bool)
    cut[s.at[:-1]] = True
    cut[1:] |= (space[1:] & ~space[:-1]) | line[:-1] | line[1:]
    start = np.flatnonzero(cut)
    end = np.append(start[1:], n)
    prefix = s.prefix()
    _, first, which = np.unique(s.hashes(prefix, start, end), return_index=True, return_inverse=True)
    base, a, b, piece, weight = lattice(s, prefix, start[first], end[first], table, p)
    total = forward(base, a, b, weight, p.sample)
    # one increasing key per edge: its end node, then the share of the node's weight up to it
    value = total[a] + weight
    new = np.concatenate([[True], b[1:] != b[:-1]])
    head = np.flatnonzero(new)
    if p.sample:
        share = np.exp(value - total[b])
        run = np.cumsum(share)
        run -= np.repeat(run[head] - share[head], np.diff(np.append(head, len(b))))
        share = np.minimum((run * 2**32).astype(np.uint64), np.uint64(2**32 - 1))
    else:
        best = value >= total[b]
        share = np.where(best, np.uint64(2**32 - 1), np.uint64(0))
        share = np.maximum.accumulate(share + (b.astype(np.uint64) << np.uint64(32))) - (b.astype(np.uint64) << np.uint64(32))
    share[np.append(head[1:], len(b)) - 1] = 2**32 - 1
    edge_key = (b.astype(np.uint64) << np.uint64(32)) | share
    order = np.argsort(which, kind="stable")  # equal chunks side by side: lookups stay in cache
    row = np.searchsorted(s.at, start, "right") - 1
    place = start - s.at[row]
    seed = flat.mix(keys.view(np.uint64)[row] * flat.MULTIPLIERS[500] + place.astype(np.uint64) * flat.MULTIPLIERS[501] + np.uint64(p.seed))[order]
    node, goal = base[1:][which[order]] - 1, base[:-1][which[order]]
    alive = np.flatnonzero(node > goal)
    taken, step = [], 0
    count = np.zeros(len(start), np.int64)
    while len(alive):
        if p.sample:
            draw = flat.mix(seed[alive] + flat.MULTIPLIERS[502:503] * np.uint64(step)) >> np.uint64(32)
            draw = np.minimum(draw, np.uint64(2**32 - 2))
        else:
            draw = np.full(len(alive), 2**31, np.uint64)
        e = np.searchsorted(edge_key, (node[alive].astype(np.uint64) << np.uint64(32)) | draw, "right" if p.sample else "left")
        taken.append((alive, piece[e]))
        count[alive] += 1
        node[alive] = a[e]
        alive = alive[node[alive] > goal[alive]]
        step += 1
    back = np.empty(len(start), np.int64)
    back[order] = np.arange(len(start))
    per_chunk = count[back]
    offset = (np.cumsum(per_chunk) - per_chunk)[order]
    out = np.empty(per_chunk.sum(), np.int32)
    for k, (which_, ids) in enumerate(taken):
        out[offset[which_] + count[which_] - 1 - k] = ids
    bounds = np.concatenate([[0], np.cumsum(np.bincount(row, per_chunk, minlength=s.docs).astype(np.int64))])
    return out, bounds


def decode_slice(ids: np.ndarray, bounds: np.ndarray, table: PieceTable) -> list[bytes]:
    """Bytes of each row's pieces, without the space that encoding put in front."""
    size = table.out_at[ids + 1] - table.out_at[ids]
    total = np.concatenate([[0], np.cumsum(size)])
    data = table.out_bytes[np.arange(total[-1]) - np.repeat(total[:-1], size) + np.repeat(table.out_at[ids], size)].tobytes()
    at = total[bounds]
    return [data[x + 1 : y] if y > x else b"" for x, y in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]


def encode(documents: DataFrame, model_path: str | None = None, p: PieceParams = PieceParams(), key: str = "doc_id") -> DataFrame:
    """One row per input row: the key column, ``n_pieces``, ``piece_ids``, ``lossless``.

    Rows are segmented by their key and text alone: rows that repeat both get equal pieces, a
    null key counts as one fixed key. A null text gives a null list and 0 pieces; an empty one
    the single leading-space piece. ``lossless`` tells that decoding gave back the very text.
    """
    spark: SparkSession = documents.sparkSession
    ship(spark)
    held = spark.sparkContext.broadcast(PieceTable(model_path or default_model_path(), p))  # a vocabulary: fixed size
    kind = dict(documents.dtypes)[key]

    def run(batches):
        table = held.value
        for batch in batches:
            for part in flat.slices(batch, "text", p.slice_bytes):
                text, hashed = part.column(1), np.asarray(part.column(2)).astype(np.int64)
                ids, bounds = encode_slice(text, hashed, table, p)
                plain = text.cast(pa.large_binary()).to_pylist()
                same = [t is None or t == d for t, d in zip(plain, decode_slice(ids, bounds, table), strict=True)]
                gone = np.asarray(text.is_null().to_numpy(zero_copy_only=False))
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids), mask=pa.array(gone))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.where(gone, 0, np.diff(bounds))), lists, pa.array(same, pa.bool_())], [key, "n_pieces", "piece_ids", "lossless"])

    rows = documents.select(F.col(key), F.col("text").cast("string").alias("text"), F.xxhash64(F.col(key).cast("string")).alias("hashed__"))
    return rows.mapInArrow(run, f"`{key}` {kind}, n_pieces long, piece_ids array<int>, lossless boolean")


def decode(encoded: DataFrame, model_path: str | None = None, p: PieceParams = PieceParams(), key: str = "doc_id") -> DataFrame:
    """The key column and ``text``, from ``piece_ids``; a null list gives a null text."""
    spark: SparkSession = encoded.sparkSession
    ship(spark)
    held = spark.sparkContext.broadcast(PieceTable(model_path or default_model_path(), p))
    kind = dict(encoded.dtypes)[key]

    def run(batches):
        for batch in batches:
            lists = batch.column(1)
            sizes = np.asarray(lists.value_lengths().fill_null(0)).astype(np.int64)
            ids = np.asarray(lists.flatten()).astype(np.int64)
            texts = decode_slice(ids, np.concatenate([[0], np.cumsum(sizes)]), held.value)
            texts = [None if not ok else t.decode() for ok, t in zip(lists.is_valid().to_pylist(), texts, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], [key, "text"])

    return encoded.select(key, "piece_ids").mapInArrow(run, f"`{key}` {kind}, text string")
