"""MinHash near-duplicate groups with sequential Bayesian verification.

1. Every text becomes its set of distinct word shingles; texts with equal sets are one node.
2. Nodes that agree in a band of MinHash values are candidates. A node's weight is the sum of
   its buckets' sizes: the least changed copies of a group weigh most. A bucket first compares
   all its members with its heaviest one (a star); members that no link has brought into the
   bucket's largest group then form stars of their own. What is still open is split by rare
   shingles: two linked sets share one of the rarest shingles of each (prefix filter), at
   places that leave enough shingles for the overlap (size classes and position bounds).
   Copies changed too much to reach the threshold have no such shingle in common, so a large
   group of copies costs about its size, and no link is lost.
3. A candidate pair is compared signature batch by batch. After each batch it is dropped if
   the posterior probability of a similarity at or above the threshold, under a uniform
   prior, is below ``miss``. Survivors are verified on their full sets.
4. Verified links are closed to connected components.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import comb, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import connected, discard, ship, written


@dataclass(frozen=True)
class NearDuplicateParams:
    """``bands * rows`` MinHash values; ``batch`` of them are compared at a time.

    With 24 bands of 4 rows a pair at similarity 0.8 shares no band with probability 4e-6.
    ``growth`` is the width of the size classes of the prefix filter.
    """

    words: int = 4
    percent: int = 80
    bands: int = 24
    rows: int = 4
    batch: int = 24
    miss: float = 1e-6
    growth: float = 1.04

    @property
    def hashes(self) -> int:
        return self.bands * self.rows


def least_matches(compared: int, threshold: float, miss: float) -> int:
    """Smallest number of agreeing values at which a pair is not dropped.

    Posterior tail under Beta(1, 1): P(s >= t | m of n) = P(Binomial(n + 1, t) <= m).
    """
    total = 0.0
    for m in range(compared + 1):
        total += comb(compared + 1, m) * threshold**m * (1 - threshold) ** (compared + 1 - m)
        if total >= miss:
            return m
    return compared


def shingle_sets(batch: pa.RecordBatch, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles of each row as 52-bit numbers, sorted by row, and the rows' bounds."""
    s = flat.Slice(batch.column(1), lower=True)
    start, end, bounds = s.words()
    h = s.hashes(s.prefix(), start, end)
    full, fits = flat.shingles(h, bounds, words)
    doc = np.repeat(np.arange(s.docs, dtype=np.uint64), np.diff(bounds))
    count = np.diff(bounds)
    key = [(doc[fits] << np.uint64(52)) | (full[fits] >> np.uint64(12))]
    for n in range(1, words):  # shorter texts are one shingle
        short = np.flatnonzero(count == n)
        if len(short):
            one = np.zeros(len(short), np.uint64)
            for k in range(n):
                one += h[bounds[short] + k] * flat.MULTIPLIERS[100 + 10 * n + k]
            key.append((short.astype(np.uint64) << np.uint64(52)) | (flat.mix(one) >> np.uint64(12)))
    key = np.unique(np.concatenate(key))
    return key & np.uint64((1 << 52) - 1), np.searchsorted(key, np.arange(s.docs + 1, dtype=np.uint64) << np.uint64(52))


def signatures(values: np.ndarray, bounds: np.ndarray, hashes: int) -> np.ndarray:
    """32-bit MinHash values, one row per set; the row of an empty set is zero."""
    out = np.zeros((len(bounds) - 1, hashes), np.uint32)
    full = np.flatnonzero(np.diff(bounds))
    if len(full):
        mixed = flat.mix(values)
        at = bounds[:-1][full]
        for k in range(hashes):
            out[full, k] = np.minimum.reduceat((mixed * flat.MULTIPLIERS[200 + k]) >> np.uint64(32), at)
    return out


def set_keys(values: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """Two 64-bit sums over each set's shingles, by which equal sets are found."""
    keys = []
    for k in range(2):
        total = np.zeros(len(values) + 1, np.uint64)
        np.cumsum(flat.mix(values * flat.MULTIPLIERS[400 + k]), out=total[1:])
        keys.append((total[bounds[1:]] - total[bounds[:-1]]).view(np.int64))
    return keys


def _signed(p: NearDuplicateParams):
    def run(batches):
        for batch in batches:
            for part in flat.slices(batch, "text"):
                values, bounds = shingle_sets(part, p.words)
                keys = set_keys(values, bounds)
                sig = signatures(values, bounds, p.hashes)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(np.diff(bounds)), pa.array(keys[0]), pa.array(keys[1]), pa.array([x.tobytes() for x in sig], pa.binary())],
                    ["doc_id", "n_shingles", "set_a", "set_b", "signature"],
                )

    return run


def _banded(p: NearDuplicateParams):
    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            sig = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint32).reshape(-1, p.hashes).astype(np.uint64)
            key = np.zeros((len(sig), p.bands), np.uint64)
            for k in range(p.rows):
                key += (sig[:, k :: p.rows] + np.uint64(1)) * flat.MULTIPLIERS[440 + k]
            key = flat.mix(key + np.arange(p.bands, dtype=np.uint64) * flat.MULTIPLIERS[450])
            yield pa.RecordBatch.from_arrays(
                [pa.array(key.ravel().view(np.int64)), pa.array(np.repeat(np.asarray(batch.column(0)), p.bands))], ["bucket", "node"]
            )

    return run


def _posterior(p: NearDuplicateParams):
    steps = [(n, least_matches(n, p.percent / 100, p.miss)) for n in range(p.batch, p.hashes + 1, p.batch)]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            a, b = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint32).reshape(-1, p.hashes) for k in (2, 3))
            alive = np.arange(len(a))
            matches = np.zeros(len(a), np.int64)
            for n, least in steps:
                matches[alive] += (a[alive, n - p.batch : n] == b[alive, n - p.batch : n]).sum(1)
                alive = alive[matches[alive] >= least]
            yield batch.select([0, 1]).take(pa.array(alive))

    return run


def _sets(p: NearDuplicateParams):
    """Shingles of the rows whose text has the asked set; a repeated id may have other texts."""

    def run(batches):
        for batch in batches:
            for part in flat.slices(batch, "text"):
                values, bounds = shingle_sets(part, p.words)
                keys = set_keys(values, bounds)
                right = np.flatnonzero((keys[0] == np.asarray(part.column(2))) & (keys[1] == np.asarray(part.column(3))))
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(values.view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(right)), lists.take(pa.array(right))], ["node", "shingles"])

    return run


def verified_links(nodes: DataFrame, sets: DataFrame, pairs: DataFrame, p: NearDuplicateParams) -> DataFrame:
    """The pairs ``(a, b)`` that survive the posterior bounds and whose full sets are similar."""
    sig = nodes.select("node", "signature")
    with_sig = (
        pairs.join(sig.select(F.col("node").alias("a"), F.col("signature").alias("sa")), "a")
        .join(sig.select(F.col("node").alias("b"), F.col("signature").alias("sb")), "b")
        .select("a", "b", "sa", "sb")
    )
    likely = written(with_sig.mapInArrow(_posterior(p), "a long, b long"), "likely")
    shared = F.size(F.array_intersect("xa", "xb")).cast("long")
    return written(
        likely.join(sets.select(F.col("node").alias("a"), F.col("shingles").alias("xa")), "a")
        .join(sets.select(F.col("node").alias("b"), F.col("shingles").alias("xb")), "b")
        .where(100 * shared >= p.percent * (F.size("xa") + F.size("xb") - shared))
        .select("a", "b"),
        "links",
    )


def _stars(rows: DataFrame) -> DataFrame:
    """Pairs of each bucket's heaviest member with its others, unless links have joined them already."""
    hubs = rows.groupBy("bucket").agg(F.max_by(F.struct("node", "part"), F.struct("weight", "node")).alias("hub"))
    met = rows.join(hubs, "bucket").where("node <> hub.node and part <> hub.part")
    return met.select(F.least("node", "hub.node").alias("a"), F.greatest("node", "hub.node").alias("b")).distinct()


def _open_buckets(buckets: DataFrame, links: DataFrame) -> DataFrame:
    """Members of buckets that links have not yet made one group: ``bucket, node, weight, part, inside``.

    ``inside`` marks the members of the bucket's largest group.
    """
    groups = connected(links)
    placed = buckets.drop("part").join(groups, "node", "left").withColumn("part", F.coalesce("component", "node")).drop("component")
    parts = placed.groupBy("bucket", "part").agg(F.count("*").alias("n"))
    main = parts.groupBy("bucket").agg(F.max_by("part", F.struct("n", "part")).alias("main"), F.count("*").alias("parts")).where("parts > 1")
    return written(placed.join(main, "bucket").select("bucket", "node", "weight", "part", (F.col("part") == F.col("main")).alias("inside")), "open")


def _prefix_pairs(open_buckets: DataFrame, sets: DataFrame, p: NearDuplicateParams) -> DataFrame:
    """Pairs of different groups, one of them open, that may still be linked; every link is among them.

    Shingles are ordered by how many of these nodes hold them. In that order a linked pair shares
    one at places i and j with at least ``need`` shingles from there on in both sets. A node
    thus meets a size class only by the shingles early enough for it, and shingles that no other
    node holds meet nothing.
    """
    t = p.percent
    nodes = open_buckets.groupBy("node").agg(F.any_value("part").alias("part"), F.bool_or(~F.col("inside")).alias("open"))
    some = sets.join(nodes, "node")
    held = some.select("node", F.explode("shingles").alias("s"))
    spread = held.groupBy("s").agg(F.count("*").alias("df")).where("df > 1")
    shared = held.join(spread, "s").groupBy("node").agg(F.array_sort(F.collect_set(F.struct("df", "s"))).alias("shared"))
    # the shingles that it alone holds come first in a node's order
    sized = written(some.select("node", "part", "open", F.size("shingles").alias("n")).join(shared, "node").where(100 * F.size("shared") >= t * F.col("n")), "sized")
    need = lambda x, y: F.ceil(F.lit(t) * (x + y) / F.lit(100 + t) - 1e-9)
    least = F.ceil(F.lit(t) * F.col("n") / 100 - 1e-9)
    size_class = lambda n: F.floor(F.ln(n) / log(p.growth)).cast("int")
    entries = sized.select("node", "part", "open", "n", F.posexplode(F.slice("shared", 1, F.greatest(F.size("shared") - least.cast("int") + 1, F.lit(0)))).alias("k", "x"), F.size("shared").alias("c"))
    entries = entries.select("node", "part", "open", "n", F.col("x.s").alias("s"), (F.col("c") - F.col("k")).alias("from_here"), size_class(F.col("n").cast("double")).alias("own"))
    classes = F.sequence(size_class(least.cast("double")), size_class(F.col("n") * (100 / t) + 1e-6))
    aimed = entries.withColumn("other", F.explode(classes)).where(
        F.col("from_here") >= need(F.col("n"), F.greatest(F.floor(F.pow(F.lit(p.growth), F.col("other")) - 1e-6), least))
    )
    aimed = written(aimed, "prefixes")
    left = aimed.where("open").select(*(F.col(c).alias(f"l_{c}") for c in aimed.columns))
    met = left.join(
        aimed,
        (F.col("l_s") == F.col("s")) & (F.col("l_own") == F.col("other")) & (F.col("l_other") == F.col("own"))
        & (F.col("l_part") != F.col("part"))
        & (F.least("l_from_here", "from_here") >= need(F.col("l_n"), F.col("n"))),
    )
    return met.select(F.least("l_node", "node").alias("a"), F.greatest("l_node", "node").alias("b")).distinct()


def near_duplicate_groups(documents: DataFrame, p: NearDuplicateParams = NearDuplicateParams()) -> DataFrame:
    """One row per input row: ``doc_id, n_shingles, component_id, kept``.

    ``documents`` needs ``doc_id`` and ``text``; other columns are ignored. A null or empty
    text has no shingles and stays alone. A row without ``doc_id`` takes part in no link and
    is kept, with a null component. Rows that repeat a ``doc_id`` are each returned and count
    as one document, linked through the text of any of them. An empty table gives an empty result.
    """
    ship(documents.sparkSession)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    signed = written(
        texts.mapInArrow(_signed(p), "doc_id long, n_shingles long, set_a long, set_b long, signature binary"), "signed"
    )
    known = signed.where("doc_id is not null and n_shingles > 0")
    key = ["set_a", "set_b", "n_shingles"]
    firsts = written(known.groupBy(*key).agg(F.min("doc_id").alias("doc_id")).withColumn("node", F.monotonically_increasing_id()), "firsts")
    members = written(known.select("doc_id", *key).join(firsts.drop("doc_id"), key).select("doc_id", "n_shingles", "node"), "members")
    nodes = written(known.join(firsts, [*key, "doc_id"]).dropDuplicates(["node"]).select("node", "doc_id", "set_a", "set_b", "signature"), "nodes")

    banded = nodes.select("node", "signature").mapInArrow(_banded(p), "bucket long, node long")
    sizes = banded.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1")
    sized = written(banded.join(sizes, "bucket"), "sized")
    weights = sized.groupBy("node").agg(F.sum("size").alias("weight"))
    buckets = written(sized.select("bucket", "node").join(weights, "node").withColumn("part", F.col("node")), "buckets")
    wanted = nodes.join(weights.select("node"), "node", "left_semi").select("doc_id", "node", "set_a", "set_b").hint("merge")
    some = texts.join(wanted, "doc_id").withColumn("same", F.xxhash64("text")).dropDuplicates(["doc_id", "node", "same"])
    sets = written(some.select("node", "text", "set_a", "set_b").mapInArrow(_sets(p), "node long, shingles array<long>"), "sets")
    discard(sized)

    links = verified_links(nodes, sets, _stars(buckets), p)
    first = _open_buckets(buckets, links)
    links = links.unionByName(verified_links(nodes, sets, _stars(first.where("not inside")), p))
    second = _open_buckets(first, links)
    links = links.unionByName(verified_links(nodes, sets, _prefix_pairs(second, sets, p), p))
    # rows that repeat an id hold its texts together
    several = members.groupBy("doc_id").agg(F.min("node").alias("a"), F.max("node").alias("most")).where("a <> most")
    groups = connected(links.unionByName(members.join(several, "doc_id").where("node <> a").select("a", F.col("node").alias("b"))))
    placed = members.join(groups, "node", "left").select("doc_id", "n_shingles", F.coalesce("component", "node").alias("component"))
    names = placed.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    grouped = placed.join(names, "component").select("doc_id", "n_shingles", "component_id")
    alone = signed.where("doc_id is null or n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    discard(nodes, sets, buckets, first, second, firsts)
    return grouped.unionByName(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
