"""Quality classifier: ordinal cumulative-link regression on hashed text.

One weight vector is shared by all grades; ordered thresholds cut its score:
P(grade <= k) = sigmoid(threshold_k - w.x). Expected grade and tail probability follow.
Features are the distinct hashed words of a text, their prefixes, and shares of word shapes.

The model is fitted from at most ``sample`` labelled texts (smallest hashes of ``doc_id`` first).
Executors hash them; the driver gets how often each frequent bucket stands in texts of each
grade, screens the buckets, and fetches only the sample's rows over those that stay. So
texts never reach the driver, and what does is bounded by the sample. Scoring is one scan.

Screening: a bucket stays if it is in ``least_share`` of the sample (3 texts at least) and if,
for some threshold between grades, its texts lie on one side of it more than chance gives
(``screen`` standard deviations) and more than a little (``effect`` of one). Without it, the tens of thousands
of neutral words fit noise. The shape features are shares of repeated words, marks and capitals,
some also capped, so that a moderate and an extreme share can weigh differently.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetspark.llm import flat
from facetspark.llm.store import discard, ship, written

LETTERS = np.ones(256, bool)  # separators of words: all ASCII but letters and digits
LETTERS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
UPPER = np.zeros(256, bool)
UPPER[65:91] = True
MARKS = np.zeros(256, bool)
MARKS[list(b"#*$%&|<>!=_~^{}[]\\")] = True


@dataclass(frozen=True)
class OrdinalParams:
    """``grades`` counts the levels, ``keep_grade`` is the least one worth keeping."""

    sample: int = 20_000
    bits: int = 22
    prefix: int = 4
    least_share: float = 0.001
    grades: int = 3
    keep_grade: int = 2
    keep_probability: float = 0.5
    screen: float = 4.0
    effect: float = 0.3
    ridge: float = 5e-5
    rounds: int = 400


def hashed_features(column: pa.Array, bits: int, prefix: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row and bucket of every word and prefix (repeats included), and dense shape shares."""
    plain = flat.Slice(column)
    upper, marks = (np.diff(np.concatenate([[0], np.cumsum(x[plain.buf])])[plain.at]) for x in (UPPER, MARKS))
    s = flat.Slice(column, lower=True)
    start, end, bounds = s.spans(LETTERS)
    sums = s.prefix()
    row = np.repeat(np.arange(s.docs), np.diff(bounds))
    mask = np.uint64((1 << bits) - 1)
    word = s.hashes(sums, start, end) & mask
    long = end - start > prefix
    head = flat.mix(s.hashes(sums, start[long], start[long] + prefix) + np.uint64(7)) & mask
    size = np.maximum(np.diff(s.at), 1)
    count = np.diff(bounds)
    distinct = np.unique((row << bits) | word.astype(np.int64)) >> bits
    again = 1 - np.bincount(distinct, minlength=s.docs) / np.maximum(count, 1)
    often = np.clip(again - 0.15 * np.log1p(count / 60), 0, 1)
    dense = np.column_stack([5 * again, 5 * often, 5 * np.minimum(often, 0.2), 10 * marks / size, 10 * np.minimum(marks / size, 0.05), 5 * upper / size, 5 * np.minimum(upper / size, 0.2), np.log1p(count) / 5])
    return np.concatenate([row, row[long]]), np.concatenate([word, head]).astype(np.int64), dense


@dataclass
class OrdinalModel:
    buckets: np.ndarray
    weights: np.ndarray
    dense: np.ndarray
    thresholds: np.ndarray
    bits: int
    prefix: int

    def scores(self, column: pa.Array) -> np.ndarray:
        row, bucket, dense = hashed_features(column, self.bits, self.prefix)
        slot = np.full(1 << self.bits, -1, np.int32) if not hasattr(self, "_slot") else self._slot
        if not hasattr(self, "_slot"):
            slot[self.buckets] = np.arange(len(self.buckets))
            self._slot = slot
        at = slot[bucket]
        known = at >= 0
        key = np.unique((row[known] << 32) | at[known])
        return dense @ self.dense + np.bincount(key >> 32, self.weights[key & 0xFFFFFFFF], minlength=len(dense))

    def at_least(self, scores: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1, 2, ..."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - scores[:, None], -40, 40)))


def minimise(loss, x: np.ndarray, rounds: int, memory: int = 12, tolerance: float = 1e-9) -> np.ndarray:
    """Limited-memory BFGS with halving steps."""
    value, grad = loss(x)
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(rounds):
        step, alphas = -grad, []
        for s, g in reversed(pairs):
            alphas.append((s @ step) / (s @ g))
            step = step - alphas[-1] * g
        if pairs:
            step = step * ((pairs[-1][0] @ pairs[-1][1]) / (pairs[-1][1] @ pairs[-1][1]))
        for (s, g), alpha in zip(pairs, reversed(alphas), strict=True):
            step = step + s * (alpha - (g @ step) / (s @ g))
        size, slope = 1.0 if pairs else min(1.0, 1 / np.abs(grad).sum()), grad @ step
        while True:
            new_value, new_grad = loss(x + size * step)
            if new_value <= value + 1e-4 * size * slope or size < 1e-10:
                break
            size /= 2
        s, g = size * step, new_grad - grad
        moved = value - new_value
        x, value, grad = x + s, new_value, new_grad
        if s @ g > 1e-12:
            pairs = [*pairs[-memory + 1 :], (s, g)]
        if moved < tolerance * max(1, abs(value)):
            break
    return x


def strong_buckets(counts: np.ndarray, sizes: np.ndarray, p: OrdinalParams) -> np.ndarray:
    """Which buckets stay: ``counts`` has texts by bucket and grade, ``sizes`` those of the sample by grade."""
    n = sizes.sum()
    held = counts.sum(1).astype(float)
    picked = np.zeros(len(counts), bool)
    for level in range(p.grades - 1):
        share = sizes[level + 1 :].sum() / n
        spread = share * (1 - share)
        pull = np.abs(counts[:, level + 1 :].sum(1) - held * share)
        noise = np.sqrt(np.maximum(held * (1 - held / n) * spread, 1e-12))
        picked |= (pull >= p.screen * noise) & (pull >= p.effect * held * np.sqrt(spread))
    return picked & (held >= max(3, p.least_share * n))


def likelihood(row: np.ndarray, col: np.ndarray, features: int, dense: np.ndarray, y: np.ndarray, p: OrdinalParams):
    """Mean negative log-likelihood with a ridge, and its gradient, of (weights, dense weights, first threshold, log gaps)."""
    n, levels = len(y), p.grades - 1
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    i, split = np.arange(n), features + dense.shape[1]

    def loss(x):
        w, d, gap = x[:features], x[features:split], np.exp(x[split + 1 :])
        theta = x[split] + np.concatenate([[0], np.cumsum(gap)])
        score = np.bincount(row, w[col], minlength=n) + dense @ d
        upto = np.concatenate([np.zeros((n, 1)), sig(theta[None, :] - score[:, None]), np.ones((n, 1))], axis=1)
        slope = upto * (1 - upto)
        like = np.maximum(upto[i, y + 1] - upto[i, y], 1e-12)
        g_score = (slope[i, y + 1] - slope[i, y]) / like / n
        g_theta = np.array([(np.where(y == k, -slope[:, k + 1], 0) + np.where(y == k + 1, slope[:, k + 1], 0)) @ (1 / like) / n for k in range(levels)])
        g_gap = np.cumsum(g_theta[::-1])[::-1][1:] * gap
        grad = np.concatenate([np.bincount(col, g_score[row], minlength=features) + p.ridge * w, dense.T @ g_score + p.ridge * d, [g_theta.sum()], g_gap])
        return -np.log(like).mean() + p.ridge / 2 * (w @ w + d @ d), grad

    return loss


def fit_rows(row: np.ndarray, col: np.ndarray, used: np.ndarray, dense: np.ndarray, y: np.ndarray, p: OrdinalParams) -> OrdinalModel:
    """Maximum likelihood with a ridge, by limited-memory quasi-Newton steps; no randomness.

    Text ``row[i]`` has bucket ``used[col[i]]``.
    """
    levels = p.grades - 1
    above = (y[:, None] > np.arange(levels)[None, :]).mean(0).clip(0.01, 0.99)
    theta = np.sort(-np.log(above / (1 - above))) + np.arange(levels) * 1e-3
    gaps = np.log(np.maximum(np.diff(theta), 1e-3))
    start = np.concatenate([np.zeros(len(used) + dense.shape[1]), theta[:1], gaps])
    x = minimise(likelihood(row, col, len(used), dense, y, p), start, p.rounds)
    split = len(used) + dense.shape[1]
    w, d = x[: len(used)], x[len(used) : split]
    theta = x[split] + np.concatenate([[0], np.cumsum(np.exp(x[split + 1 :]))])
    heavy = np.abs(w) > 1e-3
    return OrdinalModel(used[heavy], w[heavy], d, theta, p.bits, p.prefix)


def graded(labels: DataFrame) -> Column:
    """Grade of a labelled text: 0 toxic, 1 poor, 2 clean and well written.

    Insults add up without limit, so the grade that they pull to must be the open lowest one.
    """
    toxic = F.coalesce("toxic", F.lit(0)) == 1
    return F.when(toxic, 0).when(F.col("quality") == 0, 1).when(F.col("quality") == 1, 2).cast("int")


SHAPES = 8
FEATURES = "doc_id long, grade int, digest long, buckets array<int>, shapes array<double>"


def _featured(p: OrdinalParams):
    names = [x.split()[0] for x in FEATURES.split(", ")]

    def run(batches):
        for batch in batches:
            for part in flat.slices(batch, "text"):
                row, bucket, dense = hashed_features(part.column(3), p.bits, p.prefix)
                key = np.unique((row.astype(np.int64) << 32) | bucket)
                at = np.searchsorted(key, np.arange(part.num_rows + 1) << 32).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(at), pa.array((key & 0xFFFFFFFF).astype(np.int32)))
                shapes = pa.ListArray.from_arrays(pa.array((np.arange(part.num_rows + 1) * SHAPES).astype(np.int32)), pa.array(dense.ravel()))
                yield pa.RecordBatch.from_arrays([*part.columns[:3], lists, shapes], names)

    return run


def train(documents: DataFrame, labels: DataFrame, p: OrdinalParams = OrdinalParams(), grade: Column | None = None) -> OrdinalModel:
    """Fit on at most ``p.sample`` labelled texts.

    Labels without a grade or a document are left out; a null or empty text has no words, but
    counts. Labels that repeat an id, and rows that do, are each an example. Without labels the
    model has no weights and accepts every text.
    """
    spark = documents.sparkSession
    ship(spark)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rated = labels.select(F.col("doc_id").cast("long").alias("doc_id"), (graded(labels) if grade is None else grade).alias("grade"))
    rated = rated.where("grade is not null").join(texts.select("doc_id"), "doc_id", "left_semi")
    chosen = written(rated.orderBy(F.xxhash64("doc_id"), "doc_id", "grade").limit(p.sample), "chosen")
    # the sample has p.sample rows of two numbers at most: it goes to the texts
    labelled = texts.join(F.broadcast(chosen), "doc_id").select("doc_id", "grade", F.xxhash64("text").alias("digest"), "text")
    features = written(labelled.mapInArrow(_featured(p), FEATURES), "features")
    if features.count() > p.sample:  # ids with many rows
        features = written(features.orderBy("doc_id", "grade", "digest").limit(p.sample), "features")
    sizes = np.zeros(p.grades, np.int64)
    for r in features.groupBy("grade").count().collect():
        sizes[r["grade"]] = r["count"]
    if not sizes.sum():
        return OrdinalModel(np.zeros(0, np.int64), np.zeros(0), np.zeros(SHAPES), np.full(p.grades - 1, -20.0), p.bits, p.prefix)
    by_grade = [F.count_if(F.col("grade") == g).alias(f"n{g}") for g in range(p.grades)]
    counts = features.select("grade", F.explode("buckets").alias("bucket")).groupBy("bucket").agg(*by_grade)
    frequent = counts.where(sum((F.col(f"n{g}") for g in range(p.grades)), F.lit(0)) >= max(3, p.least_share * sizes.sum())).toArrow()
    picked = strong_buckets(np.column_stack([np.asarray(frequent[f"n{g}"]) for g in range(p.grades)]), sizes, p)
    used = np.sort(np.asarray(frequent["bucket"])[picked]).astype(np.int64)
    held = spark.sparkContext.broadcast(used)  # at most 1 / least_share times the buckets of a text

    def kept(batches):
        for batch in batches:
            lists, buckets = batch.column(3), np.asarray(batch.column(3).flatten())
            row = np.repeat(np.arange(batch.num_rows), np.asarray(lists.value_lengths()))
            at = np.searchsorted(held.value, buckets)
            known = at < len(held.value)
            known[known] = held.value[at[known]] == buckets[known]
            bounds = np.searchsorted(row[known], np.arange(batch.num_rows + 1)).astype(np.int32)
            cut = pa.ListArray.from_arrays(pa.array(bounds), pa.array(at[known].astype(np.int32)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], cut, batch.column(4)], batch.schema.names)

    rows = features.mapInArrow(kept, FEATURES).orderBy("doc_id", "grade", "digest").toArrow().combine_chunks()
    discard(chosen, features)
    lists = rows["buckets"].combine_chunks()
    row = np.repeat(np.arange(len(rows)), np.asarray(lists.value_lengths()))
    dense = np.asarray(rows["shapes"].combine_chunks().flatten()).reshape(-1, SHAPES)
    return fit_rows(row, np.asarray(lists.flatten()), used, dense, np.asarray(rows["grade"]).astype(np.int64), p)


def score_quality(documents: DataFrame, model: OrdinalModel, p: OrdinalParams = OrdinalParams()) -> DataFrame:
    """All columns of ``documents`` plus ``expected_grade``, ``tail_probability``, ``accepted``.

    A null or empty text is scored by the thresholds alone. Rows are judged one by one, so
    repeated rows and rows without ``doc_id`` need no rule; added columns replace columns of
    these names. An empty table gives an empty result; without labels all is accepted.
    """
    ship(documents.sparkSession)
    added = ("expected_grade", "tail_probability", "accepted")
    names = [c for c in documents.columns if c not in added]
    held = documents.sparkSession.sparkContext.broadcast(model)  # bounded by sample and bits
    level, enough = p.keep_grade - 1, p.keep_probability

    def run(batches):
        model = held.value
        for batch in batches:
            for part in flat.slices(batch, "text"):
                tail = model.at_least(model.scores(part.column(part.schema.get_field_index("text"))))
                columns = [pa.array(np.round(tail.sum(1), 9)), pa.array(np.round(tail[:, level], 9)), pa.array(tail[:, level] >= enough)]
                yield pa.RecordBatch.from_arrays([*part.columns, *columns], [*names, *added])

    kinds = dict(documents.dtypes)
    schema = ", ".join([*(f"`{c}` {kinds[c]}" for c in names), "expected_grade double", "tail_probability double", "accepted boolean"])
    return documents.select(*names).mapInArrow(run, schema)
