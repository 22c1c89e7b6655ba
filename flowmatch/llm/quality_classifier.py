"""Quality classifier: Bradley-Terry ranking from preference pairs.

A pair says that a row labelled good beats one labelled bad.  The chance of that is the logistic function of the
difference of the two rows' strengths, and a strength is linear in a row's features; so the weights minimise the logistic
loss on differences of features, without intercept.  Features are ``MEASURES`` of the whole text, and its distinct words
hashed into ``BUCKETS``, a text's buckets sharing a weight of one by the root of their number.  Weights are found by
accelerated gradient steps on a bounded sample (at most ``PER_LABEL`` rows of each label, ``PAIRS`` pairs), on the driver.

The cut is a quantile of the sample's strengths, the one that separates its labels best; scores are the logistic
function of the distance from the cut, shifted so that the cut itself scores ``ACCEPT``.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from flowmatch.llm.common import first_by_hash, mapped, pieces, text_bytes
from flowmatch.llm.textstats import SHARES, rule_counts, shares
from flowmatch.llm.tokens import Tokens, batched

PER_LABEL, PAIRS, SLACK, ACCEPT = 6000, 40_000, 0.004, 0.7
BUCKET_BITS, RIDGE, WORD_RIDGE, STEPS = 11, 1e-3, 2e-2, 300
BUCKETS = 1 << BUCKET_BITS
MEASURES = [*SHARES, "repeat_share", "dup_lines", "any_symbol", "any_exclaim"]


def measure(raw: bytes) -> list[float]:
    n, _, symbols, dup, repeat, words, count = rule_counts(raw)
    return [*shares(raw, words, count), repeat / max(1, n), dup / (int(count[10]) + 1), float(symbols > 0), float(count[33] > 0)]


def word_buckets(texts: list[bytes], tokens: Tokens) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (text, bucket), each once, of the words of the texts."""
    rows, buckets, start = [], [], 0
    for run in batched(texts):
        h, size = tokens.of(run)
        owner = np.repeat(np.arange(start, start + len(run)), size)
        word = np.ones(len(h), dtype=bool)
        word[np.cumsum(size) - 1] = False
        own = np.unique(owner[word] << BUCKET_BITS | (h[word] >> np.uint64(64 - BUCKET_BITS)).astype(np.int64))
        rows.append(own >> BUCKET_BITS)
        buckets.append(own & (BUCKETS - 1))
        start += len(run)
    return (np.concatenate(rows), np.concatenate(buckets)) if rows else (np.zeros(0, dtype=np.int64),) * 2


def measured(rows: DataFrame, text_col: str) -> DataFrame:
    """The rows' columns but the text, and their features: m, the measures, and b, a bit for each bucket that a word falls in.

    A null text is the empty one: measures of zero and no bits.
    """
    rest = [c for c in rows.columns if c != text_col]
    schema = T.StructType([*[rows.schema[c] for c in rest], T.StructField("m", T.ArrayType(T.DoubleType())), T.StructField("b", T.BinaryType())])

    def run(batches):
        import pyarrow as pa

        tokens = Tokens()
        for b in pieces(batches, len(rest)):
            texts = text_bytes(b.column(len(rest)))
            bits = np.zeros((len(texts), BUCKETS), dtype=bool)
            bits[word_buckets(texts, tokens)] = True
            packed = [x.tobytes() for x in np.packbits(bits, axis=1)]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(rest)], pa.array([measure(raw) for raw in texts], pa.list_(pa.float64())), pa.array(packed, pa.binary())], names=schema.names)

    return mapped(rows.select(*rest, text_col), run, schema)


def _logistic(x):
    return 1 / (1 + np.exp(-np.clip(x, -50, 50)))


class BradleyTerry:
    """Strengths from features.  Without rows of both labels every row has the same strength and scores 0.5.

    ``measures``: a row each; ``bits``: packed buckets of each; ``good``: the labels.
    """

    def __init__(self, measures: np.ndarray, bits: list[bytes], good: np.ndarray, seed: int = 11):
        width = len(MEASURES)
        measures, good = measures.reshape(-1, width), np.asarray(good, dtype=bool)
        self.fitted = bool(good.any() and not good.all())
        self.mean = measures.mean(axis=0) if len(measures) else np.zeros(width)
        self.spread = np.maximum(measures.std(axis=0), 1e-9) if len(measures) else np.ones(width)
        self.weights, self.words, self.cut = np.zeros(width), np.zeros(BUCKETS), 0.0
        if not self.fitted:
            return
        x = np.unpackbits(np.frombuffer(b"".join(bits), dtype=np.uint8).reshape(len(bits), -1), axis=1).astype(np.float32)
        x /= np.sqrt(np.maximum(1, x.sum(axis=1, keepdims=True)))
        x = np.hstack([self._scaled(measures).astype(np.float32), x])
        ridge = np.r_[np.full(width, RIDGE), np.full(BUCKETS, WORD_RIDGE)].astype(np.float32)
        rng = np.random.default_rng(seed)
        up, down = np.flatnonzero(good), np.flatnonzero(~good)
        a, b = up[rng.integers(len(up), size=PAIRS)], down[rng.integers(len(down), size=PAIRS)]
        n = len(x)

        def slope(w):
            s = x @ w
            wrong = 1 - _logistic(s[a] - s[b])
            pull = np.bincount(a, wrong, n) - np.bincount(b, wrong, n)
            return (pull.astype(np.float32) / PAIRS) @ x - ridge * w

        # The steepest curve of the loss, by power iteration, bounds the step.
        v = rng.standard_normal(x.shape[1]).astype(np.float32)
        for _ in range(12):
            s = x @ v
            d = s[a] - s[b]
            v = ((np.bincount(a, d, n) - np.bincount(b, d, n)).astype(np.float32) / PAIRS) @ x
            most = float(np.linalg.norm(v))
            v /= max(most, 1e-12)
        rate = 1 / (1.1 * most / 4 + float(ridge.max()))
        w = ahead = np.zeros(x.shape[1], dtype=np.float32)
        for k in range(1, STEPS + 1):
            new = ahead + rate * slope(ahead)
            ahead = new + (k - 1) / (k + 2) * (new - w)
            w = new
        self.weights, self.words = w[:width].astype(float), w[width:].astype(float)
        strength = x @ w
        # Quantiles by half percent; the strengths of either label count equally.
        cuts = np.quantile(strength, np.linspace(0.005, 0.995, 199))
        gain = (strength[good, None] >= cuts).mean(axis=0) - (strength[~good, None] >= cuts).mean(axis=0)
        self.cut = float(cuts[int(np.argmax(gain >= gain.max() - SLACK))])  # the lowest quantile that is as good, for clean rows' sake

    def _scaled(self, rows: np.ndarray) -> np.ndarray:
        return np.clip((rows.reshape(-1, len(MEASURES)) - self.mean) / self.spread, -6, 6)

    def score(self, texts: list[bytes], tokens: Tokens) -> np.ndarray:
        if not self.fitted:
            return np.full(len(texts), 0.5)
        row, bucket = word_buckets(texts, tokens)
        of_words = np.bincount(row, self.words[bucket], len(texts)) / np.sqrt(np.maximum(1, np.bincount(row, minlength=len(texts))))
        strength = self._scaled(np.array([measure(raw) for raw in texts], dtype=float)) @ self.weights + of_words
        return _logistic(strength - self.cut + np.log(ACCEPT / (1 - ACCEPT)))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> BradleyTerry:
    """``labels``: id and quality, the rows to learn from and no others.

    Null labels and ids are passed over; of contradicting labels of an id the lower counts; rows of an id that repeats are
    learnt from alike.
    """
    marks = labels.select(F.col(id_col).alias("id"), F.col("quality").alias("q")).where("id is not null and q in (0, 1)").groupBy("id").agg(F.min("q").alias("q"))
    sample = first_by_hash(marks.where("q = 1"), "id", PER_LABEL).unionByName(first_by_hash(marks.where("q = 0"), "id", PER_LABEL))
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).join(F.broadcast(sample), "id")
    # An id may repeat, so the rows are bounded once more.
    seen = measured(rows, "t").orderBy(F.xxhash64("id"), "m", "b").limit(2 * PER_LABEL).collect()
    return BradleyTerry(np.array([r.m for r in seen], dtype=float), [bytes(r.b) for r in seen], np.array([r.q == 1 for r in seen], dtype=bool))


def score(docs: DataFrame, model: BradleyTerry, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) of every row, in one narrow pass.  A null text is the empty one; repeated rows stay; other columns are not read."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("score", T.DoubleType())])

    def run(batches):
        import pyarrow as pa

        tokens = Tokens()
        for b in pieces(batches, 1):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(text_bytes(b.column(1)), tokens))], names=schema.names)

    return mapped(rows, run, schema).withColumnRenamed("id", id_col)


def accepted(docs: DataFrame, model: BradleyTerry, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all their columns, that score at least ``ACCEPT``.  Without labels of both kinds nothing is known, and all stay."""
    at = docs.columns.index(text_col)

    def run(batches):
        import pyarrow as pa

        tokens = Tokens()
        for b in pieces(batches, at):
            yield b.filter(pa.array((model.score(text_bytes(b.column(at)), tokens) >= ACCEPT) | (not model.fitted)))

    return mapped(docs, run, docs.schema)
