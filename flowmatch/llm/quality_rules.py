"""Quality rules: counts of each whole text, hard rules on them, and an isolation forest on what they say.

The forest learns the shape of good rows: it is grown from a bounded sample of labelled rows (``SAMPLE`` good ones and a
``TAINT`` share of bad ones, so that splits reach their range; ``TREES`` trees of ``PER_TREE`` rows each).  A tree splits a random measure at a random value until a row is alone; a
row that few splits isolate is unlike the sample.  The score is 2^(-mean path / expected path).  The threshold comes
from the scores of *all* labelled rows, as counts by score step and label: the step that separates the labels best
while failing at most ``MAX_LOSS`` of the good ones.

The counts are made in one narrow pass and written once (a few numbers a row), as calibration and verdict both read them.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from flowmatch.llm.common import first_by_hash, mapped, pieces, text_bytes, written
from flowmatch.llm.textstats import SHARES, rule_counts, shares

SAMPLE, TAINT, TREES, PER_TREE, STEPS, MAX_LOSS = 8192, 0.02, 100, 256, 2000, 0.003
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
MEASURES = ["letters", "upper", "symbols", "exclaim", "marked_ends", "adjacent_repeats", "top_word", "repeat_share"]  # none that length alone moves
_AT = [SHARES.index(m) for m in MEASURES[:-1]]


def counted(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, the five counts, and the forest's measures.  A null text has no words; repeated rows stay repeated; other columns are not read."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))

    def run(batches):
        import pyarrow as pa

        for b in pieces(batches, 1):
            out, vec = [], []
            for raw in text_bytes(b.column(1)):
                n, chars, symbols, dup, repeat, words, hist = rule_counts(raw)
                out.append((n, chars, symbols, dup, repeat))
                of = shares(raw, words, hist)
                vec.append([*[of[k] for k in _AT], repeat / max(1, n)])
            cols = np.array(out, dtype=np.int64).reshape(-1, 5).T
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, cols), pa.array(vec, pa.list_(pa.float32()))], names=["id", *COUNTS, "m"])

    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), *[T.StructField(c, T.LongType()) for c in COUNTS], T.StructField("m", T.ArrayType(T.FloatType()))])
    return mapped(rows, run, schema)


class IsolationForest:
    """Trees as flat arrays: at a node the measure, the value, and the left child (the right one follows it)."""

    def __init__(self, rows: np.ndarray, trees: int = TREES, per_tree: int = PER_TREE, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.size = max(2, min(per_tree, len(rows)))
        self.depth = max(1, math.ceil(math.log2(self.size)))
        self.trees = [self._grow(rows[rng.choice(len(rows), self.size, replace=False)], rng) for _ in range(trees)] if len(rows) >= 2 else []

    @staticmethod
    def _expected(n: int) -> float:
        """Mean path of an unsuccessful search in a binary tree of n keys."""
        return 0.0 if n < 2 else 1.0 if n == 2 else 2 * (math.log(n - 1) + 0.5772156649015329) - 2 * (n - 1) / n

    def _grow(self, rows: np.ndarray, rng) -> tuple[np.ndarray, ...]:
        measure, value, child, path = [-1], [0.0], [0], [0.0]
        todo = [(0, rows, 0)]
        while todo:
            at, part, deep = todo.pop()
            low, high = part.min(axis=0), part.max(axis=0)
            wide = np.flatnonzero(high > low)
            if len(part) < 2 or deep >= self.depth or not len(wide):
                child[at], path[at] = at, deep + self._expected(len(part))
                continue
            m = int(rng.choice(wide))
            v = float(rng.uniform(low[m], high[m]))
            left = part[:, m] < v
            measure[at], value[at], child[at] = m, v, len(measure)
            for side in (part[left], part[~left]):
                todo.append((len(measure), side, deep + 1))
                measure.append(-1), value.append(0.0), child.append(0), path.append(0.0)
                if not len(side):  # the value fell on the lowest one
                    todo.pop()
                    child[-1], path[-1] = len(child) - 1, float(deep + 1)
        return np.array(measure), np.array(value), np.array(child), np.array(path)

    def score(self, rows: np.ndarray) -> np.ndarray:
        """Near 1: isolated at once; about 0.5 and below: like the sample."""
        if not self.trees or not len(rows):
            return np.zeros(len(rows))
        total = np.zeros(len(rows))
        line = np.arange(len(rows))
        for measure, value, child, path in self.trees:
            at = np.zeros(len(rows), dtype=np.int64)
            for _ in range(self.depth):
                inner = measure[at] >= 0
                at = np.where(inner, child[at] + (rows[line, measure[at]] >= value[at]), at)
            total += path[at]
        return 2.0 ** (-total / len(self.trees) / self._expected(self.size))


def _matrix(column) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1).astype(np.float64) if len(column) else np.zeros((0, len(MEASURES)))


def anomaly(stats: DataFrame, model: IsolationForest) -> DataFrame:
    """The rows with the forest's score of their measures, 0 if there is no forest."""
    schema = T.StructType([*stats.schema.fields, T.StructField("anomaly", T.DoubleType())])

    def run(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(model.score(_matrix(b.column(b.schema.get_field_index("m")))))], names=schema.names)

    return mapped(stats, run, schema)


def threshold(steps: list[tuple[int, int, int]], max_loss: float = MAX_LOSS) -> float:
    """From (score step, good rows, bad rows): the score from which rows fail; over 1 (none fail) without labels of both kinds."""
    good, bad = sum(g for _, g, _ in steps), sum(b for _, _, b in steps)
    best, cut, lost, caught = 0.0, 1.01, 0, 0
    for step, g, b in sorted(steps, reverse=True):
        lost, caught = lost + g, caught + b
        if good and bad and lost <= max_loss * good and (gain := caught / bad - lost / good) > best:
            best, cut = gain, step / STEPS
    return cut


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: counts, anomaly, base_failed and kept.

    base_failed: under 50 words, or over half of them in repeated windows of three.  kept: not base_failed and an anomaly
    score under the calibrated threshold.  Null texts fail.  Repeated ids are scored row by row; labels of a repeated id
    count as bad if one of them is.  Without labels of both kinds the forest fails nothing.
    """
    stats = written(counted(docs, id_col, text_col), "rule-counts")
    marks = labels.select(F.col(id_col).alias("id"), F.col("quality").alias("q")).where("id is not null and q is not null").groupBy("id").agg(F.min("q").alias("q"))
    usable = (F.col("n_words") >= 50) & (100 * F.col("n_repeat_words") <= 50 * F.col("n_words"))
    sample = first_by_hash(marks.where("q = 1"), "id", SAMPLE).unionByName(first_by_hash(marks.where("q <> 1"), "id", math.ceil(TAINT * SAMPLE * 2)))
    of = stats.where(usable).join(F.broadcast(sample), "id").orderBy(F.xxhash64("id"), "id").select("m", "q").limit(2 * SAMPLE).collect()
    good, bad = [r.m for r in of if r.q == 1], [r.m for r in of if r.q != 1]
    rows = np.array([*good, *bad[: math.ceil(TAINT * len(good))]], dtype=np.float64).reshape(-1, len(MEASURES))
    scored = anomaly(stats, IsolationForest(rows)).drop("m")
    steps = scored.where(usable).join(marks, "id").groupBy(F.floor(F.col("anomaly") * STEPS).alias("s")).agg(F.sum((F.col("q") == 1).cast("long")).alias("g"), F.sum((F.col("q") != 1).cast("long")).alias("b"))
    cut = threshold([(r.s, r.g, r.b) for r in steps.collect()])
    return scored.select(F.col("id").alias(id_col), *COUNTS, "anomaly", (~usable).alias("base_failed"), (usable & (F.col("anomaly") < F.lit(cut))).alias("kept"))


def oracle() -> str:
    """DuckDB SQL for the counts and base_failed."""
    return r"""
with raw as (select doc_id, coalesce(text, '') as t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
lines as (select doc_id, count(*) - count(distinct line) as n_dup_lines from (select doc_id, unnest(string_split(t, chr(10))) as line from raw) where regexp_matches(line, '[^\x20\x09-\x0D]') group by doc_id),
words as (select doc_id, generate_subscripts(w, 1) as i, unnest(w) as word from raw),
three as (select doc_id, i, word as a, lead(word) over w as b, lead(word, 2) over w as c from words window w as (partition by doc_id order by i)),
often as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, a, b, c) as n from three where c is not null) where n > 1),
hit as (select doc_id, count(distinct i + k) as n_repeat_words from often, (select unnest([0, 1, 2]) as k) group by doc_id)
select doc_id, len(w)::bigint as n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::bigint as word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::bigint as n_symbols,
       coalesce(n_dup_lines, 0)::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words, len(w) < 50 or 100 * coalesce(n_repeat_words, 0) > 50 * len(w) as base_failed
from raw left join lines using (doc_id) left join hit using (doc_id)"""
