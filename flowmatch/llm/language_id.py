"""Language ID by string kernels.

The kernel of two texts is the number of character 1-, 2- and 3-grams present in both (presence, not counts), over the
geometric mean of the numbers present in either: the blended-spectrum presence kernel, normalised.  Nystroem: texts are
mapped by their kernels with a few landmark texts, whitened by the landmarks' own kernel matrix; one-versus-rest kernel
ridge regression is then a small linear solve, with targets 0 and 1.  Scoring a batch is two matrix products: presence
of the landmarks' grams by the landmark matrix, then the weights.

Characters are those of the lower-cased text: every letter is itself, and any run of anything else is one symbol; so a gram
is a number of three code points of 21 bits, and nothing is hashed or left out.  Every language is learnt.  What is learnt from is bounded:
``PER_CLASS`` texts of each language, fewer where more than ``SAMPLE`` texts or ``SAMPLE_BYTES`` bytes would come together,
but one at least; texts of up to ``USUAL_BYTES`` come first, and each is taken whole.  ``LANDMARKS`` of them, and one of
each language at least, are landmarks.
"""

from __future__ import annotations

from functools import cache

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F, types as T

from flowmatch.llm.common import mapped, pieces

PER_CLASS, SAMPLE, LANDMARKS, RIDGE, SALTS = 320, 20_480, 256, 1e-2, 16
SAMPLE_BYTES, USUAL_BYTES = 32 << 20, 32 << 10
HELD, LOW, MARGIN = 5, 0.001, 0.6  # every so many texts of a language are held back; the quantile of their scores, and the part of it, that a row must reach
POINT, OTHER = 21, 1  # bits of a code point; the symbol of what is no letter, itself the code point of none
UNKNOWN = "und"


def has_letter(text: str | None) -> bool:
    return bool(text) and (any(map(str.isalpha, text[:200])) or any(map(str.isalpha, text)))


@cache
def _symbols() -> np.ndarray:
    """Of every code point: itself if it is a letter's, else ``OTHER``."""
    return np.array([k if chr(k).isalpha() else OTHER for k in range(0x110000)], dtype=np.int32)


def grams(text: str) -> np.ndarray:
    """The sorted numbers of the grams present in a text."""
    x = _symbols()[np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    keep = np.ones(len(x), dtype=bool)
    keep[1:] = (x[1:] != OTHER) | (x[:-1] != OTHER)
    x = x[keep].astype(np.int64)
    two = x[:-1] << POINT | x[1:]
    return np.concatenate([np.unique(x), np.unique(two), np.unique(two[:-1] << POINT | x[2:])])  # no symbol is 0, so longer grams are larger


class Nystroem:
    def __init__(self, texts: list[str], langs: list[str]):
        self.langs, self.least = sorted(set(langs)), 0.0
        if not texts:
            return
        found = [grams(t) for t in texts]
        # Landmarks go round the languages, the richest texts first, so that each language has its share.
        rank: dict[str, int] = {}
        order = []
        for i in sorted(range(len(texts)), key=lambda i: -len(found[i])):
            rank[langs[i]] = rank.get(langs[i], 0) + 1
            order.append((rank[langs[i]], langs[i], i))
        marks = [i for *_, i in sorted(order)][: max(LANDMARKS, len(self.langs))]
        # Of each gram of the landmarks, in order: which landmarks have it.
        have = np.concatenate([found[i] for i in marks])
        owner = np.repeat(np.arange(len(marks), dtype=np.int32), [len(found[i]) for i in marks])
        order = np.argsort(have, kind="stable")
        self.vocabulary, first = np.unique(have[order], return_index=True)
        self.owner, self.first = owner[order], np.r_[first, len(have)]
        self.norm = np.sqrt([max(1, len(found[i])) for i in marks])
        values, vectors = np.linalg.eigh(self._kernel([found[i] for i in marks]))
        good = values > 1e-6 * values.max()
        whiten = vectors[:, good] / np.sqrt(values[good])
        mapped = self._kernel(found) @ whiten
        y = (np.array(langs)[:, None] == np.array(self.langs)[None, :]).astype(np.float64)
        # Languages weigh alike, whatever their share of the sample.
        weight = (y / y.sum(axis=0)).sum(axis=1) * len(y) / len(self.langs)
        left = (mapped * weight[:, None]).T @ mapped + RIDGE * len(y) / 100 * np.eye(mapped.shape[1])
        self.weights = (whiten @ np.linalg.solve(left, (mapped * weight[:, None]).T @ y))

    def _kernel(self, found: list[np.ndarray]) -> np.ndarray:
        """Kernels of the texts, given by their grams, with the landmarks."""
        out = np.empty((len(found), len(self.norm)))
        for k, g in enumerate(found):
            at = np.minimum(np.searchsorted(self.vocabulary, g), len(self.vocabulary) - 1)
            at = at[self.vocabulary[at] == g] if len(self.vocabulary) else at[:0]
            n = self.first[at + 1] - self.first[at]
            owners = self.owner[np.repeat(self.first[at] - np.cumsum(n) + n, n) + np.arange(n.sum())]
            out[k] = np.bincount(owners, minlength=len(self.norm)) / (self.norm * np.sqrt(max(1, len(g))))
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Language and score of each text; the score is the winning regression's value, held to 0..1, and 0 for ``und``."""
        names, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
        some = [i for i, t in enumerate(texts) if has_letter(t)] if self.langs else []
        for start in range(0, len(some), 64):
            part = some[start : start + 64]
            values = self._kernel([grams(texts[i]) for i in part]) @ self.weights
            best = values.argmax(axis=1)
            for i, k, v in zip(part, best.tolist(), values.max(axis=1).tolist()):
                names[i], scores[i] = self.langs[k], min(1.0, max(0.0, v))
        return names, scores


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Nystroem:
    """``docs``: the rows to learn from and no others; those with a null text or language are passed over.

    The sample: of every language, in each of ``SALTS`` hashed parts, the rows that hash lowest.  So no task sorts a
    language's rows together, however many they are.  What comes to the driver is at most ``SAMPLE_BYTES`` and one text a
    language.  Of rows that repeat an id and a language the least text is taken; a null id is a row like others.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"), F.col(lang_col).cast("string").alias("l")).where("t is not null and l is not null")
    n = max(1, rows.select("l").distinct().count())
    each = max(1, min(PER_CLASS, SAMPLE // n))
    salt = F.pmod(F.xxhash64("id", F.lit(3)), F.lit(SALTS))
    order, again = (Window.partitionBy(*by).orderBy("long", "h", "id") for by in (("l", "s"), ("l",)))
    size = F.octet_length("t")
    picked = (
        rows.select("id", "l", salt.alias("s"), F.xxhash64("id", F.lit(5)).alias("h"), size.alias("size"), (size > USUAL_BYTES).alias("long"))
        .withColumn("k", F.row_number().over(order)).where(F.col("k") <= max(1, each // SALTS))
        .withColumn("k", F.row_number().over(again)).withColumn("before", F.sum("size").over(again.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size"))
        .where((F.col("k") <= each) & (F.col("before") <= SAMPLE_BYTES // n)).select("id", "l")
    )
    named = picked.distinct().select(F.col("id").alias("i"), F.col("l").alias("m"))
    sample = rows.join(F.broadcast(named), F.col("id").eqNullSafe(F.col("i")) & (F.col("l") == F.col("m"))).groupBy("id", "l").agg(F.min("t").alias("t")).orderBy(F.xxhash64("id"), "t").collect()
    return calibrated([r.t for r in sample], [r.l for r in sample])


def calibrated(texts: list[str], langs: list[str]) -> Nystroem:
    """The model of all the texts; ``least`` is the score that :func:`identified` asks for, from texts held back from a model of the others.

    Only held-back texts named rightly count, so that mislabelled ones do not lower it.  Without any it is 0.
    """
    model, seen, held = Nystroem(texts, langs), {}, []
    for t, lang in zip(texts, langs):
        seen[lang] = seen.get(lang, 0) + 1
        held.append(seen[lang] % HELD == 0)
    if any(held):
        others = Nystroem([t for t, h in zip(texts, held) if not h], [x for x, h in zip(langs, held) if not h])
        back = [(t, x) for t, x, h in zip(texts, langs, held) if h]
        names, scores = others.predict([t for t, _ in back])
        right = [v for n, v, (_, x) in zip(names, scores, back) if n == x]
        model.least = MARGIN * float(np.quantile(right, LOW)) if right else 0.0
    return model


def predict(docs: DataFrame, model: Nystroem, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score) of every row, in one narrow pass.  ``und`` for a text that is null or has no letter, or if nothing was learnt."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches):
        import pyarrow as pa

        for b in pieces(batches, 1):
            names, scores = model.predict(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.string()), pa.array(scores)], names=schema.names)

    return mapped(rows, run, schema).withColumnRenamed("id", id_col)


def identified(docs: DataFrame, model: Nystroem, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all their columns, that are in one of the learnt languages: those not ``und`` whose score is as high as held-back texts' are."""
    at = docs.columns.index(text_col)

    def run(batches):
        import pyarrow as pa

        for b in pieces(batches, at):
            names, scores = model.predict(b.column(at).to_pylist())
            yield b.filter(pa.array([n != UNKNOWN and v >= model.least for n, v in zip(names, scores.tolist())], pa.bool_()))

    return mapped(docs, run, docs.schema)
