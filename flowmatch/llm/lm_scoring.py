"""Language-model scoring with a log-frequency Bloom filter.

Tokens are the words of the text with A-Z lower-cased, then one end.  They are known by 64-bit hashes, made for whole
blocks of text at once; a bigram is known by a hash of its two.

*One round trip.*  Texts are dealt into chunks of about ``CHUNK`` bytes.  A chunk asks, once each, for its distinct words
and bigrams, and says how often its own training texts have them.  Keys are routed by hash to blocks: as many as the
tokens of the corpus need, so a block's size does not grow with it, and hot keys count once a chunk.  A block adds up
what the chunks say, which gives exact counts of every word, builds its part of the filter, probes it for what was asked,
and answers each chunk in the order of its keys.  Keys travel sorted and packed, answers as packed numbers without keys.

*The filter.*  Every bigram that occurs ``LEAST`` times or more in training enters it, at any size of corpus, with its count
quantised to the lower of the edges 1, 1.41, 2, 2.83, ...: a bigram of level n is entered as (bigram, 0) to (bigram, n), and
its level is read back by probing until an entry is missing.  The filter grows with the corpus, so it has no proven bound
and is not broadcast: each block's bits stay in the task that probes them.

*Probabilities.*  P1 is the smoothed unigram share of the base score, from exact counts.  After a word seen k times the next
one has ``SHARE`` of its filtered count over k and the rest of P1; after unseen words, and for the first token, P1 stands.
Counts are quantised downwards and rare bigrams are left out, so the sum over all next words stays at or under 1.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F, types as T

from flowmatch.llm.common import text_bytes, trim, written
from flowmatch.llm.tokens import Tokens, batched, mix

LEAST, SHARE = 2, 0.3
BITS, PROBES, SLICE = 14, 8, 1 << 18
CHUNK, BLOCK_BYTES = 8 << 20, 12 << 20  # bytes of text in a chunk; bytes of text whose tokens make a block
_U = np.uint64


def pairs_of(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mix(mix(first * _U(0x9FB21C651E98DF25) + second) ^ _U(0xA0761D6478BD642F))


def followers(sizes: np.ndarray) -> np.ndarray:
    """Positions of the tokens that have another of the same text before them."""
    inner = np.ones(int(sizes.sum()), dtype=bool)
    inner[np.cumsum(sizes) - sizes] = False
    return np.flatnonzero(inner)


def level_of(counts: np.ndarray) -> np.ndarray:
    """The highest level whose edge a count reaches; -1 under ``LEAST``."""
    return np.where(counts >= LEAST, np.floor(2 * np.log2(np.maximum(counts, 1)) + 1e-9), -1).astype(np.int64)


def edge(level):
    """The least whole count of a level; 0 of what is absent."""
    return np.where(np.asarray(level) < 0, 0, np.ceil(2.0 ** (np.asarray(level) / 2) - 1e-6))


class Bloom:
    """A Bloom filter of (key, level) entries, sized for them."""

    def __init__(self, keys: np.ndarray, levels: np.ndarray):
        self.size = max(64, int((levels + 1).sum()) * BITS)
        bits = np.zeros(self.size, dtype=bool)
        for k in range(int(levels.max(initial=-1)) + 1):
            own = keys[levels >= k]
            for start in range(0, len(own), SLICE):
                bits[self._places(own[start : start + SLICE], k).ravel()] = True
        self.bits = np.packbits(bits, bitorder="little")

    def _places(self, keys: np.ndarray, level: int) -> np.ndarray:
        g = mix(mix(keys + _U(level * 0xD1B54A32D192ED03 & (1 << 64) - 1)))
        step = (g >> _U(32)) | _U(1)
        return (((g & _U(0xFFFFFFFF))[:, None] + step[:, None] * np.arange(PROBES, dtype=np.uint64)) % _U(self.size)).astype(np.int64)

    def level(self, keys: np.ndarray) -> np.ndarray:
        """Of each key the highest level up to which all are present, -1 if not even the first is."""
        out = np.full(len(keys), -1, dtype=np.int64)
        for start in range(0, len(keys), SLICE):
            live, k = np.arange(start, min(len(keys), start + SLICE)), 0
            while len(live):
                places = self._places(keys[live], k)
                for p in range(PROBES):
                    at = places[:, p]
                    found = (self.bits[at >> 3] >> (at & 7) & 1).astype(bool)
                    live, places = live[found], places[found]
                out[live] = k
                k += 1
        return out


def _block(keys: np.ndarray, n: int) -> np.ndarray:
    """The block, of ``n``, of well-mixed keys: by their upper half, so that sorted keys have sorted blocks."""
    return ((keys >> _U(32)) * _U(n) >> _U(32)).astype(np.int64)


class Chunk:
    """Tokens of a chunk's texts, its distinct words and bigrams in order, and where each token's are among them."""

    def __init__(self, texts: list[bytes]):
        tokens, parts = Tokens(), [[], []]
        for run in batched(texts):
            for to, x in zip(parts, tokens.of(run)):
                to.append(x)
        h, self.sizes = np.concatenate(parts[0]), np.concatenate(parts[1])
        self.after = followers(self.sizes)
        self.pairs, self.pair_at = np.unique(pairs_of(h[self.after - 1], h[self.after]), return_inverse=True)
        self.words, self.word_at = np.unique(h, return_inverse=True)


def _texts(table) -> list[bytes]:
    return text_bytes(table.column("t").combine_chunks())


_ASK = T.StructType([T.StructField("chunk", T.LongType()), T.StructField("block", T.LongType()), *[T.StructField(c, T.BinaryType()) for c in ("words", "seen", "pairs", "pair_seen")]])
_ANSWER = T.StructType([T.StructField("chunk", T.LongType()), T.StructField("block", T.LongType()), T.StructField("counts", T.BinaryType()), T.StructField("levels", T.BinaryType()), T.StructField("total", T.LongType()), T.StructField("distinct", T.LongType())])


def _asked(n_blocks: int):
    """What a chunk asks: a row per block, keys packed and sorted; of bigrams the lower half of the key, as the block tells the rest."""

    def ask(table):
        import pyarrow as pa

        made = Chunk(_texts(table))
        train = np.repeat(table.column("train").to_numpy(zero_copy_only=False).astype(bool), made.sizes)
        seen = np.bincount(made.word_at[train], minlength=len(made.words)).astype(np.uint32)
        pair_seen = np.bincount(made.pair_at[train[made.after]], minlength=len(made.pairs)).astype(np.uint32)
        cut = np.arange(n_blocks + 1)
        w, p = (np.searchsorted(_block(keys, n_blocks), cut) for keys in (made.words, made.pairs))
        low = (made.pairs & _U(0xFFFFFFFF)).astype(np.uint32)
        hit = np.flatnonzero((np.diff(w) > 0) | (np.diff(p) > 0))
        packed = lambda x, ends: pa.array([x[ends[k] : ends[k + 1]].tobytes() for k in hit], pa.binary())
        out = [pa.array(np.full(len(hit), table.column("chunk")[0].as_py(), dtype=np.int64)), pa.array(hit.astype(np.int64)), packed(made.words, w), packed(seen, w), packed(low, p), packed(pair_seen, p)]
        del made, train
        trim()
        return pa.table(out, names=_ASK.names)

    return ask


def _summed(table, keys: str, seen: str, kind) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[int]]:
    """Distinct keys that a block's rows ask for, their counts, where each asked key is among them, and each row's number of keys."""
    own, n = ([np.frombuffer(x, dtype=d) for x in table.column(c).to_pylist()] for c, d in ((keys, kind), (seen, np.uint32)))
    every, at = np.unique(np.concatenate(own), return_inverse=True)
    return every, np.bincount(at, weights=np.concatenate(n), minlength=len(every)).astype(np.int64), at, [len(x) for x in own]


def _answered(table):
    """A block's answers to the chunks: exact counts of words, levels of bigrams (0: absent) by probes of the block's filter."""
    import pyarrow as pa

    words, counts, word_at, word_n = _summed(table, "words", "seen", np.uint64)
    low, pair_counts, pair_at, pair_n = _summed(table, "pairs", "pair_seen", np.uint32)
    keys, level = low.astype(np.uint64), level_of(pair_counts)
    bloom = Bloom(keys[level >= 0], level[level >= 0])
    levels = (bloom.level(keys) + 1).astype(np.uint8)[pair_at]
    counts_of = counts[word_at]
    cut = lambda x, n: pa.array([y.tobytes() for y in np.split(x, np.cumsum(n)[:-1])], pa.binary())
    rows = table.num_rows
    first = lambda x: pa.array([x] + [0] * (rows - 1), pa.int64())
    return pa.table([table.column("chunk"), table.column("block"), cut(counts_of, word_n), cut(levels, pair_n), first(int(counts.sum())), first(int((counts > 0).sum()))], names=_ANSWER.names)


def base_share(counts: np.ndarray, total: int, distinct: int) -> np.ndarray:
    return (counts + 0.5) / (total + 0.5 * (distinct + 1))


def _given(total: int, distinct: int, names: list[str]):
    def give(texts_of, answer):
        import pyarrow as pa

        if not texts_of.num_rows:
            return pa.table([pa.array([], f) for f in (texts_of.schema.field("id").type, pa.int64(), pa.int64(), pa.float64(), pa.float64())], names=names)
        answer = answer.sort_by("block")
        made = Chunk(_texts(texts_of))
        counts = np.frombuffer(b"".join(answer.column("counts").to_pylist()), dtype=np.int64)
        levels = np.frombuffer(b"".join(answer.column("levels").to_pylist()), dtype=np.uint8).astype(np.int64) - 1
        if len(counts) != len(made.words) or len(levels) != len(made.pairs):
            raise ValueError("a chunk has other texts than it asked for: write the documents first if their rows can change places")
        c = counts[made.word_at]
        p1 = base_share(c, total, distinct)
        p = p1.copy()
        k = c[made.after - 1]
        q = np.minimum(edge(levels)[made.pair_at], np.minimum(k, c[made.after]))
        p[made.after] = np.where(k > 0, (1 - SHARE) * p1[made.after] + SHARE * q / np.maximum(k, 1), p1[made.after])
        first = np.cumsum(made.sizes) - made.sizes
        sums = [np.add.reduceat(x, first) for x in ((c > 0).astype(np.int64), np.log10(p1), np.log10(p))]
        out = pa.table([texts_of.column("id"), pa.array(made.sizes.astype(np.int64)), *map(pa.array, sums)], names=names)
        del made, c, p1, p, k, q, sums, counts, levels
        trim()
        return out

    return give


def scored(docs: DataFrame, training: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: the id, n_tokens, n_known, train_tokens, base_score, score; learnt from the rows where ``training`` holds.

    A null text is the empty one: a single end; a null ``training`` is none.  Without training rows every probability is
    that of a token never seen.  Rows that repeat, even in all columns, are dealt by their place, so no chunk gets them
    all; places must be the same when read twice, so ``docs`` is a table or written before.  Other columns are not read.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("t"), F.coalesce(training, F.lit(False)).alias("train"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0)).alias("n"), F.count("*").alias("rows")).first()
    volume = size.n + 16 * size.rows
    chunks, blocks = max(1, math.ceil(volume / CHUNK)), max(1, math.ceil(volume / BLOCK_BYTES))
    dealt = rows.withColumn("chunk", F.pmod(F.xxhash64("id", F.monotonically_increasing_id()), F.lit(chunks)))
    parts = max(chunks, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = dealt.repartition(parts, "chunk")
    asked = dealt.groupBy("chunk").applyInArrow(_asked(blocks), _ASK)
    answers = written(asked.groupBy("block").applyInArrow(_answered, _ANSWER), "lm-answers")
    sums = answers.agg(F.coalesce(F.sum("total"), F.lit(0)).alias("n"), F.coalesce(F.sum("distinct"), F.lit(0)).alias("v")).first()
    out = T.StructType([rows.schema["id"], T.StructField("n_tokens", T.LongType()), T.StructField("n_known", T.LongType()), T.StructField("base_score", T.DoubleType()), T.StructField("score", T.DoubleType())])
    found = dealt.groupBy("chunk").cogroup(answers.select("chunk", "block", "counts", "levels").groupBy("chunk")).applyInArrow(_given(sums.n, sums.v, out.names), out)
    return found.select(F.col("id").alias(id_col), "n_tokens", "n_known", F.lit(sums.n).cast("long").alias("train_tokens"), "base_score", "score")


def oracle() -> str:
    """DuckDB SQL for all columns of the query but the model's score; training are the rows whose CRC-32 of the id, as text, modulo 5 is not 1."""
    return r"""
with recursive bits(i, c, k) as (select range::bigint, range::bigint, 0 from range(256) union all select i, case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end, k + 1 from bits where k < 8),
crc as materialized (select list(c order by i) as tbl from bits where k = 8),
docs as materialized (select doc_id, xor(list_reduce(list_prepend(4294967295::bigint, list_transform(regexp_extract_all(hex(encode(coalesce(doc_id::varchar, ''))), '..'), lambda b: ('0x' || b)::bigint)),
   lambda a, b: xor(a >> 8, tbl[(xor(a, b) & 255) + 1])), 4294967295) % 5 = 1 as held_out,
   list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), ' ') as w from documents, crc),
tokens as materialized (select doc_id, held_out, unnest(w) as token from docs),
counts as materialized (select token, count(*) as c from tokens where not held_out group by token),
sums as (select coalesce(sum(c), 0)::bigint as n, count(*) as v from counts)
select doc_id, held_out, count(*) as n_tokens, count(c) as n_known, any_value(n) as train_tokens, round(sum(log10((coalesce(c, 0) + 0.5) / (n + 0.5 * (v + 1)))), 3) as base_score
from tokens left join counts using (token), sums group by doc_id, held_out"""
