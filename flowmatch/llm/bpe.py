"""Byte-level BPE encoding and decoding.

Two tiers.  A minimal perfect hash over the vocabulary resolves every pre-token that is itself a vocabulary entry,
one vectorised probe for all distinct pre-tokens of a batch.  The others are merged by rank: a heap of candidate
pairs over bytes held in a doubly linked list, lowest rank first and leftmost among equals, O(n log n) for a pre-token
of n bytes.  The same merge order is what the tiktoken library uses, so ids agree with it.

The vocabulary is of a checked size (``MAX_VOCABULARY`` entries); it travels to the executors in the broadcast that
Spark makes of the function, and each worker sets it up once, for all its tasks.  The work is one narrow pass, with no
shuffle; texts become Python strings a few megabytes at a time, and all that is kept is a memo of at most ``MEMO``
pre-tokens.
"""

from __future__ import annotations

import base64
import hashlib
import pickle
import re
from array import array
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from flowmatch.llm.common import mapped, pieces

MAX_VOCABULARY = 1 << 20
MEMO = 250_000

# The split of public_tokenizers.PATTERN for texts with no character of OTHER, in the syntax of the faster
# re module (there, letters are what \w has besides digits and '_', and \s agrees on what is left).
PLAIN = r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"
OTHER = "[^\x00-\x1b\x20-\x84\x86-\x9f\xa1-\xb1\xb4-\xb8\xba\xbb\xbf-\u024f]"


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    if len(ranks) > MAX_VOCABULARY:
        raise ValueError(f"a vocabulary of {len(ranks)} entries is over the bound of {MAX_VOCABULARY}")
    if missing := [b for b in range(256) if bytes([b]) not in ranks]:
        raise ValueError(f"not a byte-level vocabulary: {len(missing)} single bytes are missing")
    return ranks


def _mixed(h: np.ndarray, seed) -> np.ndarray:
    x = h ^ (np.asarray(seed, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


def _hashes(keys: list[bytes]) -> np.ndarray:
    import xxhash

    h = xxhash.xxh3_64_intdigest
    return np.fromiter((h(k) for k in keys), dtype=np.uint64, count=len(keys))


class PerfectHash:
    """Minimal perfect hash by displaced buckets: n keys fill slots 0..n-1 with no slot left free.

    Keys are dealt into buckets of about four; the fullest bucket first, each looks for the seed that sends all its
    keys to free slots.  A probe hashes the key once, mixes it with its bucket's seed, and compares the key in the slot.
    """

    def __init__(self, keys: list[bytes]):
        n = self.n = len(keys)
        hashes = _hashes(keys)
        if len(np.unique(hashes)) != n:
            raise ValueError("two keys share a 64-bit hash")
        self.seeds = np.zeros(max(1, n // 4), dtype=np.uint64)
        buckets = (hashes % np.uint64(len(self.seeds))).astype(np.int64)
        order = np.argsort(buckets, kind="stable")
        starts = np.searchsorted(buckets[order], np.arange(len(self.seeds) + 1))
        free, slot_of = np.ones(n, dtype=bool), np.empty(n, dtype=np.int64)
        tries = np.arange(1, 4097, dtype=np.uint64)
        for b in np.argsort(-np.diff(starts), kind="stable"):
            members = order[starts[b] : starts[b + 1]]
            if not len(members):
                break
            base = 0
            while True:
                slots = (_mixed(hashes[members][None, :], (tries + np.uint64(base))[: 64 if not base else None, None]) % np.uint64(n)).astype(np.int64)
                good = free[slots].all(axis=1)
                if len(members) > 1:
                    s = np.sort(slots, axis=1)
                    good &= (s[:, 1:] != s[:, :-1]).all(axis=1)
                if good.any():
                    k = int(np.argmax(good))
                    self.seeds[b] = tries[k] + np.uint64(base)
                    free[slots[k]] = False
                    slot_of[members] = slots[k]
                    break
                base += 64 if not base else len(tries)
        self.keys: list[bytes] = [b""] * n
        for i, s in enumerate(slot_of.tolist()):
            self.keys[s] = keys[i]
        self.slot_of = slot_of

    def slots(self, tokens: list[bytes]) -> list[int]:
        """For each token its slot, which holds it if any slot does."""
        if not tokens or not self.n:
            return [0] * len(tokens)
        h = _hashes(tokens)
        return (_mixed(h, self.seeds[(h % np.uint64(len(self.seeds))).astype(np.int64)]) % np.uint64(self.n)).astype(np.int64).tolist()


_held: dict[str, Codec] = {}


def _restored(digest: str, state: bytes) -> Codec:
    """The worker's own codec: set up when the first task brings it, found again by the others."""
    if digest not in _held:
        made = Codec.__new__(Codec)
        made.__dict__.update(pickle.loads(state))
        _held.clear()
        _held[digest] = made
    return _held[digest]


class Codec:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import public_tokenizers

        self.pattern, self.known = pattern, pattern == public_tokenizers.PATTERN  # PLAIN stands for no other pattern
        self.state: tuple[str, bytes] | None = None
        keys = list(ranks)
        self.hash = PerfectHash(keys)
        self.ids = [0] * len(keys)
        for s, k in zip(self.hash.slot_of.tolist(), keys):
            self.ids[s] = ranks[k]
        self.ready = False

    def prepare(self) -> None:
        """Tables derived from the vocabulary, made once in each worker."""
        import regex

        rank_of = dict(zip(self.hash.keys, self.ids))
        self.pairs: dict[int, int] = {}
        for token, rank in rank_of.items():
            for cut in range(1, len(token)):
                a, b = rank_of.get(token[:cut]), rank_of.get(token[cut:])
                if a is not None and b is not None:
                    self.pairs[a << 20 | b] = rank
        self.single = [rank_of[bytes([b])] for b in range(256)]
        self.packed = [array("i", [x]).tobytes() for x in self.ids]
        by_id = {x: k for k, x in rank_of.items()}
        self.pieces = Strings([by_id.get(i, b"") for i in range(max(by_id) + 1)])
        self.digits = Strings([b"%d " % i for i in range(max(by_id) + 1)])
        self.full, self.plain, self.other = regex.compile(self.pattern), re.compile(PLAIN), re.compile(OTHER)
        if not self.known:
            self.plain = self.full
        self.memo: dict[str, bytes] = {}
        self.ready = True

    def __reduce__(self):
        if self.state is None:
            raw = pickle.dumps({"pattern": self.pattern, "known": self.known, "hash": self.hash, "ids": self.ids, "ready": False, "state": None}, protocol=5)
            self.state = hashlib.sha256(raw).hexdigest(), raw
        return _restored, self.state

    def merged(self, token: bytes) -> list[int]:
        """The ids of a pre-token that is no vocabulary entry."""
        rank_of, n = self.pairs.get, len(token)
        part = list(map(self.single.__getitem__, token))
        rank = [rank_of(x << 20 | y, -1) for x, y in zip(part, part[1:])]  # of the pair that starts here, now
        # An entry is a pair's rank and its left position in one number, so the heap's order is rank, then leftmost.
        shift = 8 if n < 256 else 32
        mask = (1 << shift) - 1
        heap = [r << shift | i for i, r in enumerate(rank) if r >= 0]
        heapify(heap)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank.append(-1)
        part.append(0)
        while heap:
            entry = heappop(heap)
            i = entry & mask
            new = entry >> shift
            if rank[i] != new:  # stale: one of the two has been merged since
                continue
            j = after[i]
            part[i], part[j], rank[j] = new, -1, -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                r = rank[i] = rank_of(new << 20 | part[k], -1)
                if r >= 0:
                    heappush(heap, r << shift | i)
            else:
                rank[i] = -1
            h = before[i]
            if h >= 0:
                r = rank[h] = rank_of(part[h] << 20 | new, -1)
                if r >= 0:
                    heappush(heap, r << shift | h)
        return [x for x in part[:n] if x >= 0]

    def learn(self, tokens: set[str]) -> None:
        """Puts the ids of these pre-tokens, four bytes each, into the memo."""
        names = list(tokens)
        raw = [t.encode() for t in names]
        keys, packed, memo, merged = self.hash.keys, self.packed, self.memo, self.merged
        for name, token, slot in zip(names, raw, self.hash.slots(raw)):
            memo[name] = packed[slot] if keys[slot] == token else array("i", merged(token)).tobytes()

    def split(self, text: str) -> list[str]:
        return (self.plain if self.other.search(text) is None else self.full).findall(text)

    def encode(self, text: str) -> np.ndarray:
        """The ids of the text."""
        if not self.ready:
            self.prepare()
        tokens = self.split(text)
        memo = self.memo
        if len(memo) > MEMO:
            memo.clear()
        if fresh := set(tokens).difference(memo):
            self.learn(fresh)
        return np.frombuffer(b"".join(map(memo.__getitem__, tokens)), dtype=np.int32)

    def decode(self, ids: np.ndarray) -> bytes:
        if not self.ready:
            self.prepare()
        return self.pieces.joined(ids)

    def decimal(self, ids: np.ndarray) -> bytes:
        """The ids as decimal text, joined by one space."""
        if not self.ready:
            self.prepare()
        return self.digits.joined(ids)[:-1]


class Strings:
    """Byte strings by number, in one block; joins any sequence of them by one gather."""

    def __init__(self, strings: list[bytes]):
        self.block = np.frombuffer(b"".join(strings), dtype=np.uint8)
        self.sizes = np.fromiter(map(len, strings), dtype=np.int32, count=len(strings))
        self.starts = np.cumsum(self.sizes, dtype=np.int32) - self.sizes

    def joined(self, which: np.ndarray, step: int = 1 << 18) -> bytes:
        if len(which) > step:
            return b"".join(self.joined(which[i : i + step]) for i in range(0, len(which), step))
        sizes = self.sizes[which]
        ends = np.cumsum(sizes, dtype=np.int32)
        total = int(ends[-1]) if len(ends) else 0
        at = np.repeat(self.starts[which] - (ends - sizes), sizes)
        at += np.arange(total, dtype=np.int32)
        return self.block[at].tobytes()


@lru_cache(maxsize=4)
def codec(path: str, pattern: str) -> Codec:
    return Codec(read_ranks(path), pattern)


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Ids of every whole text: (id, ids array<int>).  A null text is the empty one and has no ids."""
    made = codec(path, pattern)

    def run(batches):
        import pyarrow as pa

        for b in pieces(batches, 1):
            ids = [made.encode(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["id", "ids"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    return mapped(rows, run, T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("ids", T.ArrayType(T.IntegerType()))])).withColumnRenamed("id", id_col)


def decode(encoded: DataFrame, path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """Bytes of every row of ids: (id, decoded binary).  Null or no ids give no bytes."""
    made = codec(path, pattern)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            out = [made.decode(np.asarray(x or [], dtype=np.int32)) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["id", "decoded"])

    rows = encoded.select(F.col(id_col).alias("id"), F.col(ids_col).alias("i"))
    return mapped(rows, run, T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("decoded", T.BinaryType())])).withColumnRenamed("id", id_col)


def round_trip(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encodes and decodes in one narrow pass and keeps only digests.

    Per row of ``docs``: the id, n_tokens, ids_sha256 (of the decimal ids joined by one space), decoded_sha256, and
    n_bytes (of the decoded text).  A null text is the empty one; repeated rows stay repeated; other columns are not read.
    """
    made = codec(path, pattern)

    def run(batches):
        import pyarrow as pa

        sha = hashlib.sha256
        for b in pieces(batches, 1):
            n, ids, back, size = [], [], [], []
            for t in b.column(1).to_pylist():
                coded = made.encode(t or "")
                plain = made.decode(coded)
                n.append(len(coded))
                ids.append(sha(made.decimal(coded)).hexdigest())
                back.append(sha(plain).hexdigest())
                size.append(len(plain))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(back), pa.array(size, pa.int64())], names=["id", "n_tokens", "ids_sha256", "decoded_sha256", "n_bytes"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType()), T.StructField("n_bytes", T.LongType())])
    return mapped(rows, run, schema).withColumnRenamed("id", id_col)
