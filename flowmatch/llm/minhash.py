"""Near-duplicate documents by DartMinHash signatures.

A document is a weighted set of shingles of five words; a shingle weighs as often as the document has it (or one, by
parameter), and similarity is the weighted Jaccard one: the sum of lesser weights over the sum of greater ones.  Darts are thrown at the plane of (weight, rank) of every
element: a Poisson process of unit rate, drawn from hashes of element and dart number, the same in every document that
has the element.  The darts under an element's weight are the document's; each is sent to one of ``K`` coordinates by
hash, and the earliest of a coordinate is its signature there.  Two documents share a coordinate with the chance that is
their weighted Jaccard similarity, and a document of n elements costs O(n + K log K), not O(n K).

Bands of ``ROWS`` coordinates are joined.  With 30 bands of 5 a pair of similarity 0.8 meets in one with a chance over
0.99999.  Links are confirmed exactly, on the weighted sets of the two texts.  Copies of the same words collapse first.

Groups: in a band's bucket every member is tested against the least one, not against all.  What these links connect
needs no further test; in buckets that still hold different classes, pairs of *different* classes are tested, all of
them: in small buckets as rows, in large ones within tasks that hold two tiles of the bucket and return links only.  So
no link that the bands offer is lost, and no pair of a large group becomes a row.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from flowmatch.llm.common import by_ids, dropped, mapped, pieces, text_bytes, written
from flowmatch.llm.components import components

SHINGLE, SIMILAR, BANDS, ROWS = 5, 0.8, 30, 5
SMALL, TILE, TILE_BYTES = 16, 1024, 24 << 20  # members of a bucket compared as pairs; rows of a tile; bytes of a tile's bits
K = BANDS * ROWS
_U = np.uint64
_STEP = 0x5851F42D4C957F2D | 1


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class Shingler:
    """Hashes of runs of words, from running sums of (random number of the byte) * step^position over 64 bits."""

    def __init__(self):
        self.byte = _mix(np.arange(1, 257, dtype=np.uint64) * _U(0x9E3779B97F4A7C15))
        self.power = self.inverse = np.ones(1, dtype=np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.power) < n:
            n = 1 << n.bit_length()
            with np.errstate(over="ignore"):
                self.power = np.cumprod(np.r_[_U(1), np.full(n - 1, _STEP, dtype=np.uint64)], dtype=np.uint64)
                self.inverse = np.cumprod(np.r_[_U(1), np.full(n - 1, pow(_STEP, -1, 1 << 64), dtype=np.uint64)], dtype=np.uint64)

    def hashes(self, words: list[bytes]) -> np.ndarray:
        """One for each window of five words, in order; a shorter text is one window; no words, none."""
        if not words:
            return np.zeros(0, dtype=np.uint64)
        raw = np.frombuffer(b" ".join(words), dtype=np.uint8)
        self._powers(len(raw))
        sums = np.zeros(len(raw) + 1, dtype=np.uint64)
        np.cumsum(self.byte[raw] * self.power[: len(raw)], out=sums[1:])
        gaps = np.flatnonzero(raw == 32)
        starts, ends = np.r_[0, gaps + 1], np.r_[gaps, len(raw)]
        w = min(SHINGLE, len(words))
        starts, ends = starts[: len(starts) - w + 1], ends[w - 1 :]
        return _mix((sums[ends] - sums[starts]) * self.inverse[starts] + (ends - starts).astype(np.uint64))

    def set(self, raw: bytes, weights: str) -> np.ndarray:
        """Sorted numbers of which two texts share as many as their common weight: with "count" one for each time a shingle occurs."""
        h = self.hashes(raw.split())
        if weights == "set":
            return np.unique(h)
        h.sort()
        nth = np.arange(len(h))
        again = np.zeros(len(h), dtype=bool)
        again[1:] = h[1:] == h[:-1]
        nth -= np.maximum.accumulate(np.where(again, 0, nth))
        return np.sort(np.where(nth > 0, _mix(h + nth.astype(np.uint64) * _U(0xC2B2AE3D27D4EB4F)), h))


def darts(elements: np.ndarray, weights: np.ndarray | None = None, k: int = K) -> np.ndarray:
    """Signature of a weighted set (weights over 0, one each unless given): per coordinate the number of its earliest dart.

    Weights lie in regions 0-1, 1-2, 2-4, 4-8, ...; a region throws its own darts, at a rate of its width, and a dart
    counts if it falls under the weight.  So elements and their heavier parts behave alike in all documents.
    """
    if not len(elements):
        return np.zeros(0, dtype=np.uint64)
    source, width, low, under = elements, None, None, None
    total = float(len(elements))
    if weights is not None:
        total = float(weights.sum())
        top = np.where(weights > 1, np.ceil(np.log2(np.maximum(weights, 1))), 0).astype(int)
        at = np.repeat(np.arange(len(elements)), top + 1)
        region = np.arange(len(at)) - np.repeat(np.cumsum(top + 1) - (top + 1), top + 1)
        low = np.where(region > 0, 2.0 ** (region - 1), 0.0)
        width = np.where(region > 0, low, 1.0)
        under = weights[at]
        # The first region's darts are those of an element of weight one.
        source = np.where(region > 0, _mix(elements[at] + region.astype(np.uint64) * _U(0xD1B54A32D192ED03)), elements[at])
    reach = k * (np.log(k) + 3) / total
    while True:
        rank, name = [], []
        live = np.arange(len(source))
        start, number = np.zeros(len(source)), 0
        rate = float(width.max()) if width is not None else 1.0
        block = max(1, int(np.ceil(reach * rate / 2)))
        while len(live):
            count = np.arange(number + 1, number + block + 1, dtype=np.uint64) * _U(0x9E3779B97F4A7C15)
            h = _mix(source[live][:, None] + count[None, :])
            gap = -np.log(((h >> _U(11)).astype(np.float64) + 0.5) / float(1 << 53))
            if width is not None:
                gap /= width[live][:, None]
            r = np.cumsum(gap, axis=1) + start[live][:, None]
            inside = r <= reach
            fit = inside
            if width is not None:
                y = low[live][:, None] + width[live][:, None] * ((_mix(h + _U(1)) >> _U(11)).astype(np.float64) + 0.5) / float(1 << 53)
                fit = inside & (y <= under[live][:, None])
            rank.append(r[fit])
            name.append(h[fit])
            more = inside[:, -1]
            start[live] = r[:, -1]
            live = live[more]
            number += block
        rank, name = np.concatenate(rank), np.concatenate(name)
        order = np.argsort(rank, kind="stable")
        name = _mix(name[order] ^ _U(0xA0761D6478BD642F))
        found, first = np.unique(name % _U(k), return_index=True)
        if len(found) == k:
            return name[first]
        reach *= 2


def bands(signature: np.ndarray, n: int = BANDS, rows: int = ROWS) -> np.ndarray:
    if not len(signature):
        return np.zeros(0, dtype=np.int64)
    out = np.arange(1, n + 1, dtype=np.uint64) * _U(0xE7037ED1A0B428DB)
    for column in signature[: n * rows].reshape(n, rows).T:
        out = _mix(out * _U(0x9FB21C651E98DF25) + column)
    return out.view(np.int64)


def signed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", weights: str = "count") -> DataFrame:
    """(id, words: digest of the word sequence, n: distinct shingles, bands).  A text without words has no bands.

    ``weights``: "count", a shingle weighs as often as it occurs, or "set", every one weighs one.
    """
    if weights not in ("set", "count"):
        raise ValueError("weights are 'set' or 'count'")
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("words", T.BinaryType()), T.StructField("n", T.IntegerType()), T.StructField("bands", T.ArrayType(T.LongType()))])

    def run(batches):
        import pyarrow as pa

        shingler = Shingler()
        for b in pieces(batches, 1):
            digest, size, keys = [], [], []
            for raw in text_bytes(b.column(1)):
                words = raw.split()
                elements, count = np.unique(shingler.hashes(words), return_counts=True)
                digest.append(hashlib.blake2b(b" ".join(words), digest_size=16).digest() if words else None)
                size.append(len(elements))
                heavy = weights == "count" and len(count) and count.max() > 1
                keys.append(bands(darts(elements, count.astype(float) if heavy else None)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(digest, pa.binary()), pa.array(size, pa.int32()), pa.array(keys, pa.list_(pa.int64()))], names=schema.names)

    return mapped(rows, run, schema)


def confirmed(pairs: DataFrame, texts: DataFrame, similar: float = SIMILAR, weights: str = "count") -> DataFrame:
    """Of the pairs (a, b) those whose weighted shingles have a Jaccard similarity of at least ``similar``; texts: (id, t)."""
    full = pairs.join(texts.select(F.col("id").alias("b"), F.col("t").alias("tb")), "b").join(texts.select(F.col("id").alias("a"), F.col("t").alias("ta")), "a").select("a", "b", "ta", "tb")
    schema = T.StructType([pairs.schema["a"], pairs.schema["b"]])

    def run(batches):
        import pyarrow as pa

        shingler, last, of = Shingler(), None, None
        for batch in pieces(pieces(batches, 2), 3):
            keep = []
            for a, ta, tb in zip(batch.column(0).to_pylist(), text_bytes(batch.column(2)), text_bytes(batch.column(3))):
                if last != a or of is None:
                    last, of = a, shingler.set(ta, weights)
                other = shingler.set(tb, weights)
                low, high = sorted((len(of), len(other)))
                same = len(np.intersect1d(of, other, assume_unique=True)) if low >= similar * high else 0
                keep.append(bool(same) and same >= similar * (low + high - same))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=schema.names).filter(pa.array(keep, pa.bool_()))

    return mapped(full, run, schema)


def tile_links(table, similar: float = SIMILAR, weights: str = "count"):
    """Links across classes within one tile of a bucket, or between two: the shingle sets as bits over the shingles that two texts share.

    A pair is left to the first band that both share.  Classes that a link joins count as one from there on, so at most
    one link less than there are classes comes back.
    """
    import pyarrow as pa

    table = table.sort_by("rep")
    rep, label, side = (table.column(c).to_numpy() for c in ("rep", "k", "side"))
    bands_ = table.column("bands").combine_chunks().flatten().to_numpy().reshape(len(rep), -1)
    at = int(np.flatnonzero(bands_[0] == table.column("key")[0].as_py())[0])
    shingler, label = Shingler(), label.copy()
    sets = [shingler.set(raw, weights) for raw in text_bytes(table.column("t").combine_chunks())]
    size = np.array([len(x) for x in sets])
    name, where, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    number = np.cumsum(often > 1) - 1
    width = -(-int((often > 1).sum()) // 8)
    packed = None
    if width * len(sets) <= TILE_BYTES:
        packed, starts = np.zeros((len(sets), width), dtype=np.uint8), np.cumsum(size) - size
        for i in range(len(sets)):
            own = where[starts[i] : starts[i] + size[i]]
            row = np.zeros(width * 8, dtype=bool)
            row[number[own[often[own] > 1]]] = True
            packed[i] = np.packbits(row)
    found = []
    for i in range(len(sets)):
        open_ = (label != label[i]) & (np.minimum(size, size[i]) >= similar * np.maximum(size, size[i]))
        if side[i] == 2:
            open_[: i + 1] = False
        else:
            open_ &= (side != side[i]) & (side[i] == 0)
        js = np.flatnonzero(open_)
        js = js[~(bands_[js, :at] == bands_[i, :at]).any(axis=1)]
        if not len(js):
            continue
        if packed is not None:
            both = np.bitwise_count(packed[js] & packed[i]).sum(axis=1, dtype=np.int64)
        else:
            both = np.array([len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for j in js])
        for j in js[both >= similar * (size[js] + size[i] - both)]:
            if label[j] != label[i]:
                found.append((min(rep[i], rep[j]), max(rep[i], rep[j])))
                label[label == label[j]] = label[i]
    a, b = zip(*found) if found else ((), ())
    kind = table.schema.field("rep").type
    return pa.table([pa.array(a, kind), pa.array(b, kind)], names=["a", "b"])


def tiled(large: DataFrame, reps: DataFrame, texts: DataFrame, similar: float, weights: str) -> DataFrame:
    """Links across classes in large buckets; large: (key, rep, k, tiles).  A task holds two tiles, however large the bucket is."""
    dealt = large.withColumn("tile", F.pmod(F.xxhash64("rep"), F.col("tiles")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    side = F.when(F.col("tile") == F.col("other"), 2).when(F.col("tile") < F.col("other"), 0).otherwise(1)
    rows = dealt.select("key", F.least("tile", "other").alias("lo"), F.greatest("tile", "other").alias("hi"), side.alias("side"), "rep", "k")
    rows = rows.join(reps.select("rep", "bands"), "rep").join(texts.withColumnRenamed("id", "rep"), "rep")
    schema = T.StructType([T.StructField(c, reps.schema["rep"].dataType) for c in ("a", "b")])

    def run(table):
        return tile_links(table, similar, weights)

    return rows.select("key", "lo", "hi", "side", "rep", "k", "bands", "t").groupBy("key", "lo", "hi").applyInArrow(run, schema)


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similar: float = SIMILAR, weights: str = "count") -> DataFrame:
    """Per row of ``docs``: the id, n_shingles, component_id (least id of its class) and kept (whether that is its own id).

    Null and empty texts, and rows with a null id, are classes of their own.  Rows that repeat an id get the same answer.
    An empty table gives no rows; columns besides the two named are not read.
    """
    sig = written(signed(docs, id_col, text_col, weights), "signatures")
    some = sig.where("words is not null and id is not null")
    # Copies of the same words: the least id stands for all.
    reps = written(some.groupBy("words").agg(F.min("id").alias("rep"), F.first("bands").alias("bands")), "representatives")
    rows = reps.select("rep", F.explode("bands").alias("key")).repartition("key")
    shared = rows.groupBy("key").agg(F.min("rep").alias("pivot"), F.count("*").alias("c")).where("c > 1")
    members = written(rows.join(shared.select("key", "pivot"), "key"), "buckets")
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    wanted = written(members.select(F.col("rep").alias("wanted")).distinct(), "candidate-ids")
    texts = written(by_ids(texts, wanted, F.col("id") == F.col("wanted"), "left_semi").dropDuplicates(["id"]), "candidates")
    first = written(members.where("pivot <> rep").select(F.col("pivot").alias("a"), F.col("rep").alias("b")).distinct(), "pairs")
    links = written(confirmed(first, texts, similar, weights), "confirmed")
    label = components(links)
    # Buckets with members of more than one class.  Small ones: the pairs across classes.  Large ones: compared in tiles.
    marked = written(members.select("key", "rep").join(label.withColumnRenamed("id", "rep"), "rep", "left").select("key", "rep", F.coalesce("component", "rep").alias("k")), "buckets")
    mixed = marked.groupBy("key").agg(F.min("k").alias("x"), F.max("k").alias("y"), F.count("*").alias("c")).where("x <> y and c > 2").select("key", "c")
    left = marked.join(mixed.where(F.col("c") <= SMALL).select("key"), "key", "left_semi")
    right = left.select("key", F.col("rep").alias("b"), F.col("k").alias("kb"))
    across = left.select("key", F.col("rep").alias("a"), F.col("k").alias("ka")).join(right, "key").where("a < b and ka <> kb").select("a", "b").distinct()
    rest = confirmed(across.join(first, ["a", "b"], "left_anti"), texts, similar, weights)
    large = marked.join(mixed.where(F.col("c") > SMALL).withColumn("tiles", F.ceil(F.col("c") / TILE).cast("int")).drop("c"), "key")
    rest = written(rest.unionByName(tiled(large, reps, texts, similar, weights)), "confirmed")
    dropped(members, wanted, texts, first, marked)
    if rest.isEmpty():
        final = label
    else:
        final = components(links.unionByName(rest))
    named = reps.select("words", "rep").join(final.withColumnRenamed("id", "rep"), "rep", "left").select(F.col("words").alias("w"), F.coalesce("component", "rep").alias("component_id"))
    out = sig.select("id", "words", "n").join(named, F.col("words") == F.col("w"), "left").select("id", "n", F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id")).alias("component_id"))
    return out.select(F.col("id").alias(id_col), F.col("n").cast("long").alias("n_shingles"), "component_id", F.coalesce(F.col("component_id") == F.col("id"), F.lit(True)).alias("kept"))


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similar: float = SIMILAR, weights: str = "count") -> DataFrame:
    """One row of each class, all its columns; of rows that repeat an id, one.  Rows with a null id all stay."""
    found = written(classes(docs, id_col, text_col, similar, weights).select(F.col(id_col).alias("near_dup_id"), "kept"), "classes")
    gone = written(found.where("not kept").select("near_dup_id").distinct(), "duplicate-ids")
    rows = by_ids(docs, gone, F.col(id_col) == F.col("near_dup_id"), "left_anti")
    again = found.where("near_dup_id is not null").groupBy("near_dup_id").count().where("count > 1")
    return rows if again.isEmpty() else rows.where(F.col(id_col).isNull()).unionByName(rows.where(F.col(id_col).isNotNull()).dropDuplicates([id_col]))
