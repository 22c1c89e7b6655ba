"""Sharding by weighted rendezvous hashing, in DataFrame operations only.

Every record key draws one number for each shard; the shard with the best number takes it: the least of -ln(u) / weight.
A number depends on key, shard and the shard's weight alone, so one more shard takes records only into itself, and every
shard takes its weight's share.  A key is hashed once, by MD5, to three numbers of 30 bits; each shard makes its own u of
two of them by arithmetic modulo a prime.

Within a shard slots are gapless: records are dealt by hash into parts of a shard, parts are counted, and a record's slot is
what lies before its part and its place in it.  Equal records are counted, not ordered: a run of slots belongs to them,
dealt out in lots of ``ROWS_PER_PART``.  So no task sees more than a part or a lot.
"""

from __future__ import annotations

import math
import random

from pyspark.sql import Column, DataFrame, Window, functions as F

SHARDS, ROWS_PER_PART, LAW, SEED = 40, 4096, "key", 23
PRIME = (1 << 31) - 1


def _factors(shard: int) -> tuple[int, int, int]:
    rng = random.Random(f"{SEED}:{shard}")
    return tuple(rng.randrange(1, 1 << 30) for _ in range(3))


def key_numbers(key: Column) -> tuple[Column, Column, Column]:
    """Three numbers of 30 bits from a record key; a null key is the empty one."""
    digest = F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary"))
    return tuple((F.conv(F.substring(digest, 1 + 8 * k, 8), 16, 10).cast("bigint") % (1 << 30)) for k in range(3))


def _number(x: Column, y: Column, shard: int, weight: float) -> Column:
    a, b, c = _factors(shard)
    u = (((x * a + y) % PRIME) * ((y * b + x) % PRIME) + c) % PRIME
    return F.struct((F.log((u.cast("double") + F.lit(0.5)) / F.lit(float(PRIME))) / F.lit(weight)).alias("v"), F.lit(shard).alias("s"))


def checked(n: int, weights: list[float] | None) -> list[float]:
    weights = [1.0] * n if weights is None else [float(w) for w in weights]
    if n < 1 or len(weights) != n or not all(0 < w < math.inf for w in weights):
        raise ValueError("shards need to be one or more, weights one each, positive and finite")
    return weights


def shard_of(key: Column, n: int, weights: list[float] | None = None) -> Column:
    """The shard of a key among ``n`` of the given weights (one each unless given)."""
    x, y, _ = key_numbers(key)
    best = [_number(x, y, s, w) for s, w in enumerate(checked(n, weights))]
    return (F.greatest(*best) if n > 1 else best[0]).getField("s")


def place(docs: DataFrame, n: int = SHARDS, weights: list[float] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, size, text_crc32, law, shard, slot, grown_shard (with one shard more of weight 1).

    A null text has no bytes, so size 16 and CRC 0.  A null id is a key like others.  Rows that repeat an id share its
    shard.  An empty table gives no rows.  Other columns are not read, and no text is shuffled.
    """
    weights = checked(n, weights)
    raw = F.encode(F.coalesce(F.col(text_col), F.lit("")), "UTF-8")
    x, y, z = (F.col(c) for c in "xyz")
    rows = docs.select(F.col(id_col).alias("id"), (F.octet_length(raw).cast("bigint") + 16).alias("size"), F.crc32(raw).alias("text_crc32"))
    parts = max(1, -(-rows.count() // (n * ROWS_PER_PART)))
    hashed = rows.select("*", *[v.alias(c) for c, v in zip("xyz", key_numbers(F.col("id")))])
    best = [_number(x, y, s, w) for s, w in enumerate(weights)]
    dealt = hashed.select("id", "size", "text_crc32", ((z + F.col("text_crc32")) % parts).alias("part"), (F.greatest(*best) if n > 1 else best[0]).alias("best"), _number(x, y, n, 1.0).alias("one_more"))
    dealt = dealt.select("id", "size", "text_crc32", "part", F.col("best.s").alias("shard"), F.greatest("best", "one_more")["s"].alias("grown_shard"))
    equal = dealt.groupBy("shard", "part", "id", "text_crc32", "size", "grown_shard").agg(F.count("*").alias("c"))
    whole = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = equal.groupBy("shard", "part").agg(F.sum("c").alias("c")).select("shard", "part", F.coalesce(F.sum("c").over(whole), F.lit(0)).alias("start"))
    order = Window.partitionBy("shard", "part").orderBy("id", "text_crc32").rowsBetween(Window.unboundedPreceding, -1)
    at = equal.withColumn("k", F.coalesce(F.sum("c").over(order), F.lit(0))).join(starts, ["shard", "part"]).withColumn("first", F.col("start") + F.col("k"))
    few = at.where(F.col("c") <= ROWS_PER_PART)
    lot = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("c") - 1, F.lit(ROWS_PER_PART).cast("bigint")))
    many = at.where(F.col("c") > ROWS_PER_PART).select("*", lot.alias("lot"))
    many = many.withColumn("first", F.col("first") + F.col("lot")).withColumn("c", F.least(F.col("c") - F.col("lot"), F.lit(ROWS_PER_PART)))
    every = few.unionByName(many.select(few.columns).repartition("id", "first"))
    slots = every.select("*", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("c") - 1)).alias("slot"))
    return slots.select(F.col("id").alias(id_col), "size", "text_crc32", F.lit(LAW).alias("law"), "shard", "slot", "grown_shard")


def oracle(n: int = SHARDS) -> str:
    """DuckDB SQL for :func:`place` with weights of one.  CRC-32 is summed byte by byte from its table, which a recursion makes."""
    numbers = ", ".join(f"{{'v': ln((((x * {a} + y) % {PRIME}) * ((y * {b} + x) % {PRIME}) + {c}) % {PRIME} + 0.5::double) - ln({PRIME}.0::double), 's': {s}}}" for s, (a, b, c) in ((s, _factors(s)) for s in range(n + 1)))
    return f"""
with recursive bits(i, c, k) as (select range::bigint, range::bigint, 0 from range(256) union all select i, case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end, k + 1 from bits where k < 8),
crc as materialized (select list(c order by i) as tbl from bits where k = 8),
raw as (select doc_id, hex(encode(coalesce(text, ''))) as h, md5(coalesce(doc_id::varchar, '')) as m from documents),
rows as materialized (select doc_id, length(h) // 2 + 16 as size, m, list_transform(regexp_extract_all(h, '..'), lambda b: ('0x' || b)::bigint) as bytes from raw),
summed as materialized (select doc_id, size, m, xor(list_reduce(list_prepend(4294967295::bigint, bytes), lambda a, b: xor(a >> 8, tbl[(xor(a, b) & 255) + 1])), 4294967295) as text_crc32 from rows, crc),
keyed as (select *, ('0x' || substr(m, 1, 8))::bigint % 1073741824 as x, ('0x' || substr(m, 9, 8))::bigint % 1073741824 as y, ('0x' || substr(m, 17, 8))::bigint % 1073741824 as z from summed),
drawn as (select *, [{numbers}] as numbers, greatest(1, ceil((select count(*) from documents) / {float(n * ROWS_PER_PART)})::bigint) as parts from keyed),
placed as (select doc_id, size, text_crc32, (z + text_crc32) % parts as part, list_max(numbers[1:{n}]).s as shard, list_max(numbers).s as grown_shard from drawn)
select doc_id, size, text_crc32, '{LAW}' as law, shard, row_number() over (partition by shard order by part, doc_id, text_crc32) - 1 as slot, grown_shard from placed"""
