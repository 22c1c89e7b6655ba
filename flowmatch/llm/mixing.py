"""Mixing sources to target weights by weighted sampling without replacement, in DataFrame operations only.

Sizes are words.  The sources, in code-point order with null last, have weights 5, 2, 1, 5, 2, 1, ...; a source's target
is its share of all words, held to ``MOST`` times its own size, the excess shared out again by weight.  That fixpoint is
a water level: every target is the lower of the cap and level times weight, and one sort of the sources finds the level.

A target is met by whole epochs of the source and a part of one more.  For the part each document draws a uniform number
from its id and gets the key 1 - u^(1/weight), weight being its quality: in the order of these keys, a prefix is a
sample without replacement with chances in proportion to the weights (the exponential-key scheme).  The prefix ends
where its words come nearest to what is left of the target.

No source is sorted in one task.  Keys are cut into ``STEPS`` equal steps, sums by (source, step) give prefix sums, and the
step in which a source's budget ends is cut again, as often as it takes until no such step has over ``EDGE_ROWS`` keys;
only these are ordered.  As ``STEPS`` is a power of two, a step is so many leading bits of a key and rounding moves
nothing.  What comes out is one cut key per source, so the verdict on a document is a comparison in a narrow pass, and
the text of no document is shuffled.  The table of sources is broadcast up to ``BROADCAST_SOURCES`` rows; a larger one
meets its documents by source and a salt, so that one source's documents spread.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from flowmatch.llm.common import WORD, unit, written

WEIGHTS, MOST, SEED = (5, 2, 1), 3, "mix"
STEPS, MOST_CUTS, EDGE_ROWS, BROADCAST_SOURCES, SALTS = 256, 6, 20_000, 100_000, 32
#: Characters that speak against a text when they are many.
MARKS = "#*$%&|<>!^~=+_\\/{}[]@0123456789"


def words(text: Column) -> Column:
    """Number of words; a null text has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("bigint")


def quality(text: Column) -> Column:
    """Weight of a document, from 0.1 to 1.1: the share of its characters that are no marks; a null or empty text has the least."""
    plain = F.length(F.translate(text, MARKS, ""))
    return F.coalesce(F.lit(0.1) + plain.cast("double") / F.greatest(F.length(text), F.lit(1)).cast("double"), F.lit(0.1))


def key(doc_id: Column, weight: Column) -> Column:
    return F.lit(1.0) - F.pow(unit(doc_id, F.lit(SEED)), F.lit(1.0) / weight)


def targets(sizes: DataFrame) -> DataFrame:
    """From (source, size): source, source_size, weight, target; one row per source.

    The only ordering without a key runs here, over one row per source.
    """
    every = Window.partitionBy(F.lit(0))
    by_name = every.orderBy(F.col("source").isNull(), F.col("source"))
    ranked = sizes.groupBy("source").agg(F.sum("size").alias("source_size")).withColumn("n", F.row_number().over(by_name))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in WEIGHTS]), ((F.col("n") - 1) % len(WEIGHTS) + 1).cast("int"))
    cap = F.lit(float(MOST)) * F.col("source_size")
    filling = every.orderBy(F.col("cap") / F.col("weight"), "n")
    before, after = filling.rowsBetween(Window.unboundedPreceding, -1), filling.rowsBetween(0, Window.unboundedFollowing)
    # The level if exactly the sources before this one are full; the first level that leaves this source's cap unreached is the level.
    level = ranked.withColumn("weight", weight).withColumn("cap", cap).withColumn("all", F.sum("source_size").over(every).cast("double")).withColumn(
        "level", (F.col("all") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    )
    found = level.withColumn("water", F.min(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.struct(F.col("cap") / F.col("weight"), "n", "level"))).over(every)["level"])
    return found.select("source", "source_size", "weight", F.least("cap", F.coalesce(F.col("water") * F.col("weight"), F.col("cap"))).alias("target"))


def drawn(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weight: Column | None = None) -> DataFrame:
    """(doc_id, source, size, key) of every row, written once: the passes below read no text."""
    w = quality(F.col(text_col)) if weight is None else weight
    return written(docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), words(F.col(text_col)).alias("size"), key(F.col(id_col), w).alias("key")), "mix-keys")


def by_source(rows: DataFrame, small: DataFrame, also: Column | None = None) -> DataFrame:
    """``rows`` beside the row of ``small`` of their source (its column ``s``); sources without one are left out."""
    same = F.col("source").eqNullSafe(F.col("s"))
    if also is not None:
        same = same & also
    if small.count() <= BROADCAST_SOURCES:
        return rows.join(F.broadcast(small), same)
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)))
    every = small.withColumn("z", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint"))))
    return dealt.join(every, same & (F.col("salt") == F.col("z"))).drop("salt", "z")


def step(cut: int) -> Column:
    """The step of a key after so many cuts: its leading bits."""
    return F.floor(F.col("key") * float(STEPS**cut)).cast("bigint")


def cuts(rows: DataFrame) -> DataFrame:
    """Per source: source, source_size, target, epochs, and the cut (key and id of the last document of the part epoch, or null)."""
    full = F.least(F.lit(float(MOST)), F.floor(F.col("target") / F.greatest(F.col("source_size"), F.lit(1))))
    plan = targets(rows).withColumn("epochs", full.cast("bigint")).withColumn("budget", F.col("target") - F.col("epochs") * F.col("source_size"))
    plan = written(plan, "mix-plan")
    # Of each source that has a budget: the step in which it ends, if it ends in the source at all, and what lies before.
    edge = written(plan.where("budget > 0").select(F.col("source").alias("s"), "budget", F.lit(0).cast("bigint").alias("at"), F.lit(0).cast("bigint").alias("before")), "mix-edge")
    for cut in range(1, MOST_CUTS + 1):
        inside = by_source(rows, edge, step(cut - 1) == F.col("at"))
        sums = inside.groupBy("source", step(cut).alias("step")).agg(F.sum("size").alias("words"), F.count("*").alias("n"), F.first("budget").alias("budget"), F.first("before").alias("before"))
        running = sums.withColumn("upto", F.col("before") + F.sum("words").over(Window.partitionBy("source").orderBy("step")))  # up to STEPS rows a source
        ends = running.where("upto >= budget").groupBy("source").agg(F.min("step").alias("at"), F.min_by(F.col("upto") - F.col("words"), "step").alias("before"), F.first("budget").alias("budget"), F.min_by("n", "step").alias("n"))
        edge = written(ends.select(F.col("source").alias("s"), "budget", "at", "before", "n"), "mix-edge")
        if (edge.agg(F.max("n")).first()[0] or 0) <= EDGE_ROWS:
            break
    # Documents that repeat an id have one key and go in or stay out together.
    inside = by_source(rows, edge, step(cut) == F.col("at")).groupBy("source", "key", "doc_id").agg(F.sum("size").alias("size"), F.first("before").alias("before"), F.first("budget").alias("budget"))
    order = Window.partitionBy("source").orderBy("key", "doc_id")
    met = F.col("before") + F.sum("size").over(order) - F.col("size") / 2 <= F.col("budget")
    chosen = inside.withColumn("met", met).where("met").groupBy("source").agg(F.max(F.struct("key", "doc_id")).alias("cut"))
    # If no document of the last step is in, the cut lies where that step begins.
    last = edge.select("s", "at").join(chosen.select(F.col("source").alias("t"), "cut"), F.col("s").eqNullSafe(F.col("t")), "left")
    last = last.select("s", F.col("cut.key").alias("cut_key"), F.col("cut.doc_id").alias("cut_id"), (F.col("at") / F.lit(float(STEPS**cut))).alias("edge_key"))
    return written(plan.join(last, F.col("source").eqNullSafe(F.col("s")), "left").drop("s"), "mix-cuts")


def copies() -> Column:
    """Times a row is taken: the epochs, and once more if it is not behind the cut."""
    k, i = F.col("key"), F.col("doc_id")
    first = F.coalesce((k < F.col("cut_key")) | ((k == F.col("cut_key")) & (i <= F.col("cut_id"))), k < F.col("edge_key"), F.lit(False))
    return F.when(F.col("size") > 0, F.col("epochs") + first.cast("bigint")).otherwise(F.lit(0).cast("bigint"))


def mix(rows: DataFrame) -> DataFrame:
    """From :func:`drawn`: doc_id, source, size, source_size, target, taken.

    Rows without words are taken 0 times.  Rows that repeat an id are taken or left together.  A source of no words has
    target 0.  Empty tables give empty results.
    """
    joined = by_source(rows, cuts(rows).withColumnRenamed("source", "s"))
    return joined.select("doc_id", "source", "size", "source_size", "target", (F.col("size") * copies()).alias("taken"))


def repeated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mixed corpus itself: each row of ``docs``, all its columns, as often as it is taken.  Rows without words are left out."""
    plan = cuts(drawn(docs, id_col, text_col, source_col)).withColumnRenamed("source", "s")
    own = "mix_row"
    rows = docs.select(F.struct("*").alias(own), F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), words(F.col(text_col)).alias("size"), key(F.col(id_col), quality(F.col(text_col))).alias("key"))
    taken = by_source(rows, plan).select(own, copies().alias("n")).where("n > 0")
    return taken.select(own, F.explode(F.sequence(F.lit(1), F.col("n").cast("int")))).select(f"{own}.*")


def oracle() -> str:
    marks = MARKS.replace("'", "''")
    return rf"""
with rows as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size,
         (('0x' || substr(md5(coalesce(doc_id::varchar, '') || ':{SEED}'), 1, 12))::bigint + 0.5::double) / 281474976710656.0::double as u,
         coalesce(0.1::double + length(translate(text, '{marks}', ''))::double / greatest(length(text), 1)::double, 0.1::double) as w
  from documents),
sums as (select source, sum(size)::bigint as source_size from rows group by source),
ranked as (select *, row_number() over (order by source is null, source) as n from sums),
weighed as (select *, 3.0::double * source_size as cap, [5.0::double, 2.0::double, 1.0::double][((n - 1) % 3 + 1)::int] as weight from ranked),
levels as (select *, (sum(source_size) over ()::double - coalesce(sum(cap) over (order by cap / weight, n rows between unbounded preceding and 1 preceding), 0))
                     / sum(weight) over (order by cap / weight, n rows between current row and unbounded following) as level from weighed),
water as (select arg_min(level, row(cap / weight, n)) as level from levels where level * weight <= cap),
plan as (select source, source_size, least(cap, coalesce(water.level * weight, cap)) as target from levels, water),
epochs as (select *, least(3, floor(target / greatest(source_size, 1))) as epochs, target - least(3, floor(target / greatest(source_size, 1))) * source_size as budget from plan),
keyed as (select r.*, p.source_size, p.target, p.epochs, p.budget,
                 sum(r.size) over (partition by r.source, r.doc_id) as own,
                 sum(r.size) over (partition by r.source order by 1.0::double - pow(u, 1.0::double / w), doc_id range unbounded preceding) as upto
          from rows r join epochs p on r.source is not distinct from p.source)
select doc_id, source, size, source_size, target,
       (size * (epochs + case when budget > 0 and upto - own / 2.0 <= budget then 1 else 0 end))::bigint as taken
from keyed"""
