"""Chat formatting by quotation linking, in DataFrame operations only.

A line that begins with '>' marks is quoted, as deep as it has marks.  Runs of lines of one depth are passages; their
normalised text (lower case, white space squeezed) is hashed.  Messages offer the hashes of their own words: the whole
body, its paragraphs, its lines, the runs between its own quotes, and every series of consecutive lines or paragraphs that
is as long as a passage that begins with the same two.  A passage links to the earliest earlier message that offers its hash, in its own
conversation if there is one, else in any; "earlier" is by (conv_id, turn), so links have no cycles.  A message answers
the message that its longest passage of depth 1 links to.  A conversation then holds the messages whose chain of
answers begins in it, in the order of (conv_id, turn): every answer comes after what it answers.

Offers are reduced to one message per hash (and conversation) before they are joined, so a line that many messages share
costs one row.  Places come from one range-partitioned sort and the partitions' counts, so no conversation, however
long, has to fit a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from flowmatch.llm.common import written

MARK = r"^((?:>[ \t]?)+)"
BLANK = r"\n[\x20\x09-\x0D]*\n"
QUOTED = r"(?md)^>[^\n]*(?:\n|\z)"
_ID = ["conv_id", "turn"]


def normal(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"[\x20\x09-\x0D]+", " "))


def depth(line: Column) -> Column:
    return F.length(F.regexp_replace(F.regexp_extract(line, MARK, 1), "[^>]", ""))


def body(text: Column) -> Column:
    """A message without its quoted lines, without the white space that they leave at its ends."""
    kept = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: ~x.startswith(">"))
    return F.regexp_replace(F.array_join(kept, "\n"), r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")


def units(parts: Column) -> Column:
    """The normalised parts that have words."""
    return F.filter(F.transform(parts, normal), lambda x: x != "")


def pairs(own: Column, kind: int) -> Column:
    """(kind, key, i) for each two units that follow one another, i that of the first; keys may clash, as series are compared by their text."""
    at = lambda i: F.struct(F.lit(kind).alias("kind"), F.xxhash64(F.get(own, i), F.get(own, i + 1)).alias("key"), i.alias("i"))
    return F.transform(F.when(F.size(own) > 1, F.sequence(F.lit(0), F.size(own) - 2)).otherwise(F.array().cast("array<int>")), at)


def passages(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, row, first, depth, hash, size, starts): the quoted passages that have words; starts are (kind, key, n), the first two of its n lines or paragraphs."""
    quoted = messages.where(F.col("text").rlike(r"(?m)^>")).dropDuplicates([*_ID, "row"]).select(*_ID, "row", F.posexplode(F.split("text", "\n")).alias("at", "line"))
    lines = quoted.select(*_ID, "row", "at", depth(F.col("line")).alias("depth"), F.regexp_replace("line", MARK, "").alias("line"))
    order = Window.partitionBy(*_ID, "row").orderBy("at")
    runs = lines.withColumn("run", F.sum((F.col("depth") != F.lag("depth", 1, -1).over(order)).cast("int")).over(order)).where("depth > 0")
    whole = runs.groupBy(*_ID, "row", "run").agg(F.min("at").alias("first"), F.min("depth").alias("depth"), F.array_sort(F.collect_list(F.struct("at", "line"))).alias("l"))
    said = whole.withColumn("said", normal(F.array_join(F.col("l.line"), " "))).where("said <> ''")
    said = said.withColumns({"lines": units(F.col("l.line")), "paragraphs": units(F.split(F.array_join("l.line", "\n"), BLANK))})
    start = lambda c, kind: F.transform(F.slice(pairs(F.col(c), kind), 1, 1), lambda x: F.struct(x.kind.alias("kind"), x.key.alias("key"), F.size(c).alias("n")))
    return said.select(*_ID, "row", "first", "depth", F.md5(F.col("said").cast("binary")).alias("hash"), F.length("said").alias("size"), F.concat(start("lines", 0), start("paragraphs", 1)).alias("starts"))


def offers(messages: DataFrame, found: DataFrame) -> DataFrame:
    """(conv_id, turn, hash): what messages say themselves, as a whole, by paragraph, by line, by run between quotes, and by series that passages may be."""
    messages = messages.where("conv_id is not null and turn is not null")
    parts = F.concat(F.array("body"), F.split("body", BLANK), F.split("body", "\n"), F.split("text", QUOTED))
    said = messages.select(*_ID, F.explode(F.array_distinct(units(parts))).alias("said"))
    return said.unionByName(series(messages, found)).select(*_ID, F.md5(F.col("said").cast("binary")).alias("hash"))


def series(messages: DataFrame, found: DataFrame) -> DataFrame:
    """(conv_id, turn, said): series of a message's lines or paragraphs, quotes left out, that begin as a passage of as many does.

    Rows are the places where a passage's first two units are, times the lengths of passages that begin so: never messages times passages.
    """
    asked = found.select(F.explode("starts").alias("s")).groupBy("s.kind", "s.key").agg(F.collect_set("s.n").alias("lengths"))
    paragraphs = F.flatten(F.transform(F.split("text", QUOTED), lambda run: F.split(run, BLANK)))
    own = messages.dropDuplicates([*_ID, "row"]).select(*_ID, "row", units(F.split("body", "\n")).alias("lines"), units(paragraphs).alias("paragraphs"))
    places = own.select(*_ID, "row", F.explode(F.concat(pairs(F.col("lines"), 0), pairs(F.col("paragraphs"), 1))).alias("u")).select(*_ID, "row", "u.*")
    hit = places.join(asked, ["kind", "key"]).select(*_ID, "row", "kind", "i", F.explode("lengths").alias("n"))
    cuts = hit.groupBy(*_ID, "row").agg(F.collect_set(F.struct("kind", "i", "n")).alias("cuts"))
    of = lambda c: F.when(c.kind == 0, F.col("lines")).otherwise(F.col("paragraphs"))
    whole = F.filter("cuts", lambda c: c.i + c.n <= F.size(of(c)))
    return cuts.join(own, [*_ID, "row"]).select(*_ID, F.explode(F.array_distinct(F.transform(whole, lambda c: F.array_join(F.slice(of(c), c.i + 1, c.n), " ")))).alias("said"))


def links(messages: DataFrame) -> DataFrame:
    """Per passage: its columns, and parent (conv_id, turn) or null."""
    found = written(passages(messages), "passages")
    offered = offers(messages, found).join(found.select("hash").distinct(), "hash", "left_semi")
    near = offered.groupBy("conv_id", "hash").agg(F.min("turn").alias("near"))
    far = offered.groupBy("hash").agg(F.min(F.struct(*_ID)).alias("far"))
    both = found.join(near, ["conv_id", "hash"], "left").join(far, "hash", "left")
    here = F.when(F.col("near") < F.col("turn"), F.struct("conv_id", F.col("near").alias("turn")))
    there = F.when((F.col("far.conv_id") < F.col("conv_id")) | (F.col("far.conv_id") == F.col("conv_id")) & (F.col("far.turn") < F.col("turn")), F.col("far"))
    return both.select(*_ID, "row", "first", "depth", "size", F.coalesce(here, there).alias("parent"))


def roots(parents: DataFrame) -> DataFrame:
    """From (id, up) with id unique: (id, root, hops), by doubling: as many rounds as the longest chain has bits."""
    at = written(parents.select("id", F.col("up").alias("root"), F.lit(1).alias("hops")), "answers")
    while not at.isEmpty():
        next_ = at.select(F.col("id").alias("root"), F.col("root").alias("further"), F.col("hops").alias("more"))
        new = written(at.join(next_, "root", "left").select("id", F.coalesce("further", "root").alias("root"), (F.col("hops") + F.coalesce("more", F.lit(0))).alias("hops"), F.col("further").isNotNull().alias("moved")), "answers")
        moved = not new.where("moved").isEmpty()
        at = new.drop("moved")
        if not moved:
            break
    return at


def conversations(messages: DataFrame) -> DataFrame:
    """One row per message, placed: conv_id, turn, role, n_passages, n_linked, quote_depth, parent_conv, parent_turn,
    thread_id, hops, position (from 0 in its thread), body.

    Null texts count as empty.  A message of null conv_id or turn answers nothing and is not answered; null threads hold
    what has a null conv_id.  Rows that repeat (conv_id, turn) are messages of their own that share an answered message:
    that of the longest passage among them.  Columns other than conv_id, turn, role, text are not read.
    """
    rows = messages.select(F.col("conv_id"), F.col("turn"), F.col("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("body", body(F.col("text"))).withColumn("row", F.xxhash64("role", "text"))
    found = written(links(rows), "quotations")
    summed = found.groupBy(*_ID, "row").agg(F.count("*").alias("n_passages"), F.count("parent").alias("n_linked"), F.max("depth").alias("quote_depth"))
    best = found.where("depth = 1 and parent is not null").groupBy(F.struct(*_ID).alias("id")).agg(F.max_by("parent", F.struct("size", -F.col("first"), -F.col("row"))).alias("up"))
    best = written(best, "answered")
    tree = roots(best).join(best, "id").select(F.col("id.conv_id").alias("c"), F.col("id.turn").alias("t"), "up", "root", "hops")
    k = rows.join(summed.select(F.col("conv_id").alias("c1"), F.col("turn").alias("t1"), F.col("row").alias("r1"), "n_passages", "n_linked", "quote_depth"), F.col("conv_id").eqNullSafe(F.col("c1")) & F.col("turn").eqNullSafe(F.col("t1")) & (F.col("row") == F.col("r1")), "left")
    k = k.join(tree, (F.col("conv_id") == F.col("c")) & (F.col("turn") == F.col("t")), "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    placed = k.select(*_ID, "role", zero("n_passages"), zero("n_linked"), zero("quote_depth"), F.col("up.conv_id").alias("parent_conv"), F.col("up.turn").alias("parent_turn"), F.coalesce("root.conv_id", "conv_id").alias("thread_id"), zero("hops"), "body")
    n = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    key = ["thread_id", *_ID, "role", "body", "n_passages", "n_linked", "quote_depth"]
    ordered = placed.repartitionByRange(n, *key).sortWithinPartitions(*key).withColumn("mark", F.monotonically_increasing_id())
    ordered = written(ordered.withColumns({"part": F.shiftright("mark", 33), "nth": F.col("mark").bitwiseAND(F.lit((1 << 33) - 1))}).drop("mark"), "ordered")
    before = Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = ordered.groupBy("part").count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))  # one row per partition
    ranked = ordered.join(F.broadcast(starts), "part").withColumn("rank", F.col("start") + F.col("nth")).drop("part", "start", "nth")
    heads = ranked.groupBy("thread_id").agg(F.min("rank").alias("head")).withColumnRenamed("thread_id", "h")
    done = ranked.join(heads, F.col("thread_id").eqNullSafe(F.col("h")))
    return done.select(*_ID, "role", "n_passages", "n_linked", "quote_depth", "parent_conv", "parent_turn", "thread_id", "hops", (F.col("rank") - F.col("head")).alias("position"), "body")


def oracle() -> str:
    return r"""
with recursive messages as (
  select conv_id, turn, role, coalesce(text, '') as text, row_number() over () as rid from conversations),
lines as (
  select conv_id, turn, rid, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from messages),
bodies as (
  select *, regexp_replace(array_to_string(list_filter(string_split(text, chr(10)), lambda x: not starts_with(x, '>')), chr(10)),
                           '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') as body from messages),
deep as (
  select conv_id, turn, rid, pos, length(regexp_replace(regexp_extract(line, '^((?:>[ \t]?)+)', 1), '[^>]', '', 'g')) as depth,
         regexp_replace(line, '^((?:>[ \t]?)+)', '') as line from lines),
breaks as (select *, case when depth is distinct from lag(depth) over (partition by rid order by pos) then 1 else 0 end as new from deep),
runs as (select *, sum(new) over (partition by rid order by pos) as run from breaks),
said as (
  select conv_id, turn, rid, run, min(pos) as first, min(depth) as depth,
         trim(regexp_replace(lower(string_agg(line, ' ' order by pos)), '[\x20\x09-\x0D]+', ' ', 'g'), ' ') as said
  from runs where depth > 0 group by all),
passages as (select * from said where said <> ''),
offers as (
  select distinct conv_id, turn, trim(regexp_replace(lower(p), '[\x20\x09-\x0D]+', ' ', 'g'), ' ') as said
  from (select conv_id, turn, unnest([body] || regexp_split_to_array(body, '\n[\x20\x09-\x0D]*\n') || string_split(body, chr(10))) as p
        from bodies where conv_id is not null and turn is not null)),
nearby as (select conv_id, said, min(turn) as near from offers where said <> '' group by all),
far as (select said, min(row(conv_id, turn)) as far, arg_min(conv_id, row(conv_id, turn)) as far_conv, arg_min(turn, row(conv_id, turn)) as far_turn from offers where said <> '' group by said),
linked as (
  select p.*, case when near < p.turn then p.conv_id when far_conv < p.conv_id or far_conv = p.conv_id and far_turn < p.turn then far_conv end as up_conv,
              case when near < p.turn then near when far_conv < p.conv_id or far_conv = p.conv_id and far_turn < p.turn then far_turn end as up_turn
  from passages p left join nearby n on n.conv_id = p.conv_id and n.said = p.said left join far f on f.said = p.said),
counts as (select rid, count(*) as n_passages, count(up_conv) as n_linked, max(depth) as quote_depth from linked group by rid),
answered as (
  select conv_id, turn, arg_max(up_conv, row(length(said), -first)) as up_conv, arg_max(up_turn, row(length(said), -first)) as up_turn
  from linked where depth = 1 and up_conv is not null group by all),
chain as (
  select conv_id, turn, up_conv, up_turn, 1 as hops from answered
  union all
  select c.conv_id, c.turn, a.up_conv, a.up_turn, c.hops + 1 from chain c join answered a on a.conv_id = c.up_conv and a.turn = c.up_turn),
roots as (select conv_id, turn, max(hops) as hops, arg_max(up_conv, hops) as root_conv from chain group by all)
select b.conv_id, b.turn, b.role, coalesce(n_passages, 0)::bigint as n_passages, coalesce(n_linked, 0)::bigint as n_linked, coalesce(quote_depth, 0)::bigint as quote_depth,
       a.up_conv as parent_conv, a.up_turn as parent_turn, coalesce(root_conv, b.conv_id) as thread_id, coalesce(hops, 0)::bigint as hops,
       row_number() over (partition by coalesce(root_conv, b.conv_id) order by b.conv_id nulls first, b.turn nulls first, b.role nulls first, b.body, coalesce(n_passages, 0), coalesce(n_linked, 0), coalesce(quote_depth, 0)) - 1 as position, b.body
from bodies b left join counts c on c.rid = b.rid left join answered a on a.conv_id = b.conv_id and a.turn = b.turn
     left join roots r on r.conv_id = b.conv_id and r.turn = b.turn"""
