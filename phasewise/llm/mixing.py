"""Mixing sources to target weights by a low-discrepancy schedule, in DataFrame functions only.

Sizes are numbers of words.  Each source's documents are put in a fixed shuffled order and laid
end to end; the row of words is cut into blocks of equally many tokens.  Slots i = 0, 1, ... of
the schedule map the golden-ratio points frac(i * 0.618...) through the sources' cumulative
shares, slots are ranked per source, and the slot of rank r takes block r modulo the source's
number of blocks.  Every stretch of the schedule thus holds the sources in their target shares,
and the mix is read in the order of its slots: ``mixed_words`` tells each document's first slot,
``mixed_documents`` puts the documents out in that order.
The last slot of a source is cut and the few slots that chance leaves short are appended, so
that each source ends on its target.

Nothing is ranked or summed in one task per source: order keys are split into ranges, summed
per range, and the sums are carried over in two levels (the same is done for slots).  Only the
table of sources, one row each, is ordered in one task.

Defined results: null texts and texts without words have size 0 and are never taken; the null
source comes last; rows that repeat an id are separate documents, equal rows follow each other;
an empty table gives an empty table; extra columns are ignored, and pass through in
``mixed_documents``.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .store import stored

#: Weights of the sources in their order, and the most passes over a document.
WEIGHTS = (5, 2, 1)
MOST_TIMES = 3
#: The golden-ratio point of slot i is (i * GOLDEN mod RING) / RING.
RING = 1 << 31
GOLDEN = 1327217885
CELLS = 4096
#: Broadcast bounds (rows of some numbers each), and the places of a partition of the mix.
MOST_SOURCES, MOST_PLACES, PART_PLACES = 100_000, 1_000_000, 50_000


def word_count(text):
    return F.size(F.array_remove(F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+"), "")).cast("long")


def order_key(seed: str = "mix"):
    return F.md5(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("|" + seed)).cast("binary"))


def identity() -> list:
    """Rows of equal identity are alike for the mix."""
    return [F.col("doc_id"), F.col("source"), F.xxhash64("text").alias("t1"), F.xxhash64(F.lit("again"), "text").alias("t2")]


def sized(docs: DataFrame) -> DataFrame:
    """(doc_id, source, t1, t2, size, m): size, and how many rows are alike."""
    rows = docs.select(*identity(), word_count(F.col("text")).alias("size"))
    return rows.groupBy("doc_id", "source", "t1", "t2").agg(F.first("size").alias("size"), F.count("*").alias("m"))


def carried(df: DataFrame, by: str, at: str, value, fan: int = 4096) -> DataFrame:
    """(by, at, before): the sum of ``value`` over all smaller ``at`` of the same ``by``, carried
    within groups of ``fan`` and between them."""
    each = df.groupBy(by, at).agg(F.sum(value).alias("s")).withColumn("high", F.floor(F.col(at) / fan))
    before = lambda *keys: F.coalesce(F.sum("s").over(W.partitionBy(*keys[:-1]).orderBy(keys[-1]).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    high = each.groupBy(by, "high").agg(F.sum("s").alias("s")).select(by, "high", before(by, "high").alias("start"))
    low = each.select(by, at, "high", before(by, "high", at).alias("inside"))
    return low.join(high, [by, "high"]).select(by, at, (F.col("start") + F.col("inside")).alias("before"))


def source_targets(sizes: DataFrame, share: float = 1.0) -> DataFrame:
    """(source, place, source_size, weight, target): shares of ``share`` times all sizes; what a
    source cannot take within MOST_TIMES its size goes to the others by weight."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = W.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("place", F.row_number().over(order) - 1)
    weight = F.get(F.array(*(F.lit(x) for x in WEIGHTS)), F.col("place") % len(WEIGHTS))
    per = per.withColumn("weight", weight.cast("long")).withColumn("cap", F.col("source_size") * MOST_TIMES)
    total = W.partitionBy(F.lit(1))
    filled = W.orderBy(F.col("cap") / F.col("weight"), "place")
    per = per.withColumn("all", F.sum("source_size").over(total) * F.lit(share)).withColumn("w_all", F.sum("weight").over(total))
    # level: what one unit of weight gets if all sources up to the one before this are full
    level = (F.col("all") - (F.sum("cap").over(filled) - F.col("cap"))) / (F.col("w_all") - (F.sum("weight").over(filled) - F.col("weight")))
    per = per.withColumn("level", level)
    level = F.max(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))).over(total)
    target = F.least(F.col("weight") * F.coalesce(level, F.lit(float("inf"))), F.col("cap").cast("double"))
    return per.select("source", "place", "source_size", "weight", target.alias("target"))


def _blocks(targets: DataFrame, block_tokens: int) -> DataFrame:
    """Adds goal, block (tokens of a block), blocks, passes, rest, slots."""
    goal = F.least(F.round("target").cast("long"), MOST_TIMES * F.col("source_size"))
    t = targets.withColumn("goal", goal).where("source_size > 0")
    t = t.withColumn("block", F.greatest(F.lit(1), F.least(F.lit(block_tokens), F.floor(F.col("goal") / 64))).cast("long"))
    t = t.withColumn("blocks", F.ceil(F.col("source_size") / F.col("block")).cast("long"))
    t = t.withColumn("passes", F.floor(F.col("goal") / F.col("source_size")).cast("long"))
    t = t.withColumn("rest", F.col("goal") - F.col("passes") * F.col("source_size"))
    return t.withColumn("slots", F.col("passes") * F.col("blocks") + F.ceil(F.col("rest") / F.col("block")).cast("long"))


def schedule(plan: DataFrame) -> DataFrame:
    """(slot, place, rank, block_no, is_last): which block of which source each slot takes."""
    spark = plan.sparkSession
    n = plan.agg(F.sum("slots")).head()[0] or 0
    upto = F.sum("slots").over(W.orderBy("place"))
    edge = lambda c: F.floor(c.cast("double") / F.lit(float(max(n, 1))) * RING).cast("long")
    shares = plan.withColumn("lo", edge(upto - F.col("slots"))).withColumn("hi", edge(upto)).where("hi > lo")
    step = RING // CELLS
    shares = shares.select("place", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / step), F.floor((F.col("hi") - 1) / step))).alias("cell"))
    points = spark.range(n).select(F.col("id").alias("slot"), (F.col("id") % RING * GOLDEN % RING).alias("u")).withColumn("cell", F.floor(F.col("u") / step))
    slots = points.join(shares, "cell").where("u >= lo and u < hi").select("slot", "place", F.floor(F.col("slot") / CELLS).alias("stretch"))
    ranked = slots.join(carried(slots, "place", "stretch", F.lit(1)), ["place", "stretch"])
    ranked = ranked.withColumn("rank", F.col("before") + F.row_number().over(W.partitionBy("place", "stretch").orderBy("slot")) - 1)
    ranked = ranked.select("slot", "place", "rank").join(plan.select("place", "slots", "blocks"), "place").where("rank < slots")
    had = ranked.groupBy("place").agg(F.count("*").alias("had"))
    short = plan.join(had, "place", "left").withColumn("had", F.coalesce("had", F.lit(0))).where("had < slots")
    short = short.select(F.lit(n).alias("slot"), "place", F.explode(F.sequence("had", F.col("slots") - 1)).alias("rank"), "slots", "blocks")
    return ranked.select("slot", "place", "rank", "slots", "blocks").union(short).select("slot", "place", "rank", (F.col("rank") % F.col("blocks")).alias("block_no"), (F.col("rank") == F.col("slots") - 1).alias("is_last"))


def mix(docs: DataFrame, *, block_tokens: int = 1024, share: float = 1.0, range_rows: int = 500) -> DataFrame:
    """Per row of ``docs``: doc_id, source, t1, t2, m, copy (its number among the m rows alike), size,
    source_size, target, taken, first_slot (of any of its words), and starts: the slots that take its
    first word."""
    sizes = stored(sized(docs).withColumn("key", order_key()), "sizes")
    targets = stored(source_targets(sizes.select("source", (F.col("size") * F.col("m")).alias("size")), share), "targets")
    plan = stored(_blocks(targets, block_tokens), "plan")
    few = plan.count() <= MOST_SOURCES
    small = F.broadcast if few else (lambda df: df)
    ranges = max(1, math.ceil(sizes.count() / range_rows))
    value = F.conv(F.substring("key", 1, 8), 16, 10).cast("long")
    placed = sizes.join(small(targets), sizes.source.eqNullSafe(targets.source)).drop(targets.source)
    placed = placed.withColumn("part", F.floor(value * F.lit(float(ranges)) / F.lit(float(1 << 32))).cast("long")).withColumn("all", F.col("size") * F.col("m"))
    within = W.partitionBy("place", "part").orderBy("key", "size", "t1", "t2").rowsBetween(W.unboundedPreceding, 0)
    placed = placed.join(carried(placed, "place", "part", "all"), ["place", "part"]).withColumn("start", F.col("before") + F.sum("all").over(within) - F.col("all"))
    placed = placed.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("m").cast("int")))).withColumn("start", F.col("start") + (F.col("copy") - 1) * F.col("size"))
    row = ["doc_id", "source", "t1", "t2", "copy"]
    placed = stored(placed.select(*row, "m", "place", "size", "source_size", "target", "start"), "placed")

    # the slots of each block: of whole ones, and the last one of a source
    slot, last = F.when(~F.col("is_last"), F.col("slot")), F.when(F.col("is_last"), F.col("slot"))
    used = schedule(plan).groupBy("place", "block_no").agg(F.sort_array(F.collect_list(slot)).alias("whole"), F.max(last).alias("last"))  # MOST_TIMES + 1 slots at most
    facts = plan.select("place", "block", "rest", "source_size")
    # the last slot of a source that does not end a pass takes only what the target still needs
    used = used.join(small(facts), "place").withColumn("from", F.col("block_no") * F.col("block"))
    used = used.withColumn("to", F.least(F.col("from") + F.col("block"), "source_size"))
    cut = F.when(F.col("last").isNull(), F.col("from")).when(F.col("rest") > 0, F.least("rest", "to")).otherwise(F.col("to"))
    used = used.select("place", "block_no", "whole", "last", "from", "to", cut.alias("cut"))
    some = placed.where("size > 0").select(*row, "place", "start", (F.col("start") + F.col("size")).alias("end")).join(small(plan.select("place", "block")), "place")
    pieces = some.withColumn("block_no", F.explode(F.sequence(F.floor(F.col("start") / F.col("block")), F.floor((F.col("end") - 1) / F.col("block")))))
    hit = pieces.join(used, ["place", "block_no"])
    lo = F.greatest("start", "from")
    got = F.size("whole") * (F.least("end", "to") - lo) + F.greatest(F.lit(0), F.least("end", "cut") - lo)
    cut_too = F.when(F.least("end", "cut") > lo, F.col("last"))
    first = F.least(F.array_min("whole"), cut_too)
    begins = F.array_compact(F.concat("whole", F.array(F.when(F.col("start") < F.col("cut"), F.col("last")))))
    starts = F.when((F.col("start") >= F.col("from")) & (F.col("start") < F.col("to")), begins)
    taken = hit.select(*(F.col(c).alias(f"{c}_") for c in row), got.alias("got"), first.alias("first"), starts.alias("starts"))
    taken = taken.groupBy(*(f"{c}_" for c in row)).agg(F.sum("got").alias("taken"), F.min("first").alias("first_slot"), F.first("starts", ignorenulls=True).alias("starts"))
    same = [F.col(c).eqNullSafe(F.col(f"{c}_")) for c in row]
    out = placed.join(taken, reduce(lambda a, b: a & b, same), "left")
    return out.select(*row, "m", "size", "source_size", "target", "start", F.coalesce("taken", F.lit(0)).alias("taken"), "first_slot", "starts")


def mixed_words(docs: DataFrame, **settings) -> DataFrame:
    """Per row of ``docs``: doc_id, size, source_size, target, taken, first_slot (null if not taken)."""
    return mix(docs.select("doc_id", "source", "text"), **settings).select("doc_id", "size", "source_size", "target", "taken", "first_slot")


def mixed_documents(docs: DataFrame, **settings) -> DataFrame:
    """The mix as whole documents, in the order of the schedule: each stands at every slot that takes its
    first word.  Written files follow each other in that order."""
    spark = docs.sparkSession
    out = mix(docs.select("doc_id", "source", "text"), **settings)
    names = {c: f"mix_{c}" for c in ("doc_id", "source", "t1", "t2", "copy", "m", "start", "slot")}
    while set(names.values()) & set(docs.columns):
        names = {c: n + "_" for c, n in names.items()}
    places = stored(out.select("doc_id", "source", "t1", "t2", "copy", "m", "start", F.explode("starts").alias("slot")).toDF(*names.values()), "places")
    n, most, last = places.agg(F.count("*"), F.max(names["m"]), F.max(names["slot"])).head()
    if not n:
        return docs.where("false")
    at = {c: F.col(f"`{x}`") for c, x in names.items()}
    ids = dict(zip(("doc_id", "source", "t1", "t2"), identity(), strict=True))
    same = reduce(lambda a, b: a & b, (e.eqNullSafe(at[c]) for c, e in ids.items()))
    picked = docs.join(F.broadcast(places) if n <= MOST_PLACES else places, same)
    if most > 1:  # rows alike are told apart by a number
        number = F.row_number().over(W.partitionBy(*ids.values()).orderBy(F.lit(0)))
        numbered = docs.join(F.broadcast(places) if n <= MOST_PLACES else places, same & (at["m"] > 1), "left_semi").withColumn(f"{names['copy']}n", number)
        twins = numbered.join(places, same & (F.col(f"`{names['copy']}n`") == at["copy"])).drop(f"{names['copy']}n")
        picked = picked.where(at["m"] == 1).unionByName(twins)
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(n / PART_PLACES))
    part = F.floor(at["slot"] * F.lit(float(parts)) / F.lit(float(last + 1))).cast("int")
    return picked.repartitionById(parts, part).sortWithinPartitions(at["slot"], at["start"]).select(*(F.col(f"`{c}`") for c in docs.columns))


#: The schedule and the mix again: slots from golden-ratio points, ranks, blocks, and the words of
#: each document that they take.
ORACLE = f"""
with d as (
  select row_number() over () as uid, doc_id, source, len(list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> ''))::bigint as size,
         md5(coalesce(doc_id::varchar, '') || '|mix') as key from documents
), s as (
  select source, sum(size)::bigint as source_size, row_number() over (order by source nulls last) - 1 as place from d group by source
), w as (
  select *, [5, 2, 1][place % 3 + 1] as weight, {MOST_TIMES} * source_size as cap from s
), l as (
  select *, (sum(source_size) over () - (sum(cap) over f - cap)) / (sum(weight) over () - (sum(weight) over f - weight)) as level
  from w window f as (order by cap / weight, place)
), t as (
  select source, place, source_size, least(weight * coalesce(max(case when level * weight <= cap then level end) over (), 'infinity'::double), cap::double) as target from l
), b as (
  select *, least(round(target)::bigint, {MOST_TIMES} * source_size) as goal from t
), c as (
  select *, greatest(1, least(1024, goal // 64)) as block from b where source_size > 0
), p as (
  select *, (source_size + block - 1) // block as blocks, goal // source_size as passes, goal % source_size as rest from c
), q as (
  select *, passes * blocks + (rest + block - 1) // block as slots from p
), h as (
  select *, floor((sum(slots) over o - slots)::double / sum(slots) over () * {RING})::bigint as lo, floor((sum(slots) over o)::double / sum(slots) over () * {RING})::bigint as hi
  from q window o as (order by place)
), i as (
  select unnest(range(0, (select coalesce(sum(slots), 0)::bigint from q))) as slot
), r as (
  select slot, place, row_number() over (partition by place order by slot) - 1 as rank from i join h on slot % {RING} * {GOLDEN} % {RING} >= lo and slot % {RING} * {GOLDEN} % {RING} < hi
), g as (
  select r.* from r join q using (place) where rank < slots
  union all
  select (select sum(slots)::bigint from q), place, unnest(range(coalesce(had, 0), slots)) from q left join (select place, count(*) as had from r group by place) using (place)
), u as (
  select slot, place, rank % blocks * block as "from", case when rank = slots - 1 and rest > 0 then least(rest, rank % blocks * block + block, source_size) else least(rank % blocks * block + block, source_size) end as "to"
  from g join q using (place)
), e as (
  select d.uid, d.doc_id, size, source_size, target, place, sum(size) over (partition by d.source order by key, size, uid rows unbounded preceding) as stop
  from d join t on d.source is not distinct from t.source
), x as (
  select uid, sum(least(stop, "to") - greatest(stop - size, "from"))::bigint as taken, min(slot) as first_slot
  from e join u on e.place = u.place and "from" < stop and "to" > stop - size where size > 0 group by uid
)
select doc_id, size, source_size, target, coalesce(taken, 0) as taken, first_slot::bigint as first_slot from e left join x using (uid)
"""
