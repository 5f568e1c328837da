"""Line removal by a deletion-neighbourhood join.

Two lines are near-duplicates if at most ``edits`` insertions, deletions and substitutions of
characters lead from one to the other.  An occurrence of a line stays only if no earlier occurrence
(by document id, then place) of the same line exists, or of a near-duplicate one (for lines of
``min_chars`` characters or more).

How it runs
-----------
1. Lines are grouped by a 128-bit hash: equal lines cost one aggregation, however short they are.
2. Of ``edits`` + 1 pieces of the shorter line at least one stands unchanged in the longer one, with
   no more edits before and after it than there are other pieces.  Lines that share no such piece
   with another line are out before any variant is made.
3. The others emit, for each piece that they share, all variants of what stands before and after it,
   as hashed keys: characters left out, either as deletions or, with their place kept, as
   substitutions.  Lines with an equal variant are within the bound.  All that a bucket needs is the
   earliest line of each length, so buckets are aggregated and never paired.
4. The earliest line of a bucket and each later one form a candidate; edit distances are
   verified on the lines' text before a line goes.
A line that stands very often meets its verdict by a broadcast of such lines (their number is
bounded by their frequency), so no task holds all its places.

Defined results: lines are compared without white space at their ends; blank lines always stay;
lines of fewer than ``exact_from`` characters always stay, those below ``min_chars`` go only as exact
copies; null texts stay null; null ids come last in the order; rows that repeat an id and its text
are one document (each keeps the same lines); extra columns pass through; an empty table gives an
empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import stored

EXACT_FROM, MIN_CHARS, EDITS = 1, 20, 1
#: Broadcast bounds: pairs of hashes, places of lines (12 to 24 bytes each), and very frequent lines.
BROADCAST_ROWS, BROADCAST_PLACES, BROADCAST_HOT = 500_000, 1_000_000, 200_000


def _trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit("\x20\x09\x0a\x0b\x0c\x0d"))


def _identity() -> list[Column]:
    return [F.coalesce(F.col("doc_id"), F.lit((1 << 63) - 1)).alias("d"), F.xxhash64("text").alias("t")]


def _lines(docs: DataFrame, exact_from: int) -> DataFrame:
    """(d, t, pos, line, h1, h2) of every line that takes part."""
    line = docs.where("text is not null").select(*_identity(), F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    line = line.withColumn("line", _trimmed(F.col("line"))).where(F.length("line") >= max(exact_from, 1))
    return line.select("*", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit("again"), "line").alias("h2"))


def _roles(edits: int) -> list[tuple[int, int, int]]:
    """(delta, piece, shift): a line that is ``delta`` longer than its shorter partner has the partner's
    piece ``shift`` characters further on."""
    return [(delta, i, s) for delta in range(edits + 1) for i in range(edits + 1) for s in range(-i, i + 1) if abs(s - delta) <= edits - i]


def _cut(n: Column, delta: Column | int, i: Column | int, edits: int) -> tuple[Column, Column]:
    """(start from 0, length) of piece i of a partner of n - delta characters."""
    at = lambda x: F.floor((n - delta) * x / (edits + 1)).cast("int")
    return at(i if isinstance(i, int) else i.cast("int")), at(i + 1) - at(i)


def _gate(n: Column, line: Column, role: tuple[int, int, int], edits: int) -> Column:
    delta, i, shift = role
    start, size = _cut(n, delta, i, edits)
    return F.when(start + shift >= 0, F.xxhash64(n - delta, F.lit(i), F.substr(line, start + shift + 1, size)))


def _left_out(part: Column, deletions: int, marks: int) -> Column:
    """array of (t, p, d, w): ``part`` without up to so many characters, d of them deleted and w of them
    marked by their places p."""
    kind = "array<struct<t:string,p:string,d:int,w:int,at:int>>"
    level = F.array(F.struct(part.alias("t"), F.lit("").alias("p"), F.lit(0).alias("d"), F.lit(0).alias("w"), F.lit(1).alias("at"))).cast(kind)
    out = level

    def shorter(s: Column) -> Column:
        places = F.when(F.length(s["t"]) >= s["at"], F.sequence(s["at"], F.length(s["t"]))).otherwise(F.array().cast("array<int>"))

        def one(j: Column) -> Column:
            rest = F.concat(F.substr(s["t"], F.lit(1), j - 1), F.substr(s["t"], j + 1))
            ways = []
            if deletions:
                ways.append(F.struct(rest.alias("t"), s["p"].alias("p"), (s["d"] + 1).alias("d"), s["w"].alias("w"), j.alias("at")))
            if marks:
                ways.append(F.struct(rest.alias("t"), F.concat(s["p"], F.lit(","), j.cast("string")).alias("p"), s["d"].alias("d"), (s["w"] + 1).alias("w"), j.alias("at")))
            return F.array(*ways)

        return F.flatten(F.transform(places, one))

    for _ in range(deletions + marks):
        level = F.filter(F.flatten(F.transform(level, shorter)), lambda x: (x["d"] <= deletions) & (x["w"] <= marks)).cast(kind)
        out = F.concat(out, level)
    return out


def _variants(n: Column, line: Column, role: tuple[int, int, int], edits: int) -> Column:
    """Hashed variants of a line in this role.  Its partner has d - delta deletions and the same marks,
    and all of them together are ``edits`` at most, ``piece`` of them before the piece."""
    delta, i, shift = role
    start, size = _cut(n, delta, i, edits)
    before, after = F.substr(line, F.lit(1), start + shift), F.substr(line, start + shift + size + 1)
    sides = []
    for part, most in ((before, i), (after, edits - i)):
        deletions, marks = min(most, (edits + delta) // 2), min(most, edits - delta)
        sides.append(_left_out(part, deletions, marks) if deletions + marks else None)
    if any(x is None for x in sides):  # that side is empty: the first piece begins the line, the last one ends it
        some = F.filter(sides[0] if sides[1] is None else sides[1], lambda x: (x["d"] >= delta) & (x["w"] + 2 * x["d"] <= edits + delta))
        return F.array_distinct(F.transform(some, lambda x: F.xxhash64(x["t"], x["p"])))
    both = F.flatten(F.transform(sides[0], lambda x: F.transform(sides[1], lambda y: F.struct(F.xxhash64(x["t"], x["p"], y["t"], y["p"]).alias("v"), (x["d"] + y["d"]).alias("d"), (x["w"] + y["w"]).alias("w")))))
    fits = F.filter(both, lambda x: (x["d"] >= delta) & (x["w"] + 2 * x["d"] <= edits + delta))
    return F.array_distinct(F.transform(fits, lambda x: x["v"]))


def _few(df: DataFrame) -> DataFrame:
    """Broadcast behind a check of its rows (a few numbers each)."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def _meet(rows: DataFrame, table: DataFrame, often: int) -> DataFrame:
    """``rows`` joined with ``table(h1, h2, times, ...)``: broadcast if it is small; else its lines of more than
    ``often`` places are, and the others are shuffled."""
    keys = ["h1", "h2"]
    if table.count() <= BROADCAST_ROWS:
        return rows.join(F.broadcast(table), keys)
    hot = F.broadcast(table.where(F.col("times") > often))
    cold = rows.join(hot.select(*keys), keys, "left_anti").join(table.where(F.col("times") <= often), keys)
    return rows.join(hot, keys).unionByName(cold)


def dropped_lines(docs: DataFrame, *, min_chars: int = MIN_CHARS, edits: int = EDITS, exact_from: int = EXACT_FROM) -> DataFrame:
    """(d, t, drop): per document that loses lines, their places (from 0).  ``edits`` = 0: exact copies only."""
    line, n = F.col("line"), F.col("n")
    roles = _roles(edits) if edits else []
    gates = [F.max(F.when(n >= max(min_chars, 2 * edits), _gate(n, line, r, edits))).alias(f"g{j}") for j, r in enumerate(roles)]
    lines = _lines(docs, exact_from).withColumn("n", F.length("line")).groupBy("h1", "h2", "n").agg(F.count("*").alias("times"), *gates)
    lines = stored(lines, "distinct")
    total = lines.agg(F.coalesce(F.sum("times"), F.lit(0))).head()[0]
    often = max(10_000, total // BROADCAST_HOT)  # BROADCAST_HOT lines at most stand more often

    facts = [F.struct(F.lit(j).alias("role"), F.lit(r[0]).alias("delta"), F.col(f"g{j}").alias("key")) for j, r in enumerate(roles)]
    none = F.array().cast("array<struct<role:int,delta:int,key:bigint>>")
    each = lines.select("h1", "h2", "n", F.explode(F.array(*facts) if facts else none).alias("gate")).select("h1", "h2", "n", "gate.*").where("key is not null")
    shared = each.groupBy("key").agg(F.count("*").alias("c"), F.min("delta").alias("least")).where("c > 1 and least = 0").select("key")
    gated = stored(each.join(_few(stored(shared, "gates")), "key"), "gated")
    near = stored(gated.select("h1", "h2").distinct().withColumn("near", F.lit(True)), "near")

    # places matter only for lines that stand twice or may have a near-duplicate
    some = stored(lines.select("h1", "h2", "times").join(near, ["h1", "h2"], "left").where("times > 1 or near").withColumn("near", F.coalesce("near", F.lit(False))), "some")
    places = _meet(_lines(docs, exact_from), some, often).select("d", "t", "pos", "h1", "h2", "times", F.when(F.col("near"), line).alias("line"))
    places = stored(places, "places")
    found = stored(places.where("line is not null").groupBy("h1", "h2").agg(F.min("line").alias("line")), "texts")
    small = stored(places.groupBy("h1", "h2").agg(F.min(F.struct("d", "t", "pos")).alias("first"), F.first("times").alias("times")), "first")
    made = gated.join(found, ["h1", "h2"]).join(small.drop("times"), ["h1", "h2"])
    variants = F.array().cast("array<bigint>")
    for j, r in enumerate(roles):
        variants = F.when(F.col("role") == j, _variants(n, line, r, edits)).otherwise(variants)
    made = made.select("h1", "h2", "key", "first", "delta", F.explode(variants).alias("v"))
    made = stored(made, "variants")
    me = F.struct("first", "h1", "h2")
    kinds = range(edits + 1)
    buckets = made.groupBy("key", "v").agg(F.count("*").alias("c"), *(F.min(F.when(F.col("delta") == k, me)).alias(f"m{k}") for k in kinds)).where("c > 1 and m0 is not null")
    hit = made.join(buckets, ["key", "v"])
    other = F.when(F.col("delta") == 0, F.least(*(F.col(f"m{k}") for k in kinds)) if edits else F.col("m0")).otherwise(F.col("m0"))
    edges = hit.select("h1", "h2", "first", other.alias("o")).where("o.first < first").select("h1", "h2", F.col("o.h1").alias("o1"), F.col("o.h2").alias("o2")).distinct()
    both = edges.join(found.toDF("h1", "h2", "line"), ["h1", "h2"]).join(found.toDF("o1", "o2", "earlier"), ["o1", "o2"])
    gone = both.where(F.levenshtein("line", "earlier") <= edits).select("h1", "h2").distinct().withColumn("gone", F.lit(True))

    verdict = stored(small.join(gone, ["h1", "h2"], "left").where("times > 1 or gone").select("h1", "h2", "times", "first", F.coalesce("gone", F.lit(False)).alias("gone")), "verdicts")
    lost = _meet(places.select("d", "t", "pos", "h1", "h2"), verdict, often).where(F.col("gone") | (F.struct("d", "t", "pos") != F.col("first")))
    return lost.groupBy("d", "t").agg(F.collect_set("pos").alias("drop"))


def without_copies(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with cleaned ``text`` and a struct column ``lines_`` (n_lines, n_dropped)."""
    drops = stored(dropped_lines(docs, **settings), "drops").toDF("d_", "t_", "drop_")
    places = drops.agg(F.coalesce(F.sum(F.size("drop_")), F.lit(0))).head()[0]
    drops = F.broadcast(drops) if places <= BROADCAST_PLACES else drops
    d, t = _identity()
    out = docs.join(drops, (d == F.col("d_")) & (t == F.col("t_")), "left")
    pieces = F.split("text", "\n")
    stay = F.array_except(F.sequence(F.lit(0), F.size(pieces) - 1), F.col("drop_"))
    text = F.when(F.col("drop_").isNull(), F.col("text")).otherwise(F.array_join(F.transform(stay, lambda i: F.get(pieces, i)), "\n"))
    facts = F.struct(F.coalesce(F.size(pieces), F.lit(0)).cast("long").alias("n_lines"), F.coalesce(F.size("drop_"), F.lit(0)).cast("long").alias("n_dropped"))
    return out.select(*(text.alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns), facts.alias("lines_"))


def cleaned(docs: DataFrame, **settings) -> DataFrame:
    """Per row of ``docs``: doc_id, text without the lines that go, n_lines, n_dropped."""
    out = without_copies(docs.select("doc_id", "text"), **settings)
    return out.select("doc_id", "text", "lines_.n_lines", "lines_.n_dropped")


def documents_left(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with cleaned texts (and ``n_chars`` to match); a document that loses all it has goes."""
    out = without_copies(docs, **settings)
    out = out.where("lines_.n_dropped = 0 or trim(text) <> ''")
    return out.select(*(F.length("text").cast(out.schema[c].dataType).alias(c) if c == "n_chars" else F.col(f"`{c}`") for c in docs.columns))
