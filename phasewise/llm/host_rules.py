"""Host-level quality rules, in DataFrame functions only.

Every document is measured and held against four rules.  Failures are added up by host (the
``source`` of a document), each host's failure rate is shrunk towards the corpus by a beta
prior that is fitted to all hosts (method of moments), and hosts whose shrunk rate of some rule
passes ``host_limit`` are rejected; the verdict is joined back to the host's documents.

Defined results: a null text has no words (so it fails); null hosts form one host; extra
columns are kept aside under one struct and cannot clash; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import stored

#: White space between words, and the symbols that are counted.
SPACE = r"[\x20\x09-\x0D]+"
NO_SYMBOL = r"[^#*$%&|<>]+"

RULES = ("short", "repeats", "symbols", "copied_lines")
BROADCAST_HOSTS = 100_000


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, SPACE), "")


MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def measured(docs: DataFrame, at: str = "q", only: tuple[str, ...] = MEASURES) -> DataFrame:
    """``docs`` and a struct column ``at`` with measures (``only`` these) of the whole text."""
    text = F.coalesce("text", F.lit(""))
    one = docs.withColumn(f"{at}_words", words_of(text))
    w = F.col(f"{at}_words")
    gram = lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2))
    grams = F.when(F.size(w) >= 3, F.transform(F.sequence(F.lit(0), F.size(w) - 3), gram)).otherwise(F.array().cast("array<bigint>"))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    two = one.withColumn(f"{at}_grams", grams).withColumn(f"{at}_lines", lines).withColumn(f"{at}_n", F.size(w)).drop(f"{at}_words")
    g = F.col(f"{at}_grams")
    # only texts with a repeated window are sorted
    pairs = F.when(F.size(F.array_distinct(g)) < F.size(g), F.sort_array(F.transform(g, lambda h, i: F.struct(h.alias("h"), i.alias("p")))))
    three = two.withColumn(f"{at}_sorted", pairs).drop(f"{at}_grams")
    s = F.col(f"{at}_sorted")
    twice = F.transform(s, lambda e, j: F.when((F.get(s, j - 1)["h"] == e["h"]) | (F.get(s, j + 1)["h"] == e["h"]), e["p"]))
    four = three.withColumn(f"{at}_starts", F.sort_array(F.array_compact(twice))).drop(f"{at}_sorted")
    p = F.col(f"{at}_starts")
    covered = F.aggregate(F.transform(p, lambda x, j: F.least(F.lit(3), F.coalesce(F.get(p, j + 1), x + 3) - x)), F.lit(0), lambda a, b: a + b)
    n_lines = F.size(f"{at}_lines")
    each = {
        "n_words": F.col(f"{at}_n"),
        "word_chars": F.length(F.regexp_replace(text, SPACE, "")),
        "n_symbols": F.length(F.regexp_replace(text, NO_SYMBOL, "")),
        "n_lines": n_lines,
        "n_dup_lines": n_lines - F.size(F.array_distinct(f"{at}_lines")),
        "n_repeat_words": F.coalesce(covered, F.lit(0)),
    }
    q = F.struct(*(each[m].cast("long").alias(m) for m in only))
    return four.select(*(F.col(f"`{c}`") for c in docs.columns), q.alias(at))


def failures(q: str) -> dict[str, Column]:
    c = lambda name: F.col(f"{q}.{name}")
    return {
        "short": c("n_words") < 50,
        "repeats": 100 * c("n_repeat_words") > 50 * c("n_words"),
        "symbols": 10 * c("n_symbols") > c("word_chars"),
        "copied_lines": 100 * c("n_dup_lines") > 30 * c("n_lines"),
    }


def host_counts(measures: DataFrame, host: str, q: str) -> DataFrame:
    """(host, n, failures of each rule), written once: one row per host."""
    fails = failures(q)
    hosts = measures.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n"), *(F.sum(F.when(fails[r], 1).otherwise(0)).alias(r) for r in RULES))
    return stored(hosts, "hosts")


def host_verdicts(hosts: DataFrame, host_limit: float) -> DataFrame:
    """(host, n, rate of each rule, host_rejected) from the counts of ``host_counts``."""
    total = hosts.agg(F.sum("n").alias("all_n"), F.count("*").alias("hosts"), *(F.sum(r).alias(f"all_{r}") for r in RULES))
    hosts = hosts.join(F.broadcast(total))  # one row
    mean = {r: F.col(f"all_{r}") / F.col("all_n") for r in RULES}
    spread = hosts.agg(
        *(F.sum(F.col("n") * (F.col(r) / F.col("n") - mean[r]) * (F.col(r) / F.col("n") - mean[r])).alias(f"dev_{r}") for r in RULES),
    )
    hosts = hosts.join(F.broadcast(spread))  # one row
    shrunk = []
    for r in RULES:
        noise = F.col("hosts") * mean[r] * (1 - mean[r])
        between = F.greatest((F.col(f"dev_{r}") - noise) / F.col("all_n"), F.lit(1e-9))
        strength = F.least(F.greatest(mean[r] * (1 - mean[r]) / between - 1, F.lit(2.0)), F.lit(1000.0))
        shrunk.append(((F.col(r) + mean[r] * strength) / (F.col("n") + strength)).alias(f"rate_{r}"))
    out = hosts.select("host", "n", *shrunk)
    return out.withColumn("host_rejected", F.greatest(*(F.col(f"rate_{r}") for r in RULES)) > host_limit)


def _rejected(hosts: DataFrame, host_limit: float) -> DataFrame:
    """(q_host) of the rejected hosts; broadcast behind a check of their number."""
    out = stored(host_verdicts(hosts, host_limit).where("host_rejected").select(F.col("host").alias("q_host"), F.lit(True).alias("q_rejected")), "rejected")
    return F.broadcast(out) if out.count() <= BROADCAST_HOSTS else out


BASE_MEASURES = ("n_words", "n_repeat_words")


def base_failed(q: str) -> Column:
    fails = failures(q)
    return fails["short"] | fails["repeats"]


def judge(docs: DataFrame, *, host: str = "source", host_limit: float = 0.5) -> DataFrame:
    """Per row of ``docs``: doc_id, measures, base_failed, kept."""
    measures = stored(measured(docs.select("doc_id", F.col(host).alias("host"), "text")).select("doc_id", "host", "q"), "measures")
    out = measures.join(_rejected(host_counts(measures, "host", "q"), host_limit), F.col("host").eqNullSafe(F.col("q_host")), "left")
    failed = base_failed("q")
    return out.select("doc_id", "q.n_words", "q.word_chars", "q.n_symbols", "q.n_dup_lines", "q.n_repeat_words", failed.alias("base_failed"), (~failed & F.col("q_rejected").isNull()).alias("kept"))


def keep_good(docs: DataFrame, *, host: str = "source", host_limit: float = 0.5) -> DataFrame:
    """``docs`` without the documents that the rules or their host's verdict reject.

    Texts are measured twice, for the hosts and for the verdicts, so that none is written or moved."""
    at = "q"
    while any(c.startswith(at) for c in docs.columns):
        at += "q"
    rejected = _rejected(host_counts(measured(docs.select(F.col(host).alias("host"), "text")), "host", "q"), host_limit)
    # the row number keeps the measures from being written out anew inside the filter
    full = measured(docs, at, BASE_MEASURES).withColumn(f"{at}_row", F.monotonically_increasing_id()).where(~base_failed(at) & (F.col(f"{at}_row") >= 0))
    return full.join(rejected, F.col(f"`{host}`").eqNullSafe(F.col("q_host")), "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))


ORACLE = """
with d as (
  select row_number() over () as rid, doc_id, source as host, coalesce(text, '') as t from documents
), w as (
  select rid, list_filter(string_split_regex(t, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as ws,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as ls from d
), pos as (
  select rid, ws, unnest(range(0, greatest(len(ws) - 2, 0))) as i from w
), win as (
  select rid, i, count(*) over (partition by rid, ws[i + 1], ws[i + 2], ws[i + 3]) as c from pos
), cover as (
  select rid, count(distinct i + k) as r from win cross join range(0, 3) as o(k) where c > 1 group by rid
), m as (
  select d.doc_id, d.host, len(w.ws)::bigint as n_words,
         length(regexp_replace(d.t, '[\\x20\\x09-\\x0D]+', '', 'g'))::bigint as word_chars,
         length(regexp_replace(d.t, '[^#*$%&|<>]+', '', 'g'))::bigint as n_symbols,
         len(w.ls)::bigint as n_lines, (len(w.ls) - len(list_distinct(w.ls)))::bigint as n_dup_lines,
         coalesce(cover.r, 0)::bigint as n_repeat_words
  from d join w using (rid) left join cover using (rid)
), f as (
  select *, (n_words < 50)::int as f1, (100 * n_repeat_words > 50 * n_words)::int as f2,
         (10 * n_symbols > word_chars)::int as f3, (100 * n_dup_lines > 30 * n_lines)::int as f4 from m
), h as (
  select host, count(*) as n, unnest([1, 2, 3, 4]) as rule, unnest([sum(f1), sum(f2), sum(f3), sum(f4)]) as bad from f group by host
), g as (
  select rule, sum(n) as all_n, count(*) as hosts, sum(bad) / sum(n) as mean from h group by rule
), v as (
  select rule, any_value(all_n) as all_n, any_value(hosts) as hosts, any_value(mean) as mean, sum(n * (bad / n - mean) * (bad / n - mean)) as dev
  from h join g using (rule) group by rule
), s as (
  select rule, mean, least(greatest(mean * (1 - mean) / greatest((dev - hosts * mean * (1 - mean)) / all_n, 1e-9) - 1, 2.0), 1000.0) as strength from v
), r as (
  select host, max((bad + mean * strength) / (n + strength)) > 0.5 as rejected from h join s using (rule) group by host
)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (f1 = 1 or f2 = 1) as base_failed,
       not (f1 = 1 or f2 = 1) and not rejected as kept
from f join r on f.host is not distinct from r.host
"""
