"""The gates of the license rules lose no match."""

import random
import re
import time
from re import _parser as parser

from phasewise.llm import license_rules


def sample(rng, nodes):
    """A random text that the parsed pattern matches."""
    out = ""
    for kind, arg in nodes:
        if kind is parser.LITERAL:
            out += chr(arg)
        elif kind is parser.ANY:
            out += "x"
        elif kind is parser.IN:
            kind, c = rng.choice(arg)
            out += chr(c if kind is parser.LITERAL else rng.randint(*c))
        elif kind is parser.SUBPATTERN:
            out += sample(rng, arg[-1])
        elif kind is parser.BRANCH:
            out += sample(rng, rng.choice(arg[1]))
        else:
            low, high, inner = arg
            out += "".join(sample(rng, inner) for _ in range(rng.randint(low, min(high, low + 2))))
    return out


#: Texts without a word that most license texts hold, and a label of each.
NAMED = (("This tool is released under the MIT.", "mit"), ("Available under Apache 2.0", "apache-2"), ("distributed under the terms of the BSD 3-Clause", "bsd-3"), ("redistributed under the terms of Mozilla Public 2.0", "mpl"), ("for research use only", "research-only"))


def test_the_gates_lose_no_match(spark):
    rng = random.Random(10)
    texts = [f"Zz, {sample(rng, parser.parse(r.pattern))}. Zz" for r in license_rules.rules()] + [t for t, _ in NAMED]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8)
    got = sorted(tuple(map(str, r)) for r in license_rules.scan(docs).collect())
    assert got == sorted(tuple(map(str, r)) for r in license_rules.scan(docs, gated=False).collect())
    labels = {int(r[0]): r[6].split(",") for r in got}
    assert all(v != [""] for v in labels.values())
    for i, (_, label) in enumerate(NAMED, len(texts) - len(NAMED)):
        assert label in labels[i]


def brute(text):
    """(base labels, labels, score) by Python's regular expressions and all pairs of hits."""
    lower = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    words = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", lower)
    norm, hits = " " + " ".join(words) + " ", []
    for i, r in enumerate(license_rules.rules()):
        for m in re.finditer(f"(?<= )(?:{r.pattern})(?= )", norm):
            s, e = norm[: m.start()].count(" ") - 1, norm[: m.end()].count(" ")
            hits.append((r.priority, e - s, -i, s, e, r))
    base = len(license_rules.BASE)
    kept = [h for h in hits if -h[2] < base or not any(g[3] <= h[3] and h[4] <= g[4] and g[:3] > h[:3] for g in hits)]
    labels = lambda hs: ",".join(sorted({h[5].label for h in hs}))
    return labels([h for h in hits if -h[2] < base]), labels(kept), max((h[5].confidence for h in kept), default=0.0)


def test_labels_and_suppression_by_brute_force(spark, monkeypatch):
    rng = random.Random(11)
    parts = [sample(rng, parser.parse(r.pattern)) for r in license_rules.rules()]
    parts += [t for t, _ in NAMED] + ["Apache License, Version 2.0", "GNU General Public License v3", "und so weiter", "é K", "the", "of"]
    texts = ["; ".join(rng.choice(parts) for _ in range(rng.randint(1, 9))) for _ in range(150)] + parts[:: 5] + ["", "cc by nc " * 40, "mit license " * 700]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8)
    want = {i: brute(t) for i, t in enumerate(texts)}
    assert {r.doc_id: (r.base_labels, r.labels, r.score) for r in license_rules.scan(docs).collect()} == want
    monkeypatch.setattr(license_rules, "BACK", ())  # every hit looks back over all
    assert {r.doc_id: (r.base_labels, r.labels, r.score) for r in license_rules.scan(docs).collect()} == want


def test_ten_thousand_matches_take_seconds(spark):
    text = "released under the MIT License, " * 10_000
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    license_rules.scan(docs.limit(0)).collect()
    began = time.perf_counter()
    row = license_rules.scan(docs).head()
    assert (row.n_base, row.first_word, row.last_word, row.labels) == (10_000, 1, 49_996, "mit") and time.perf_counter() - began < 60


def test_there_are_hundreds_of_written_rules():
    assert len(license_rules.NOTICES) + len(license_rules.written()) >= 250
