"""License scans, secrets, decontamination, quality and mixing against brute force."""

import hashlib
import re
from collections import Counter, defaultdict
from math import isclose

import pytest

from bitgraph.llm import contamination, licenses, mixing, queries, quality, secrets
from bitgraph.llm.common import Scratch

from .conftest import DATA, ODD_SCHEMA

ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
PLAIN = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def rows_of(df, *cols):
    return Counter(tuple(r) for r in df.select(*cols).collect())


def brute_licenses(t):
    w = ALNUM.findall(lower(t))
    at = [(i, label) for p, label in licenses.PHRASES.items() for i in range(len(w)) if w[i : i + len(p.split())] == p.split()]
    labels, best = {x for _, x in at}, 1.0 if at else 0.0
    for block in re.split(licenses.BLOCK_END, lower(t)):
        have = set(ALNUM.findall(block))
        for tpl in licenses.make_templates():
            if 5 * len(have & tpl.tokens) >= 4 * len(tpl.tokens):
                labels.add(tpl.label)
                best = max(best, len(have & tpl.tokens) / len(tpl.tokens))
    starts = [i for i, _ in at]
    return len(w), len(at), min(starts, default=None), max(starts, default=None), ",".join(sorted({x for _, x in at})), ",".join(sorted(labels)), best


def test_licenses(spark, docs, odd):
    extra = ["Released  under THE MIT-License! cc by nc cc by nc", "licensed under the\napache license version 2.0", "This work is licensed under the GNU General Public License, version 3.", "the gnu general public license version 3 this work is", "a b under the mit license"]
    more = spark.createDataFrame([(100_000 + i, t) for i, t in enumerate(extra)], "doc_id long, text string")
    both = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(more)
    got = rows_of(licenses.scan(both), "doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")
    assert got == Counter((r.doc_id, *brute_licenses(r.text)) for r in both.collect())
    assert licenses.scan(both.limit(0)).count() == 0


def brute_windows(t):
    w, labels, best = ALNUM.findall(lower(t)), set(), 0.0
    for tpl in licenses.make_templates():
        share = max((len(tpl.tokens.intersection(w[i : i + tpl.width])) / len(tpl.tokens) for i in range(len(w))), default=0.0)
        if share * len(tpl.tokens) > tpl.need - 0.5:
            labels.add(tpl.label)
            best = max(best, share)
    return labels, best


def test_notices_over_lines_and_sentences(spark, docs, odd):
    notices = [
        ("apache-2", "# You may not use this file except in compliance with the License.\n# You may obtain a copy of the License at\n"),
        ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files"),
        ("bsd", " * Redistribution and use in source and binary forms, with or without\n * modification, are permitted provided that the following conditions\n * are met:"),
        ("gpl", "This program is free software: you can redistribute it and/or modify\nit under the terms of the GNU General Public License as published"),
        ("mpl-2", "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0."),
    ]
    far = " filler" * 40 + " "
    more = [(i, f"Some prose.\n{t} and more.") for i, (_, t) in enumerate(notices)] + [(99, far.join(licenses.TEMPLATES[1][1].split()))]
    both = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(spark.createDataFrame([(200_000 + i, t) for i, t in more], "doc_id long, text string"))
    rows = licenses.scan(both, windows=True).collect()
    got = {r.doc_id: r.labels for r in rows}
    assert [got[200_000 + i] for i in range(len(notices))] == [label for label, _ in notices] and got[200_099] == "mit"
    want = Counter()
    for r in both.collect():
        base, (labels, best) = brute_licenses(r.text), brute_windows(r.text)
        want[r.doc_id, ",".join(sorted({x for x in base[5].split(",") if x} | labels)), max(base[6], best)] += 1
    assert Counter((r.doc_id, r.labels, r.score) for r in rows) == want


def test_secrets_base_and_links(spark, odd):
    key = "AKIA" + "ABCDEFGH12345678"
    weak = "wJalrXUtnFEMI7MDENGbPxRfiCYEXAMPLEKEY"
    texts = {
        1: f"token: password: abcdefghijkl and {key}", 2: 'API_KEY="abcdef123456" deadbeefdeadbeef0', 3: "Passwd=short token = 04dbebab91ab85687d33eeaaf9ac699e1188f962",
        4: f"client_id: alpha77\nvalue {weak}\nsee https://db.example.org/x", 5: f"value {weak} alone", 6: f"client_id: alpha77\n\n{weak}", 7: "ſecret=aaaaaaaaaaaaaaaa toKen=bbbbbbbbbbbbbbbbb",
    }
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: r for r in secrets.scan(df, redacted=True).collect()}
    assert [(got[i].n_assign, got[i].n_access, got[i].n_hex) for i in range(1, 8)] == [(0, 1, 0), (1, 0, 1), (1, 0, 1), (0, 0, 0), (0, 0, 0), (0, 0, 0), (0, 0, 2)]
    assert [s.split(":")[0] for s in got[4].spans.split(",")] == ["linked_id", "linked_secret", "linked_endpoint"]
    assert got[5].spans == got[6].spans == ""
    assert weak not in got[4].redacted and weak in got[5].redacted
    base = ["hex:%d:%d" % m.span() for m in re.finditer("[0-9a-f]{16,}", texts[2])]
    a = re.search("API.*6", texts[2])
    assert got[2].base_sha256 == hashlib.sha256(",".join([f"assign:{a.start()}:{a.end()}", *base]).encode()).hexdigest()
    assert secrets.scan(odd).count() == odd.count() and secrets.scan(odd.limit(0)).count() == 0


def test_secrets_of_any_length_and_distance_in_a_scope():
    weak = "".join(hashlib.sha256(b"%d" % i).hexdigest().replace("0", "Gh") for i in range(4))
    long_id, words = "user" + "x7" * 60, "some words " * 200
    for text in (f"client_id: alpha77 {weak} https://db.example.org/x", f"client_id: {long_id} {weak}", f"client_id: alpha77\n{words}\n{weak}\n{words}\nhttps://db.example.org/x"):
        spans = secrets.linked_spans(text, secrets.base_spans(text))
        out = secrets.redact(text, secrets.base_spans(text) + spans)
        kinds = {secrets.KINDS[k] for _, k, _ in spans}
        assert {"linked_id", "linked_secret"} <= kinds and ("linked_endpoint" in kinds) == ("://" in text)
        assert not any(x in out for x in ("alpha77", "x7x7", weak[-20:], "example.org"))


def brute_contamination(docs, items):
    out = Counter()
    for i, t in docs:
        w = ALNUM.findall(lower(t))
        hit, found = set(), set()
        for item, x in items:
            iw = ALNUM.findall(lower(x))
            n = min(10, len(iw))
            grams = {tuple(iw[k : k + n]) for k in range(len(iw) - n + 1)} if iw else set()
            for k in range(len(w) - n + 1):
                if n and tuple(w[k : k + n]) in grams:
                    hit.update(range(k, k + n))
                    found.add(str(item))
        out[i, len(w), len(hit), ",".join(sorted(found))] += 1
    return out


def test_contamination(spark, docs, odd):
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()][:12] + [(900, "some words"), (901, None), (902, "..."), (903, items_text := "a b c d e f g h i j k"), (904, items_text)]
    more = [(500_000, "x A b c d e f g h i j"), (500_001, "a b c d e f g h i x b c d e f g h i j k l"), (500_002, " ".join(["a"] * 40))]
    both = docs.select("doc_id", "text").limit(80).union(odd.select("doc_id", "text")).union(spark.createDataFrame(more, "doc_id long, text string"))
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = Counter((r.doc_id, r.n_words, r.n_hit, ",".join(r["items"])) for r in contamination.scan(both, bench).collect())
    assert got == brute_contamination([(r.doc_id, r.text) for r in both.collect()], items)
    assert all(not r["items"] for r in contamination.scan(both, bench.limit(0)).collect())
    assert contamination.scan(both.limit(0), bench).count() == 0


def test_winnowing_is_the_same_by_both_ways_of_joining(spark, docs, monkeypatch):
    bench = spark.read.parquet(f"{DATA}/benchmark.parquet")
    one = rows_of(contamination.scan(docs, bench), "doc_id", "n_hit")
    monkeypatch.setattr(contamination, "MOST_FINGERPRINTS", 0)
    monkeypatch.setattr(contamination, "MOST_WINDOWS", 0)
    assert rows_of(contamination.scan(docs, bench), "doc_id", "n_hit") == one


def brute_quality(t):
    t = t or ""
    w = PLAIN.findall(t)
    grams = defaultdict(list)
    for k in range(len(w) - 4):
        grams[tuple(w[k : k + 5])].append(k)
    repeated = {p for v in grams.values() if len(v) > 1 for k in v for p in range(k, k + 5)}
    lines = [x for x in t.split("\n") if PLAIN.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(repeated)


def test_quality(spark, docs, odd):
    more = spark.createDataFrame([(900_000, "a b c d e a b c d e a b c d e f"), (900_001, "x\nx\n\nx\ny")], "doc_id long, text string")
    both = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(more)
    cols = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    cascade = quality.Cascade.fit(both)
    assert rows_of(cascade.apply(both, always=cols), "doc_id", *cols) == Counter((r.doc_id, *brute_quality(r.text)) for r in both.collect())
    kept = rows_of(cascade.apply(both), "doc_id", "kept")
    assert kept == rows_of(quality.Cascade(tuple(reversed(cascade.rules))).apply(both), "doc_id", "kept")
    assert quality.Cascade.fit(both.limit(0)).apply(both.limit(0)).count() == 0
    every = quality.features(both).select("doc_id", *quality.FEATURES)
    assert rows_of(every, "doc_id", *cols) == rows_of(cascade.apply(both, always=cols), "doc_id", *cols)


def test_a_rejected_row_skips_the_counts_of_later_rules(spark):
    docs = spark.createDataFrame([(1, "one two"), (2, "A B C D E F G H I J K L"), (3, "plain words of a text that is long enough to stay")], "doc_id long, text string")
    few, shouting, exclaiming = (next(r for r in quality.RULES if r.name == n) for n in ("few_words", "shouting", "exclaiming"))
    rows = {r.doc_id: r for r in quality.Cascade((few, shouting, exclaiming)).apply(docs).collect()}
    assert [rows[i].failed_rule for i in (1, 2, 3)] == ["few_words", "shouting", None]
    assert [rows[i].n_words for i in (1, 2, 3)] == [2, 12, 11]
    assert [rows[i].n_upper for i in (1, 2, 3)] == [None, 12, 0]
    assert [rows[i].n_exclaim for i in (1, 2, 3)] == [None, None, 0]


def brute_targets(sizes, weights=(1, 2, 3)):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(order)}
    total, full = sum(sizes.values()), {}
    while True:
        free = [s for s in order if s not in full]
        left = total - sum(full.values())
        share = {s: left * w[s] / max(1, sum(w[x] for x in free)) for s in free}
        over = [s for s in free if share[s] > 3 * sizes[s]]
        if not over:
            return full | share
        full |= {s: 3 * sizes[s] for s in over}


def test_importance_scales_the_odds_of_inclusion(spark):
    """Of documents of one size, those of nine times the odds are taken as often as Pareto sampling has it."""
    df = spark.range(4000).selectExpr("id AS doc_id", "concat('a b c d ', id) AS text", "IF(id % 4 = 0, 'y', 'x') AS source", "IF(id % 2 = 0, 9.0, 1.0) AS weight")
    rows = mixing.mix(df, Scratch(spark), importance="weight", carry=("weight",)).where("source = 'x'").collect()
    part = {w: [r.copies for r in rows if r.weight == w] for w in (9.0, 1.0)}
    often, seldom = (sum(c) / len(c) for c in (part[9.0], part[1.0]))
    total = (often * len(part[9.0]) + seldom * len(part[1.0])) / len(rows)
    assert isclose(total, rows[0].target / rows[0].source_size, abs_tol=0.01)
    assert isclose(often / (1 - often), 9 * seldom / (1 - seldom), rel_tol=0.35)


def test_secrets_of_a_long_text_take_linear_time():
    """Twice the text takes about twice the time, and the spans shift with the scopes."""
    part = "client_id: abcd1234efgh https://host.example/x Zx81Qw93Er27Ty65Ui40 " * 400
    once, twice = (secrets.linked_spans(t, secrets.base_spans(t)) for t in (part, part + "\n\n" + part))
    assert len(twice) == 2 * len(once) > 1000
    assert twice[len(once) :] != once and {k for _, k, _ in once} == {3, 4, 5}


def test_mixing(spark, docs, odd):
    skew = spark.createDataFrame([(10_000 + i, "w " * (i % 50), ["big", "tiny", None, "zz"][i % 97 % 4 if i % 97 < 4 else 0]) for i in range(3000)], "doc_id long, text string, source string")
    for df in (docs, odd, skew):
        rows = mixing.mix(df, Scratch(spark)).collect()
        texts = df.collect()
        assert Counter((r.doc_id, r.source, r.size) for r in rows) == Counter((r.doc_id, r.source, len(PLAIN.findall(r.text or ""))) for r in texts)
        sizes, taken, most = Counter(), Counter(), Counter()
        for r in rows:
            sizes[r.source] += r.size
            taken[r.source] += r.taken
            most[r.source] = max(most[r.source], r.size)
        want = brute_targets({s: sizes[s] for s in sizes})
        for r in rows:
            assert isclose(r.target, want[r.source], abs_tol=1e-6) and r.source_size == sizes[r.source] and 0 <= r.taken <= 3 * r.size
        for s in sizes:
            assert abs(taken[s] - want[s]) <= most[s] / 2 + 1e-6
        again = mixing.mix(df, Scratch(spark)).collect()
        assert Counter(map(tuple, rows)) == Counter(map(tuple, again))
    assert mixing.mix(docs.limit(0), Scratch(spark)).count() == 0


@pytest.mark.parametrize("name", ["op1_license_scans", "op2_secret_scans", "op4_mixing", "op6_decontamination", "op10_quality_rules"])
def test_queries_cover_the_table(spark, docs, name):
    assert queries.QUERIES[name](spark, DATA).count() == docs.count()
    assert ODD_SCHEMA
