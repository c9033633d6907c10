"""License scans: phrases, and an exact containment join of text blocks with license templates.

The join finds every pair of a block (a sentence of a line) and a template of which the block holds at least the given
share of distinct tokens. Tokens of the templates are ordered by the number of texts that hold them, rarest first. A block
that reaches the threshold must hold one of a template's first tokens (prefix filter), enough tokens (length filter),
and from the first common token on enough tokens on both sides (positional filter). What passes is counted exactly.
Templates are parameters, so that they alone bound what is broadcast. All of it is DataFrame expressions.

A notice that is wrapped over lines or runs over sentences has no such block. ``window_join`` finds it in any run of words
of a template's length, with room for SLACK, whatever stands between the words.

Defined results: null text is empty, has no words and no labels; equal rows get equal results; an empty table gives an
empty result; columns of other names are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from functools import reduce
from math import ceil
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import NOT_ALNUM, alnum_words, lower_ascii, row_key, whole

#: Base phrases and their labels.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}

#: Short notices and first sentences of common licenses, with the label of each.
TEMPLATES = (
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("apache-2", "licensed under the apache license version 2 0"),
    ("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("cc-by-sa", "this work is licensed under a creative commons attribution sharealike 4 0 international license"),
    ("cc-by-nc", "this work is licensed under a creative commons attribution noncommercial 4 0 international license"),
    ("gpl-3", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
)
CONTAINMENT = Fraction(4, 5)
#: Words of a window for each word of a template.
SLACK = Fraction(5, 4)
#: A block ends at a line's end, or behind a sentence's last mark and white space.
BLOCK_END = r"\n|(?<=[.!?;])[\x20\t\r]+"


@dataclass(frozen=True)
class Template:
    id: int
    label: str
    tokens: frozenset[str]
    n_words: int

    @property
    def width(self) -> int:
        return ceil(SLACK * self.n_words)

    @property
    def need(self) -> int:
        return ceil(CONTAINMENT * len(self.tokens))

    def prefix(self, rank: dict[str, int]) -> list[str]:
        """Its tokens, rarest first, of which a block that reaches the threshold holds one."""
        return sorted(self.tokens, key=rank.__getitem__)[: len(self.tokens) - self.need + 1]


def make_templates(pairs=TEMPLATES) -> list[Template]:
    return [Template(i, label, frozenset(text.split()), len(text.split())) for i, (label, text) in enumerate(pairs)]


def phrase_starts(words: str, joined: str, phrases: dict[str, str] = PHRASES) -> Column:
    """Array of (at, label), one for each place of a phrase; ``joined`` is the words with a space round each."""
    def starts(phrase: str, label: str) -> Column:
        tokens = phrase.split()
        here = lambda i: reduce(and_, [F.get(F.col(words), i + k) == t for k, t in enumerate(tokens)])
        at = F.filter(F.sequence(F.lit(0), F.size(words) - len(tokens)), here)
        found = F.transform(at, lambda i: F.struct(i.cast("long").alias("at"), F.lit(label).alias("label")))
        return F.when(F.contains(F.col(joined), F.lit(f" {phrase} ")), found).otherwise(F.array().cast("array<struct<at:bigint,label:string>>"))

    return F.flatten(F.array(*[starts(p, x) for p, x in phrases.items()]))


def token_order(docs: DataFrame, templates: list[Template], text: str = "text") -> dict[str, int]:
    """Rank of each template token by the number of texts with it, ties by the token. As many rows as template tokens."""
    vocabulary = sorted(set().union(*[t.tokens for t in templates]))
    held = F.array_intersect(alnum_words(whole(text)), F.array(*[F.lit(x) for x in vocabulary]))
    # an inner explode would compute its array a second time, to filter by its size
    counts = {r["token"]: r["n"] for r in docs.select(F.explode_outer(held).alias("token")).where("token IS NOT NULL").groupBy("token").agg(F.count("*").alias("n")).collect()}
    return {x: i for i, x in enumerate(sorted(vocabulary, key=lambda x: (counts.get(x, 0), x)))}


def containment_join(docs: DataFrame, templates: list[Template], rank: dict[str, int], key: list[str], text: str = "text") -> DataFrame:
    """(*key, block, template, label, common, containment) of every block and template at or over the threshold.

    ``block`` counts a text's blocks from 0.
    """
    spark = docs.sparkSession
    index = [(t.label, t.id, rank[x], i, len(t.tokens), t.need, sorted(rank[y] for y in t.tokens)) for t in templates for i, x in enumerate(t.prefix(rank))]
    index_df = spark.createDataFrame(index, "label string, template int, token int, at_t int, n_t int, need int, tokens array<int>")
    first = sorted({x for t in templates for x in t.prefix(rank)})
    ranks = F.create_map(*[F.lit(v) for x, i in rank.items() for v in (x, i)])
    vocabulary = F.array(*[F.lit(x) for x in rank])
    least = min(t.need for t in templates)

    lowered = docs.select(*key, lower_ascii(whole(text)).alias("t"))
    held = F.array_intersect(F.split("t", NOT_ALNUM), F.array(*[F.lit(x) for x in first]))
    blocks = lowered.where(F.size(held) > 0).select(*key, F.posexplode_outer(F.split("t", BLOCK_END)).alias("block", "b"))
    mine = F.array_intersect(F.split("b", NOT_ALNUM), vocabulary)
    blocks = blocks.select(*key, "block", mine.alias("mine")).where(F.size("mine") >= least)
    blocks = blocks.select(*key, "block", F.sort_array(F.transform("mine", lambda x: F.element_at(ranks, x))).alias("b_tokens"))
    prefixes = blocks.select(*key, "block", "b_tokens", F.posexplode("b_tokens").alias("at_b", "token"))
    n_b = F.size("b_tokens")
    room = F.least(F.col("n_t") - F.col("at_t"), n_b - F.col("at_b"))
    near = prefixes.join(F.broadcast(index_df), "token").where((n_b >= F.col("need")) & (room >= F.col("need")))
    # The first common token is the only one whose place bounds all the rest, so a pair is counted once, at that token.
    found = F.array_intersect("b_tokens", "tokens")
    near = near.withColumn("common", found).where((F.size("common") >= F.col("need")) & (F.get("common", F.lit(0)) == F.col("token")))
    return near.select(*key, "block", "template", "label", F.size("common").alias("common"), (F.size("common") / F.col("n_t")).alias("containment"))


def window_join(docs: DataFrame, templates: list[Template], rank: dict[str, int], key: list[str], text: str = "text") -> DataFrame:
    """(*key, label, containment) of every text and template with a window that holds enough of the template's tokens.

    Only texts that hold as many of a template's tokens at all have their windows looked at, one from each such token.
    """
    spark = docs.sparkSession
    rows = [(t.id, t.label, sorted(t.tokens), len(t.tokens), t.need, t.width) for t in templates]
    sent = F.broadcast(spark.createDataFrame(rows, "template int, label string, tokens array<string>, n_t int, need int, width int"))
    first = sorted({x for t in templates for x in t.prefix(rank)})
    words = docs.select(*key, alnum_words(whole(text)).alias("w"))
    words = words.where(F.arrays_overlap("w", F.array(*[F.lit(x) for x in first]))).withColumn("mine", F.array_intersect("w", F.array(*[F.lit(x) for x in rank])))
    pairs = words.join(sent, F.size(F.array_intersect("mine", "tokens")) >= F.col("need"))
    at = F.transform("w", lambda x, i: F.when(F.array_contains("tokens", x), F.struct(i.alias("i"), x.alias("x"))))
    pairs = pairs.select(*key, "label", "n_t", "need", "width", F.filter(at, lambda h: h.isNotNull()).alias("hits"))

    def held(h: Column, k: Column) -> Column:
        window = F.filter(F.slice("hits", k + 1, F.col("width")), lambda g: g["i"] < h["i"] + F.col("width"))
        return F.size(F.array_distinct(F.transform(window, lambda g: g["x"])))

    most = pairs.select(*key, "label", "n_t", "need", F.array_max(F.transform("hits", held)).alias("most")).where(F.col("most") >= F.col("need"))
    return most.select(*key, "label", (F.col("most") / F.col("n_t")).alias("containment"))


def scan(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", templates: list[Template] | None = None, windows: bool = False) -> DataFrame:
    """With ``windows``, templates are also looked for over lines and sentences.

    doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score (best containment, 1 with a phrase).
    """
    templates = make_templates() if templates is None else templates
    rank = token_order(docs, templates, text)
    keyed = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).withColumn("key", row_key(F.col("doc_id"), whole("text")))
    pairs = containment_join(keyed, templates, rank, ["key"]).select("key", "label", "containment")
    if windows:
        pairs = pairs.union(window_join(keyed, templates, rank, ["key"]))
    pairs = pairs.groupBy("key").agg(F.collect_set("label").alias("found"), F.max("containment").alias("best"))
    base = keyed.select("doc_id", "key", alnum_words(whole("text")).alias("w")).withColumn("joined", F.concat(F.lit(" "), F.array_join("w", " "), F.lit(" ")))
    base = base.select("doc_id", "key", F.size("w").cast("long").alias("n_words"), phrase_starts("w", "joined").alias("p"))
    base = base.select("*", F.transform("p", lambda x: x["at"]).alias("at"), F.array_distinct(F.transform("p", lambda x: x["label"])).alias("l"))
    join_sorted = lambda a: F.array_join(F.array_sort(a), ",")
    return base.join(pairs, "key", "left").select(
        "doc_id", "n_words", F.size("at").cast("long").alias("n_base"), F.array_min("at").alias("first_word"), F.array_max("at").alias("last_word"),
        join_sorted(F.col("l")).alias("base_labels"), join_sorted(F.array_union("l", F.coalesce("found", F.array().cast("array<string>")))).alias("labels"),
        F.when(F.size("at") > 0, F.lit(1.0)).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"),
    )
