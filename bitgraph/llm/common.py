"""Shared pieces of the text operators: tables, word splitting and row keys.

Words come in two kinds: *plain* words are runs without ASCII white space, *alnum* words are runs of ASCII
letters, digits and all non-ASCII characters. Lower-casing touches A-Z only, so that results do not depend on
a locale or a Unicode version.
"""

from __future__ import annotations

import string
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bitgraph.store import Scratch  # noqa: F401  for the operators

#: ASCII white space, and the characters that end an alnum word after lower-casing.
SPACE = r"[\x20\x09-\x0D]+"
NOT_ALNUM = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_ascii(col: Column) -> Column:
    """A-Z to a-z and nothing else. lower() is faster, and the same where no other character has a lower case."""
    others = col.rlike(r"[\p{Lu}\p{Lt}\p{Nl}\p{So}&&[^A-Z]]")
    return F.when(others, F.translate(col, string.ascii_uppercase, string.ascii_lowercase)).otherwise(F.lower(col))


def whole(col: str | Column) -> Column:
    """The text with null as empty."""
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def plain_words(text: Column) -> Column:
    return F.filter(F.split(text, SPACE), lambda w: w != "")


def alnum_words(text: Column) -> Column:
    return F.filter(F.split(lower_ascii(text), NOT_ALNUM), lambda w: w != "")


def adjacent(a: Column, b: Column, shift: int, size: Column, body) -> Column:
    """body(a[i], b[i + shift]) for the first ``size`` positions: a lambda without index arithmetic, which is slow."""
    return F.zip_with(F.slice(a, F.lit(1), size), F.slice(b, F.lit(1 + shift), size), body)


def gram_hashes(words: Column, width: int) -> Column:
    """A 64-bit hash of each run of ``width`` words (2 or more), from hashes of runs of half the length.

    Every array of hashes is named once: an expression that is mentioned twice is computed twice.
    """
    none = F.array().cast("array<bigint>")
    mix = lambda a, b: F.xxhash64(a, b)

    def grow(runs: dict[int, Column]) -> Column:
        have = max(runs)
        if 2 * have <= width:
            return let(adjacent(runs[have], runs[have], have, F.size(words) - (2 * have - 1), mix), lambda h: grow(runs | {2 * have: h}))
        return finish(runs, runs[have], have)

    def finish(runs: dict[int, Column], out: Column, have: int) -> Column:
        if have == width:
            return out
        part = max(k for k in runs if k <= width - have)
        return finish(runs, adjacent(out, runs[part], have, F.size(words) - (have + part - 1), mix), have + part)

    return F.when(F.size(words) < width, none).otherwise(let(F.transform(words, lambda w: F.xxhash64(w)), lambda h: grow({1: h})))


def let(value: Column, body) -> Column:
    """body(value), with value computed once however often body mentions it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def row_key(*cols: Column) -> Column:
    """A 128-bit key of a row's content, so that repeated ids with different texts stay apart."""
    return F.struct(F.xxhash64(*cols).alias("a"), F.xxhash64(F.lit(1), *cols).alias("b"))


#: The type of a row key.
ROW_KEY = "struct<a:bigint,b:bigint>"


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in pieces of a few rows, so that a worker holds little at once; memory kept for arrays that are gone is given back."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        pa.default_memory_pool().release_unused()


def covered(positions: Column, width: int) -> Column:
    """How many integers the windows [p, p + width) of the sorted distinct positions cover."""
    start = F.struct(F.lit(0).alias("n"), F.lit(-width - 1).alias("last"))
    step = lambda a, p: F.struct((a["n"] + F.least(F.lit(width), p - a["last"])).alias("n"), p.alias("last"))
    return F.aggregate(positions, start, step, lambda a: a["n"])
