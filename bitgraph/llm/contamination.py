"""Benchmark decontamination by winnowing, in DataFrame expressions only.

A window is a run of WINDOW words of an item (a shorter item is one window). Of every WINDOW - K + 1 consecutive K-gram
hashes, texts and items keep the smallest, so that a shared window shares a kept hash. Kept hashes of the texts are
joined with those of the items (items of fewer words by the hash of all their words), which leaves the texts that may hold
a window. In these a match is extended to the windows around it, which must equal an item's window word by word. So each
occurrence of each window is found, and nothing else, and words are copied from the few texts only.

What is broadcast is the items' side and the keys of the texts left, behind counts; larger ones are joined by a shuffle.

Defined results: null text has no words and no hits; an item without words has no windows; repeated rows get equal
results; an empty table on either side gives no hits; columns of other names are dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, adjacent, alnum_words, gram_hashes, let, row_key, whole

WINDOW = 10
K = 5
#: Rows of the items' side that may be broadcast (fingerprints of 8 bytes, windows of some 100).
MOST_FINGERPRINTS = 2_000_000
MOST_WINDOWS = 200_000
#: Keys of texts that may be broadcast (16 bytes each).
MOST_KEYS = 1_000_000


def _slide(h: Column, size: Column, width: int, body) -> Column:
    """body (least or greatest) over each run of ``width`` values of h, whose length is ``size``."""
    def build(a: Column, have: int) -> Column:
        if have == width:
            return a
        step = min(have, width - have)
        return let(adjacent(a, a, step, size - (have + step - 1), body), lambda x: build(x, have + step))

    return let(h, lambda a: build(a, 1))


def kept_hashes(words: str) -> Column:
    """Array of the distinct hashes that winnowing keeps. Empty for fewer than WINDOW words."""
    w = WINDOW - K + 1
    keep = lambda h: F.array_distinct(_slide(h, F.size(words) - (K - 1), w, lambda a, b: F.least(a, b)))
    return F.when(F.size(words) < WINDOW, F.array().cast("array<bigint>")).otherwise(let(gram_hashes(F.col(words), K), keep))


def run_hashes(words: Column, width: int) -> Column:
    """Array of a hash of each run of ``width`` words."""
    return F.transform(words, lambda w: F.xxhash64(w)) if width == 1 else gram_hashes(words, width)


def fingerprints(words: str) -> Column:
    """Array of (at, h): places and hashes that winnowing keeps. Empty for fewer than WINDOW words."""
    w = WINDOW - K + 1
    pad = F.array_repeat(F.lit(-(1 << 63)).cast("long"), w - 1)
    n = F.size(words) - (K - 1)

    def keep(h: Column) -> Column:
        least = _slide(h, n, w, lambda a, b: F.least(a, b))
        # A hash is at least the minimum of every run with it, so it is one of them if it equals the largest.
        largest = _slide(F.concat(pad, least, pad), n + (w - 1), w, lambda a, b: F.greatest(a, b))
        marked = F.zip_with(h, largest, lambda a, b: F.when(a == b, a))
        return F.filter(F.transform(marked, lambda x, i: F.struct(i.alias("at"), x.alias("h"))), lambda x: x["h"].isNotNull())

    none = F.array().cast("array<struct<at:int,h:bigint>>")
    return F.when(F.size(words) < WINDOW, none).otherwise(let(gram_hashes(F.col(words), K), keep))


def windows_of(words: Column, first: Column, width: int) -> Column:
    """Array of (start, width, gram) for each run of ``width`` words; ``first`` is the place of the first word."""
    starts = F.sequence(F.lit(0), F.size(words) - width)
    gram = lambda i: F.struct((first + i).alias("start"), F.lit(width).alias("width"), F.array_join(F.slice(words, i + 1, width), " ").alias("gram"))
    return F.when(F.size(words) >= width, F.transform(starts, gram)).otherwise(F.array().cast("array<struct<start:int,width:int,gram:string>>"))


def item_windows(items: DataFrame, item_id: str = "item_id", text: str = "text") -> DataFrame:
    """(gram, width, items): each distinct window and the sorted ids, as strings, of the items that hold it."""
    w = items.select(F.col(item_id).cast("string").alias("item"), alnum_words(whole(text)).alias("w")).where(F.size("w") > 0)
    short = F.array(F.struct(F.lit(0).alias("start"), F.size("w").alias("width"), F.array_join("w", " ").alias("gram")))
    rows = w.select("item", F.explode(F.when(F.size("w") < WINDOW, short).otherwise(windows_of(F.col("w"), F.lit(0), WINDOW))).alias("x"))
    return rows.groupBy(F.col("x.gram").alias("gram"), F.col("x.width").alias("width")).agg(F.sort_array(F.collect_set("item")).alias("items"))


def _bounded(df: DataFrame, most: int) -> DataFrame:
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def hits(docs: DataFrame, items: DataFrame, key: str = "key", text: str = "text", item_id: str = "item_id", item_text: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """(key, start, width, items): each place in a text of an item's window, once."""
    scratch = scratch or Scratch(docs.sparkSession)
    windows = scratch.keep(item_windows(items, item_id, item_text))
    item_words = items.select(alnum_words(whole(item_text)).alias("w"))
    prints = scratch.keep(item_words.select(F.explode(kept_hashes("w")).alias("h")).distinct())
    widths = [r["width"] for r in windows.where(F.col("width") < WINDOW).select("width").distinct().collect()]  # at most WINDOW - 1
    short = windows.where(F.col("width") < WINDOW).select(F.split("gram", " ").alias("w"))
    looked_for = prints
    for width in widths:
        looked_for = looked_for.union(short.where(F.size("w") == width).select(F.get(run_hashes(F.col("w"), width), F.lit(0)).alias("h")))
    found = F.flatten(F.array(kept_hashes("w"), *[F.array_distinct(run_hashes(F.col("w"), width)) for width in widths])) if widths else kept_hashes("w")
    # an inner explode would compute its array a second time, to filter by its size
    of_texts = docs.select(key, alnum_words(whole(text)).alias("w")).select(key, F.explode_outer(found).alias("h"))
    touched = scratch.keep(of_texts.join(_bounded(looked_for, MOST_FINGERPRINTS), "h", "left_semi").select(key).distinct())

    reach = WINDOW - K
    words = docs.select(key, text).join(_bounded(touched, MOST_KEYS), key, "left_semi").select(key, alnum_words(whole(text)).alias("w"))

    def around(f: Column) -> Column:
        first = F.greatest(f["at"] - reach, F.lit(0))
        return F.struct(f["h"].alias("h"), first.alias("first"), F.slice("w", first + 1, f["at"] + WINDOW - first).alias("near"))

    kept = words.withColumn("f", fingerprints("w")).select(key, F.explode_outer(F.transform("f", around)).alias("f")).select(key, "f.*")
    matched = kept.join(_bounded(prints, MOST_FINGERPRINTS), "h", "left_semi")
    places = matched.select(key, F.explode_outer(windows_of(F.col("near"), F.col("first"), WINDOW)).alias("x"))
    for width in widths:
        places = places.unionByName(words.select(key, F.explode_outer(windows_of(F.col("w"), F.lit(0), width)).alias("x")))
    equal = places.select(key, "x.*").join(_bounded(windows, MOST_WINDOWS), ["gram", "width"])
    return equal.groupBy(key, "start", "width").agg(F.first("items").alias("items"))


def covered_words(spans: Column) -> Column:
    """How many words the (start, width) pairs of an array sorted by start cover."""
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("to"))
    end = lambda x: x["start"] + x["width"]
    step = lambda a, x: F.struct((a["n"] + F.greatest(F.lit(0), end(x) - F.greatest(x["start"], a["to"]))).alias("n"), F.greatest(a["to"], end(x)).alias("to"))
    return F.aggregate(spans, zero, step, lambda a: a["n"].cast("long"))


def scan(docs: DataFrame, items: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, n_words, n_hit, items (sorted ids), spans (start, width of the hit windows) of every row of docs."""
    keyed = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).withColumn("key", row_key(F.col("doc_id"), whole("text")))
    by_key = hits(keyed, items).groupBy("key").agg(
        F.sort_array(F.collect_list(F.struct("start", "width"))).alias("spans"), F.sort_array(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    n_words = F.size(alnum_words(whole("text"))).cast("long").alias("n_words")
    out = keyed.select("doc_id", "key", n_words).join(by_key, "key", "left")
    none = lambda c, kind: F.coalesce(F.col(c), F.array().cast(kind)).alias(c)
    return out.select("doc_id", "n_words", F.coalesce(covered_words(F.col("spans")), F.lit(0).cast("long")).alias("n_hit"), none("items", "array<string>"), none("spans", "array<struct<start:int,width:int>>"))
