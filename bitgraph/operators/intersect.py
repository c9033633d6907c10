"""Intersection of ID lists: by merging, by galloping, by bitmaps. IDs are cut into blocks, so that no list is long."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: IDs of a block, the bits of one of Spark's bitmaps.
BLOCK = 32768
KERNELS = ("merge", "gallop", "bitmap")


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of two sorted lists without repeats, in time of both lengths: a stable sort merges the two runs."""
    both = np.sort(np.concatenate((a, b)), kind="stable")
    return both[:-1][both[1:] == both[:-1]]


def gallop(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Each entry of the shorter list is looked up in the longer one: for lengths that differ much."""
    short, long = (a, b) if len(a) <= len(b) else (b, a)
    if not len(short):
        return short
    at = np.searchsorted(long, short)
    return short[long[np.minimum(at, len(long) - 1)] == short]


def _listed(df: DataFrame, x: str, name: str) -> DataFrame:
    """(block, name): sorted distinct IDs of a block, at most BLOCK of them."""
    return df.select(F.col(x).alias("x")).groupBy(F.expr(f"(x - 1) DIV {BLOCK}").alias("block")).agg(F.sort_array(F.collect_set("x")).alias(name))


def intersect(left: DataFrame, right: DataFrame, x: str, kernel: str = "gallop") -> DataFrame:
    """Distinct IDs (from 1) in column ``x`` of both sides. Nulls are in neither."""
    left, right = (t.select(x).where(F.col(x).isNotNull()) for t in (left, right))
    if kernel == "bitmap":
        return _by_bitmaps(left, right, x)
    if kernel not in KERNELS:
        raise ValueError(f"no kernel named {kernel}")
    f = merge if kernel == "merge" else gallop
    pairs = _listed(left, x, "a").join(_listed(right, x, "b"), "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in zip(batch.column("a"), batch.column("b"), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(f(a.values.to_numpy(), b.values.to_numpy()), pa.int64())], names=[x])

    return pairs.select("a", "b").mapInArrow(run, f"{x} bigint")


def _by_bitmaps(left: DataFrame, right: DataFrame, x: str) -> DataFrame:
    """A bitmap a block and side, built and intersected by Spark's own aggregates."""
    side = lambda df, i: df.groupBy(F.bitmap_bucket_number(x).alias("block")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(x)).alias("bits")).withColumn("side", F.lit(i))
    both = side(left, 0).unionAll(side(right, 1)).groupBy("block").agg(F.count("*").alias("n"), F.bitmap_and_agg("bits").alias("bits")).where("n = 2")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, bits in zip(batch.column("block"), batch.column("bits"), strict=True):
                at = np.flatnonzero(np.unpackbits(np.frombuffer(bits.as_py(), np.uint8), bitorder="little"))
                yield pa.RecordBatch.from_arrays([pa.array(at + (block.as_py() - 1) * BLOCK + 1, pa.int64())], names=[x])

    return both.select("block", "bits").mapInArrow(run, f"{x} bigint")
