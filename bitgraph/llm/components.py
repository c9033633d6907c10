"""Connected components of a distributed edge table, by alternating stars.

Each round points every node's larger neighbours, then its smaller ones, at the smallest node next to it. Edges stay as
many as they were, no neighbourhood is ever gathered in one place, and rounds grow with the logarithm of the diameter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

#: Edges that a file of a round holds: rounds are many and their tables small, as are then the files, without AQE.
EDGES_A_FILE = 1 << 19


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b")))


def components(edges: DataFrame, scratch: Scratch, most_rounds: int = 60, most: int | None = None) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b) that is not itself the smallest of its component. ``most``: rows of edges at most, if known."""
    packed = lambda df, n: df.coalesce(-(-n // EDGES_A_FILE) or 1)
    first = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now = scratch.keep(first if most is None else packed(first, most))
    seen = None
    for _ in range(most_rounds):
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark[0] == 0 or mark == seen:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        seen, old = mark, now
        now = scratch.keep(packed(_small_star(_large_star(old).distinct()).distinct(), mark[0]))  # no more edges than before
        scratch.drop(old)
    raise RuntimeError(f"components: not settled after {most_rounds} rounds")
