"""The relational twin of the tree: a row for each node with the mask of its children, built by bit_or, level by level."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitgraph.functions.geometry import Schedule, cell_code, decode_cell


def nodes(ids: DataFrame, schedule: Schedule) -> DataFrame:
    """(p_id, level, code, mask): masks in this order are T, then the last level's bits. Factors up to 4."""
    points = ids.select("p_id", cell_code(F.col("s_id") - 1, F.col("o_id") - 1, schedule).alias("code"))
    below, levels = 2 * sum(schedule.bits), []
    for level, b in enumerate(schedule.bits):
        below -= 2 * b
        child = F.shiftright("code", below).bitwiseAND((1 << (2 * b)) - 1)
        mask = F.bit_or(F.expr("1L") * F.pow(F.lit(2.0), child).cast("bigint")).alias("mask")
        levels.append(points.groupBy("p_id", F.lit(level).alias("level"), F.shiftright("code", below + 2 * b).alias("code")).agg(mask))
    return reduce(lambda a, b: a.unionAll(b), levels)


class NodeTable:
    """Patterns by joins down the levels; a second implementation to test the packed one with."""

    def __init__(self, table: DataFrame, schedule: Schedule):
        self.table, self.schedule = table, schedule

    def match(self, s: int | None = None, p: int | None = None, o: int | None = None) -> DataFrame:
        row, col = (None if v is None else v - 1 for v in (s, o))
        out, below = self.table.select("p_id").distinct().withColumn("code", F.lit(0).cast("bigint")), sum(self.schedule.bits)
        if p is not None:
            out = out.where(F.col("p_id") == p)
        for level, b in enumerate(self.schedule.bits):
            below -= b
            k = 1 << b
            digit = lambda v: None if v is None else (v >> below) & (k - 1)  # noqa: B023, E731
            children = [c for c in range(k * k) if digit(row) in (None, c >> b) and digit(col) in (None, c & (k - 1))]
            if max(row or 0, col or 0) >= self.schedule.side:
                children = []
            here = self.table.where(F.col("level") == level).select("p_id", "code", "mask")
            options = F.array(*[F.when(F.col("mask").bitwiseAND(1 << c) != 0, F.lit(c)) for c in children]) if children else F.array().cast("array<int>")
            out = out.join(here, ["p_id", "code"]).select("p_id", "code", F.explode(F.array_compact(options)).alias("c"))
            out = out.select("p_id", F.shiftleft("code", 2 * b).bitwiseOR(F.col("c")).alias("code"))
        r, c = decode_cell(F.col("code"), self.schedule)
        return out.select((r + 1).alias("s_id"), "p_id", (c + 1).alias("o_id"))
