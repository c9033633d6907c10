"""Mixing sources to target weights by Pareto order sampling.

A source's target divided by its size is the copies that each of its words should get. The whole part is copied for
certain; of the rest, documents are ranked by their random odds divided by the odds of their inclusion probability, and
taken in that order until the words come nearest to what is left of the target. Random numbers are hashes of the rows,
so that reruns agree. Documents of one source have equal odds unless ``importance`` scales them, so that each of its words
is as likely to be taken as any other; those of different sources have not.

No source is ordered as a whole: ranks fall in ranges of equal probability, sums per range find the one where the target
is met, and only that range is ordered row by row.

Defined results: null text has size 0 and is taken 0 times; a null source is a source, last in order; repeated rows have
one random number and rank next to each other, each counted by itself; ties of ranks go by id, null first; an empty table gives an empty result; columns of other names are dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE, Scratch, whole

WEIGHTS = (1, 2, 3)
MOST_COPIES = 3
SEED = 20
#: Ranges of ranks that are summed before any row is ordered.
RANGES = 1 << 14


def size_of(text: str) -> Column:
    """Number of plain words."""
    t = F.trim(F.regexp_replace(whole(text), SPACE, " "))
    return F.when(t == "", F.lit(0)).otherwise(F.length(t) - F.length(F.replace(t, F.lit(" "), F.lit(""))) + 1).cast("long")


def targets(sources: DataFrame, weights: tuple[int, ...] = WEIGHTS, most_copies: int = MOST_COPIES) -> DataFrame:
    """(source, source_size) with ``target``: the weighted share of all sizes, no more than most_copies sizes.

    The weights go round in the code point order of the sources, null last. What a full source can't take is shared
    again by weight among the others. Sources are filled in the order of room per weight, so that one running sum tells
    for each whether those before it, full, leave it more than its room. One row a source comes together, of some 50 bytes:
ten million sources fit one task.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    place = F.pmod(F.row_number().over(order) - 1, F.lit(len(weights)))
    s = sources.withColumn("w", F.get(F.array(*[F.lit(float(x)) for x in weights]), place)).withColumn("room", F.col("source_size") * float(most_copies))
    fill = Window.orderBy(F.col("room") / F.col("w"), F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    all_rows = Window.partitionBy()
    s = s.withColumns({
        "left": F.sum("source_size").over(all_rows) - F.coalesce(F.sum("room").over(before), F.lit(0.0)),
        "open": F.sum("w").over(all_rows) - F.coalesce(F.sum("w").over(before), F.lit(0.0)),
    }).withColumn("full", F.col("left") * F.col("w") >= F.col("room") * F.col("open"))
    level = F.min(F.when(~F.col("full"), F.struct(F.col("room") / F.col("w"), F.col("left") / F.col("open")))).over(all_rows)
    return s.withColumn("level", level["col2"]).select("source", "source_size", F.when(F.col("full"), F.col("room")).otherwise(F.col("level") * F.col("w")).alias("target"))


def mix(docs: DataFrame, scratch: Scratch, weights: tuple[int, ...] = WEIGHTS, most_copies: int = MOST_COPIES, seed: int = SEED, carry: tuple[str, ...] = (), importance: str | None = None) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken of each row of docs (doc_id, text, source), with ``carry``.

    ``importance`` names a positive column that scales a row's inclusion odds; without it they are those of its source.
    """
    scale = F.coalesce(F.col(importance).cast("double"), F.lit(1.0)) if importance else F.lit(1.0)
    rows = scratch.keep(docs.select("doc_id", "source", *carry, size_of("text").alias("size"), F.xxhash64(F.col("doc_id"), F.lit(seed), whole("text")).alias("key"), scale.alias("scale")))
    sized = targets(rows.groupBy("source").agg(F.sum("size").alias("source_size")), weights, most_copies)
    sized = sized.withColumn("ratio", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    sized = sized.withColumn("whole", F.least(F.floor("ratio"), F.lit(most_copies))).withColumn("part", F.col("ratio") - F.col("whole"))
    sized = scratch.keep(sized.withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")))

    u = (F.shiftrightunsigned("key", 11) + F.lit(0.5)) / F.lit(float(1 << 53))
    odds = F.col("part") / (1 - F.col("part")) * F.col("scale")
    rank = F.when(F.col("part") > 0, u / (1 - u) / odds).otherwise(F.lit(float("inf")))
    ranked = rows.withColumnRenamed("source", "s").join(F.broadcast(sized) if _small(sized) else sized, F.col("s").eqNullSafe(F.col("source"))).drop("s")
    ranked = ranked.withColumn("rank", rank)
    # The share of a source that ranks before a row, were its odds those of the source: fine where the target is met.
    share = F.when(F.col("part") > 0, F.col("rank") * F.col("part") / (1 - F.col("part") + F.col("rank") * F.col("part"))).otherwise(F.lit(1.0))
    ranked = ranked.withColumn("range", F.least(F.floor(share * RANGES), F.lit(RANGES - 1)).cast("int"))

    sums = ranked.where("part > 0").groupBy("source", "range", "rest").agg(F.sum("size").alias("n"))
    up_to = Window.partitionBy("source").orderBy("range")
    sums = sums.withColumn("before", F.sum("n").over(up_to) - F.col("n"))
    met = scratch.keep(sums.where("before < rest AND before + n >= rest").groupBy("source").agg(F.min_by(F.struct("range", "before"), "range").alias("m")).select(F.col("source").alias("ms"), "m.*").withColumnsRenamed({"range": "met", "before": "met_before"}))
    ranked = ranked.join(F.broadcast(met) if _small(met) else met, F.col("source").eqNullSafe(F.col("ms")), "left").drop("ms")

    # In the range where the target is met: rows in order, while the middle of a row lies before the target.
    inside = F.col("range") == F.col("met")
    by_rank = Window.partitionBy("source", "range").orderBy("rank", "doc_id", "key")
    ordered = ranked.where(inside).withColumn("at", F.col("met_before") + F.sum("size").over(by_rank.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size"))
    edge = ordered.withColumn("extra", (F.col("at") + F.col("size") / 2 <= F.col("rest")).cast("int")).drop("at")
    others = ranked.where(F.coalesce(~inside, F.lit(True))).withColumn("extra", F.when(F.col("part") > 0, F.coalesce((F.col("range") < F.col("met")).cast("int"), F.lit(0))).otherwise(0))
    copies = F.least(F.col("whole") + F.col("extra"), F.lit(most_copies)).cast("long")
    out = others.unionByName(edge).withColumn("copies", copies)
    return out.select("doc_id", "source", *carry, "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


#: Rows of a table of sources that may be broadcast.
MOST_BROADCAST = 100_000


def _small(sources: DataFrame) -> bool:
    return sources.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST
