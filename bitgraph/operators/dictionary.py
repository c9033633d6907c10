"""Term dictionary: roles, dense lexicographic IDs in four categories, encoding and decoding.

Terms in both roles come first with one ID for both; subject-only and object-only terms follow in ranges of their own,
which overlap. So an ID means a term only together with its role.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitgraph.store import Scratch

SUBJECT, OBJECT = 1, 2
ROLE_NAMES = {SUBJECT | OBJECT: "SO", SUBJECT: "S", OBJECT: "O"}
#: Rows of a dictionary side that may be broadcast.
MOST_BROADCAST = 500_000


def roles(triples: DataFrame) -> DataFrame:
    """(term, role), role one of SO, S and O. Each task first folds the uses that it sees."""
    uses = triples.select(F.col("s").alias("term"), F.lit(SUBJECT).alias("use")).unionAll(triples.select(F.col("o").alias("term"), F.lit(OBJECT).alias("use")))
    flag = uses.groupBy("term").agg(F.bit_or("use").alias("f"))
    name = F.when(F.col("f") == 3, "SO").when(F.col("f") == SUBJECT, "S").otherwise("O")
    return flag.select("term", name.alias("role"))


def _dense(rows: DataFrame, scratch: Scratch, category: Column, term: str) -> tuple[DataFrame, dict[int, int]]:
    """rows with ``at``: 0, 1, ... in the order of ``term`` within each category, and the size of each category.

    A range shuffle sorts globally; per-partition counts, a few rows a partition, give each partition its offset.
    """
    ranged = rows.withColumn("c", category).repartitionByRange("c", term).sortWithinPartitions("c", term).withColumn("i", F.monotonically_increasing_id())
    kept = scratch.keep(ranged)
    part = F.shiftright("i", 33).cast("int")
    counts = sorted((r["c"], r["part"], r["first"], r["n"]) for r in kept.groupBy("c", part.alias("part")).agg(F.min("i").alias("first"), F.count("*").alias("n")).collect())
    offsets, sizes = [], {}
    for c, p, first, n in counts:
        offsets.append((c, p, sizes.get(c, 0) - first))
        sizes[c] = sizes.get(c, 0) + n
    table = rows.sparkSession.createDataFrame(offsets or [(-1, -1, 0)], "c int, part int, shift bigint")
    return kept.withColumn("part", part).join(F.broadcast(table), ["c", "part"]).withColumn("at", F.col("i") + F.col("shift")).drop("part", "i", "shift"), sizes


def assign(roles_df: DataFrame, scratch: Scratch) -> tuple[DataFrame, dict[str, int]]:
    """(term, role, s_id, o_id), and n_so, n_s, n_o. IDs count from 1; a term without a role has null there."""
    order = F.when(F.col("role") == "SO", 0).when(F.col("role") == "S", 1).otherwise(2)
    rows, sizes = _dense(roles_df, scratch, order, "term")
    n_so, n_s, n_o = (sizes.get(c, 0) for c in range(3))
    after = F.col("at") + 1 + F.when(F.col("role") == "SO", 0).otherwise(n_so)
    none = F.lit(None).cast("bigint")
    terms = rows.select("term", "role", F.when(F.col("role") == "O", none).otherwise(after).alias("s_id"), F.when(F.col("role") == "S", none).otherwise(after).alias("o_id"))
    return scratch.keep(terms), {"n_so": n_so, "n_s": n_s, "n_o": n_o}


def predicates(triples: DataFrame, scratch: Scratch) -> DataFrame:
    """(pred, p_id, n_triples, n_subj, n_obj)."""
    counts = triples.groupBy("p").agg(F.count("*").alias("n_triples"), F.countDistinct("s").alias("n_subj"), F.countDistinct("o").alias("n_obj"))
    rows, _ = _dense(counts, scratch, F.lit(0), "p")
    return scratch.keep(rows.select(F.col("p").alias("pred"), (F.col("at") + 1).alias("p_id"), "n_triples", "n_subj", "n_obj"))


def predicate_names(triples: DataFrame, scratch: Scratch) -> DataFrame:
    """(pred, p_id) as in ``predicates``, without the counts of distinct terms, which take two more shuffles of all facts."""
    rows, _ = _dense(triples.select("p").distinct(), scratch, F.lit(0), "p")
    return scratch.keep(rows.select(F.col("p").alias("pred"), (F.col("at") + 1).alias("p_id")))


def _maybe_broadcast(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST else df


def encode(triples: DataFrame, terms: DataFrame, preds: DataFrame) -> DataFrame:
    """(s_id, p_id, o_id)."""
    s = terms.where("s_id IS NOT NULL").select(F.col("term").alias("s"), "s_id")
    o = terms.where("o_id IS NOT NULL").select(F.col("term").alias("o"), "o_id")
    p = preds.select(F.col("pred").alias("p"), "p_id")
    return triples.join(_maybe_broadcast(p), "p").join(s, "s").join(o, "o").select("s_id", "p_id", "o_id")


def decode(df: DataFrame, terms: DataFrame, preds: DataFrame, columns: dict[str, str]) -> DataFrame:
    """df with IDs replaced by terms. ``columns``: name to 's', 'o' or 'p'; a shared variable may be read in either role."""
    for name, role in columns.items():
        if role == "p":
            names = preds.select(F.col("p_id").alias("__id"), F.col("pred").alias("__term"))
        else:
            names = terms.where(f"{role}_id IS NOT NULL").select(F.col(f"{role}_id").alias("__id"), F.col("term").alias("__term"))
        df = df.join(names, df[name] == names["__id"], "left").drop("__id", name).withColumnRenamed("__term", name)
    return df


def lookup(terms: DataFrame, preds: DataFrame, constants: list[tuple[str, str]]) -> dict[tuple[str, str], int]:
    """IDs of (term, role) constants; those that never play the role are left out."""
    out: dict[tuple[str, str], int] = {}
    if wanted := sorted({t for t, r in constants if r != "p"}):
        for row in terms.where(F.col("term").isin(wanted)).collect():
            out |= {(row["term"], r): row[f"{r}_id"] for r in "so" if row[f"{r}_id"] is not None}
    if wanted := sorted({t for t, r in constants if r == "p"}):
        out |= {(row["pred"], "p"): row["p_id"] for row in preds.where(F.col("pred").isin(wanted)).collect()}
    return {k: out[k] for k in constants if k in out}
