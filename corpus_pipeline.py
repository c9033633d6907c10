"""A training corpus from the documents table: identify, deduplicate, decontaminate, redact, mix.

Each stage takes (spark, docs, sf_dir) and works on all rows of its predecessor. All but the last return the columns of
documents. Rows may have nulls in any column; a stage keeps them unless its rule is about that column.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitgraph.llm import contamination, dedup, langid, mixing, secrets
from bitgraph.llm.common import Scratch, row_key, table, whole

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Least posterior of the language that a text is taken to be in.
LEAST_POSTERIOR = 0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops texts without a letter and those in no learned language for sure."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")
    model = langid.NaiveBayes.fit(langid.bounded_sample(labelled, "doc_id", langid.MOST_TRAINING))
    scored = model.predict(docs.select(*COLUMNS))
    return scored.where((F.col("lang_pred") != langid.UNKNOWN) & (F.col("score") >= LEAST_POSTERIOR)).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each component of similarity 0.8 on shingles of five words."""
    return dedup.representatives(docs.select(*COLUMNS), Scratch(spark))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents with a window of ten words of a benchmark item."""
    keyed = docs.select(*COLUMNS).withColumn("key", row_key(F.col("doc_id"), whole("text")))
    scratch = Scratch(spark)
    hit = scratch.keep(contamination.hits(keyed, table(spark, sf_dir, "benchmark"), scratch=scratch).select("key").distinct())
    sent = F.broadcast(hit) if hit.count() <= contamination.MOST_KEYS else hit
    return keyed.join(sent, "key", "left_anti").select(*COLUMNS)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces secrets in texts by the kind found; n_chars follows."""
    scanned = secrets.scan(docs.select(*COLUMNS), redacted=True)
    found = F.col("spans") != ""
    text = F.when(found, F.col("redacted")).otherwise(F.col("text"))
    return scanned.withColumn("text", text).withColumn("n_chars", F.when(found, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, with how many copies of each."""
    keyed, scratch = docs.select(*COLUMNS).withColumn("key", row_key(*[F.col(c) for c in COLUMNS])), Scratch(spark)
    rows = mixing.mix(keyed.withColumn("row", F.col("key")), scratch, carry=("row",)).groupBy(F.col("row").alias("key"))
    mixed = rows.agg(F.max("size").alias("size"), F.sum("copies").alias("copies"), F.sum("taken").alias("taken"), (F.count("*") > 1).alias("repeated"))
    taken = scratch.keep(mixed.where("copies > 0"))
    repeated = taken.where("repeated")
    sent = F.broadcast(repeated) if repeated.count() <= mixing.MOST_BROADCAST else repeated
    # texts are long: they are dealt out by key once, and a second time only where rows repeat
    out = keyed.join(taken.where("NOT repeated"), "key").union(keyed.join(sent, "key").dropDuplicates(["key"]))
    return out.select(*COLUMNS, "size", "copies", "taken")


STAGES = [("language_id", identify_language), ("near_dedup", drop_near_duplicates), ("decontamination", decontaminate), ("secret_redaction", redact_secrets), ("mixing", mix_sources)]

#: Hash sketches, a trained classifier and samples by hash are beyond the SQL of the oracle; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = table(spark, sf_dir, "documents"), Scratch(spark)
    for _, stage in STAGES[:-1]:
        docs = scratch.keep(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
