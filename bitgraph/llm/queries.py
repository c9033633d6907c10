"""The registered queries of the text operators and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import contamination, dedup, html, langid, licenses, lm, mixing, quality, secrets, toxicity
from .common import Scratch, table


def op1_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op1_license_notices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The license scan with notices wrapped over lines and sentences, which the SQL of op1_license_scans leaves out."""
    return licenses.scan(table(spark, sf_dir, "documents"), windows=True)


def op2_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans")


def op3_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract asks for shingles of two words; other users of the operator take five."""
    found = dedup.near_duplicates(table(spark, sf_dir, "documents"), Scratch(spark), width=2)
    return found.select("doc_id", "n_shingles", "component_id", "kept")


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"), Scratch(spark)).select("doc_id", "size", "source_size", "target", "taken")


def fold(modulus: int):
    """True for the rows that a query holds out of training; a null id is not."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % modulus == 0, F.lit(False))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    trained = langid.bounded_sample(docs.where(~fold(5) & F.col("lang").isNotNull()).select("doc_id", "lang", "text"), "doc_id", langid.MOST_TRAINING)
    model = langid.NaiveBayes.fit(trained)
    return model.predict(docs.select("doc_id", "text", fold(5).alias("held_out"))).select("doc_id", "held_out", "lang_pred", "score")


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    ids = F.sha2(F.array_join("items", ","), 256)
    return contamination.scan(docs, items).select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), ids.alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.NoisyOr.fit(toxicity.labelled_sample(docs, labels.where(~fold(5))))
    scored = model.score(docs.select("doc_id", "text", fold(5).alias("held_out")))
    return scored.select("doc_id", "held_out", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op8_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.main_text(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op9_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = table(spark, sf_dir, "documents").select("doc_id", "text"), Scratch(spark)
    model = lm.SuffixTree.fit(docs.where(~fold(10)), scratch)
    scored = model.score(docs, scratch)
    return scored.select("doc_id", fold(10).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    judged = quality.Cascade.fit(docs).apply(docs, always=("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"))
    base = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), (F.col("kept") & ~base).alias("kept"))


QUERIES = {"op1_license_scans": op1_license_scans, "op1_license_notices": op1_license_notices, "op2_secret_scans": op2_secret_scans, "op3_near_dedup": op3_near_dedup, "op4_mixing": op4_mixing, "op6_decontamination": op6_decontamination, "op5_language_id": op5_language_id, "op7_toxicity": op7_toxicity, "op8_main_text": op8_main_text, "op9_lm_score": op9_lm_score, "op10_quality_rules": op10_quality_rules}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PLAIN = r"[\x20\x09-\x0D]+"
_NOT_ALNUM = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _alnum(text: str) -> str:
    return f"list_filter(regexp_split_to_array({text}, '{_NOT_ALNUM}'), lambda x: x <> '')"


def _lowered(text: str) -> str:
    return f"translate(coalesce({text}, ''), '{_UPPER}', '{_LOWER}')"


def _license_sql() -> str:
    """Phrases by place, and the containment of every template in every block, without any filter."""
    phrases = ", ".join(f"('{label}', {len(p.split())}, '{p}')" for p, label in licenses.PHRASES.items())
    templates = ", ".join(f"({t.id}, '{t.label}', {sorted(t.tokens)!r}, {t.need})" for t in licenses.make_templates())
    blocks = r"string_split(regexp_replace(t, '([.!?;])[\x20\t\r]+', '\1' || chr(10), 'g'), chr(10))"
    return f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_lowered("text")} AS t FROM documents),
w AS (SELECT r, doc_id, {_alnum("t")} AS w FROM d),
p(label, n, phrase) AS (VALUES {phrases}),
places AS (SELECT r, label, unnest(list_filter(range(len(w)), lambda i: array_to_string(w[i + 1 : i + n], ' ') = phrase)) AS i FROM w, p WHERE contains(' ' || array_to_string(w, ' ') || ' ', ' ' || phrase || ' ')),
base AS (SELECT r, count(*) AS n_base, min(i) AS first_word, max(i) AS last_word, list(DISTINCT label) AS labels FROM places GROUP BY r),
q(id, label, tokens, need) AS (VALUES {templates}),
b AS (SELECT r, {_alnum("unnest(" + blocks + ")")} AS w FROM d),
c AS (SELECT r, label, len(list_intersect(w, tokens)) / len(tokens) AS part FROM b, q WHERE len(list_intersect(w, tokens)) >= need),
m AS (SELECT r, list(DISTINCT label) AS labels, max(part) AS best FROM c GROUP BY r)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(array_to_string(list_sort(base.labels), ','), '') AS base_labels,
 array_to_string(list_sort(list_distinct(list_concat(coalesce(base.labels, []), coalesce(m.labels, [])))), ',') AS labels, CASE WHEN n_base > 0 THEN 1.0 ELSE coalesce(best, 0.0) END::DOUBLE AS score
FROM w LEFT JOIN base USING (r) LEFT JOIN m USING (r)"""


_CONTAMINATION_SQL = f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_alnum(_lowered("text"))} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_alnum(_lowered("text"))} AS w FROM benchmark),
bw AS (SELECT DISTINCT item, n, array_to_string(w[i : i + n - 1], ' ') AS g FROM (SELECT item, w, least(10, len(w)) AS n, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM b WHERE len(w) > 0) x),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT r, n, i, array_to_string(w[i : i + n - 1], ' ') AS g FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n) x),
h AS MATERIALIZED (SELECT r, i, dw.n, item FROM dw JOIN bw USING (n, g)),
hit AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS p FROM h) x GROUP BY r),
items AS (SELECT r, count(DISTINCT item) AS n_items, array_to_string(list_sort(list(DISTINCT item)), ',') AS ids FROM h GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (r) LEFT JOIN items USING (r)"""

_QUALITY_SQL = f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, list_filter(regexp_split_to_array(coalesce(text, ''), '{_PLAIN}'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT r, i, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT r, w, unnest(range(1, len(w) - 3)) AS i FROM d WHERE len(w) > 4) x),
again AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM g) x WHERE n > 1),
rep AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + 5)) AS p FROM again) x GROUP BY r),
l AS (SELECT r, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS l FROM d),
f AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
 CAST(len(l) AS BIGINT) AS n_lines, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words, length(regexp_replace(t, '[^A-Z]+', '', 'g')) AS n_upper, length(t) - length(replace(t, '!', '')) AS n_exclaim
 FROM d JOIN l USING (r) LEFT JOIN rep USING (r))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed, NOT ({" OR ".join(rule.fails for rule in quality.RULES)}) AS kept FROM f"""

ORACLES = {"op1_license_scans": _license_sql(), "op6_decontamination": _CONTAMINATION_SQL, "op10_quality_rules": _QUALITY_SQL}
