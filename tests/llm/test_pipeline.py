"""The pipeline's stages, each against brute force on its own input."""

import re
from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline as cp
from bitgraph.llm import secrets
from bitgraph.llm.common import Scratch

from .conftest import DATA
from .test_dedup import brute
from .test_scans import ALNUM, PLAIN, lower

SF = DATA


def ids(rows):
    return Counter(r.doc_id for r in rows)


def test_stages(spark, docs, odd):
    scratch = Scratch(spark)
    now = scratch.keep(docs.union(odd.withColumn("doc_id", F.col("doc_id") + 1_000_000).select(*docs.columns)).union(docs.limit(3)))
    before = now.collect()
    for name, stage in cp.STAGES:
        out = stage(spark, now, SF)
        if name != "mixing":
            assert out.columns == docs.columns
            out = scratch.keep(out)
        after = out.collect()
        if name == "language_id":
            letters = [r for r in before if re.search(r"[^\W\d_]", r.text or "")]
            assert set(ids(after)) <= set(ids(letters)) and len(after) > 0.98 * len(letters) and len(after) < len(before)
        elif name == "near_dedup":
            groups = brute([(r.doc_id, r.text) for r in before], 5)
            assert ids(after) == Counter({d: 1 for (d, _, _, kept) in groups if kept})
        elif name == "decontamination":
            grams = {tuple(w[i : i + 10]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect() for w in [ALNUM.findall(lower(r.text))] for i in range(len(w) - 9)}
            clean = [r for r in before if not any(tuple(w[i : i + 10]) in grams for w in [ALNUM.findall(lower(r.text))] for i in range(len(w) - 9))]
            assert ids(after) == ids(clean) and len(after) < len(before)
        elif name == "secret_redaction":
            assert ids(after) == ids(before)
            assert not any(secrets.base_spans(r.text) for r in after) and any(secrets.base_spans(r.text) for r in before)
            assert {r.doc_id: r.text for r in after if "[" not in r.text}.items() <= {r.doc_id: r.text for r in before}.items()
        else:
            sizes = {r.doc_id: len(PLAIN.findall(r.text or "")) for r in before}
            assert all(r.taken == r.copies * sizes[r.doc_id] and 1 <= r.copies <= 3 for r in after) and max(ids(after).values()) == 1
        now, before = out, after
    assert cp.run(spark, SF).agg(F.sum("copies")).first()[0] > 0


def test_stages_of_nothing(spark, docs):
    for _, stage in cp.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0


def test_mixing_deals_out_only_repeated_texts_to_find_repeats(spark, docs):
    now = docs.limit(40).union(docs.limit(3))
    out = cp.mix_sources(spark, now, SF)
    dealt = out._jdf.queryExecution().optimizedPlan().toString().split("first(text")
    assert len(dealt) > 1 and "repeated" in dealt[-1]
    got, rows = out.collect(), Counter(tuple(r) for r in now.collect())
    assert len({r.doc_id for r in got}) == len(got) and all(r.copies <= 3 * rows[tuple(r[:5])] for r in got)
