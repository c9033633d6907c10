"""Gap-coded lists: opened in bulk, only where a binding asks, against the facts."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitgraph.plans import baselines
from bitgraph.store import Scratch


@pytest.fixture(scope="module")
def facts():
    rng = np.random.default_rng(8)
    wide = {(1, 2, int(o)) for o in rng.choice(200_000, 90_000, replace=False) + 1}
    return wide | {(int(s), int(p), int(o)) for s, p, o in rng.integers(1, 30, (400, 3))}


@pytest.mark.parametrize("name", ["six", "slices"])
def test_lists(spark, facts, name):
    ids = spark.createDataFrame(sorted(facts), "s_id bigint, p_id bigint, o_id bigint").cache()
    engine = baselines.make(name, ids, Scratch(spark), 200_000)
    as_set = lambda df: (df.count(), set(map(tuple, df.collect())))
    for s, p, o in ((1, 2, None), (None, None, 7), (3, None, 5), (None, 4, None), (1, 2, 5), (None, 3, 9)):
        want = {f for f in facts if all(v is None or v == x for v, x in zip((s, p, o), f, strict=True))}
        assert as_set(engine.match(s, p, o)) == (len(want), want)
        given = {c: v for c, v in zip(("s_id", "p_id", "o_id"), (s, p, o), strict=True) if v is not None}
        asked = spark.range(2).select(*[F.lit(v).cast("bigint").alias(c) for c, v in given.items()])
        assert as_set(engine.match_batch(asked)) == (len(want), want)
    assert engine.size_bits() > 0


def test_bytes_of_gaps(spark):
    gaps = [0, 1, 127, 128, 16383, 16384, 65535, 2**21 - 1, 2**21, 2**40]
    got = spark.createDataFrame([(g,) for g in gaps], "g bigint").select(baselines.varbyte_bits(F.col("g"))).collect()
    assert [r[0] for r in got] == [8 * max(1, -(-g.bit_length() // 7)) for g in gaps]
