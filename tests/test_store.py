"""Facts of new terms, exchange, bundles, list kernels, codes and late events, against sets."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitgraph.operators.dynamic import DynamicGraph
from bitgraph.operators.graph import Graph
from bitgraph.operators.intersect import BLOCK, KERNELS, gallop, intersect, merge
from bitgraph.operators.joins import Pattern
from bitgraph.plans import planner, sparql
from bitgraph.sources import surface
from bitgraph.store import Scratch
from bitgraph.streaming import ingest

DATA = "/root/testdata/sf0.001"
SCHEMA = "s string, p string, o string"


def drawn(rng, n, names):
    return {(f"n/{rng.randrange(names)}", f"p{rng.randrange(3)}", f"n/{rng.randrange(names)}") for _ in range(n)}


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_facts_of_new_terms(spark):
    rng = random.Random(4)
    now = drawn(rng, 60, 30)
    base = Graph(spark, spark.createDataFrame(sorted(now), SCHEMA))
    d = DynamicGraph.of(base, base.scratch)
    for step in range(2):
        new = drawn(rng, 30, 50 + 20 * step) | {("only/s", "p9", "ü"), (f"was/o{step}", "p0", "only/s")}
        d, now = d.insert(spark.createDataFrame([*sorted(new), (None, "p0", "n/1"), next(iter(new))], SCHEMA)), now | new
    gone = set(rng.sample(sorted(now), 20))
    d, now = d.delete(spark.createDataFrame([*sorted(gone), ("unknown", "p0", "n/1")], SCHEMA)), now - gone
    assert rows(d.match()) == sorted(now)
    assert rows(d.match(p="p0")) == sorted(x for x in now if x[1] == "p0")
    assert rows(d.match(s="n/1")) == sorted(x for x in now if x[0] == "n/1")
    assert rows(d.match(o="only/s")) == sorted(x for x in now if x[2] == "only/s")
    assert d.match(s="nobody").count() == 0
    want = {(a[0], a[2], b[2]) for a in now for b in now if a[2] == b[0] and a[1] == "p0" and b[1] == "p1"}
    assert rows(d.chain({"p": "p0"}, {"p": "p1"})) == sorted(want)
    small, fresh = d.compact(), Graph(spark, spark.createDataFrame(sorted(now), SCHEMA))
    assert small.counts == fresh.counts and rows(small.ids) == rows(fresh.ids)


def test_facts_go_into_an_empty_graph(spark):
    none = Graph(spark, spark.createDataFrame([], SCHEMA))
    d = DynamicGraph.of(none, none.scratch).insert(spark.createDataFrame([("a", "p", "b"), ("b", "p", "c")], SCHEMA))
    assert rows(d.match()) == [("a", "p", "b"), ("b", "p", "c")]
    assert rows(d.chain({"p": "p"}, {"p": "p"})) == [("a", "b", "c")]


def test_kernels_on_lists():
    rng = np.random.default_rng(3)
    for n, m in ((0, 0), (0, 5), (1, 1), (50, 50), (3, 4000), (4000, 3)):
        a, b = (np.unique(rng.integers(0, 5000, k)) for k in (n, m))
        for f in (merge, gallop):
            assert f(a, b).tolist() == sorted(set(a.tolist()) & set(b.tolist()))


@pytest.mark.parametrize("kernel", KERNELS)
def test_kernels_over_blocks(spark, kernel):
    rng = random.Random(8)
    edges = [1, 2, BLOCK - 1, BLOCK, BLOCK + 1, 2 * BLOCK, 2 * BLOCK + 1, 10**12]
    a, b = ({*rng.sample(range(1, 200_000), 3000), *edges[:k]} for k in (8, 5))
    frame = lambda ids: spark.createDataFrame([(i,) for i in [*sorted(ids), 7, 7]] + [(None,)], "x long")
    assert [r.x for r in intersect(frame(a), frame(b), "x", kernel).orderBy("x").collect()] == sorted((a | {7}) & (b | {7}))
    assert intersect(frame(a), frame(b).limit(0), "x", kernel).count() == 0


def test_unknown_kernel(spark):
    with pytest.raises(ValueError):
        intersect(spark.range(1), spark.range(1), "id", "guess")


def test_exchange_and_bundles(spark):
    facts = sorted(drawn(random.Random(6), 80, 25) | {('a\t"', "p\n", "ß")})
    g = Graph(spark, spark.createDataFrame(facts, SCHEMA), "small")
    path = f"{g.scratch.root}/exchange"
    surface.export_graph(g, path)
    back = surface.import_graph(spark, path)
    assert rows(back.match()) == facts and back.name == "small" and back.counts == g.counts and rows(back.ids) == rows(g.ids)
    assert rows(back.join(Pattern("?a", "p0", "?b"), Pattern("?b", "p1", "?c"))) == rows(g.join(Pattern("?a", "p0", "?b"), Pattern("?b", "p1", "?c")))
    sums = {r.p_id: (r.n_points, r.bundle) for r in g.index().bundles(20).collect()}
    before = 0
    for p, (n, bundle) in sorted(sums.items()):
        assert bundle == before // 20
        before += n
    g.index().write_bundled(f"{path}/bundled", 20)
    assert rows(surface.open_index(spark, f"{path}/bundled").match()) == rows(g.ids)


@pytest.mark.parametrize("chunk", [2, 4, 8, 16])
def test_codes_in_sql(spark, chunk):
    numbers = [0, 1, 3, 255, 256, 65_535, 65_536, 10**9, 7]
    df = spark.createDataFrame([(numbers,)], "x array<long>").select(surface.dac_encode(chunk)("x").alias("c"), F.explode(F.sequence(F.lit(0), F.lit(8))).alias("i"))
    assert [r.v for r in df.select("i", surface.dac_get("c", F.col("i").cast("long")).alias("v")).orderBy("i").collect()] == numbers


def test_tree_stats(spark):
    facts = sorted(drawn(random.Random(7), 90, 25))
    g = Graph(spark, spark.createDataFrame(facts, SCHEMA))
    for leaf in ("plain", "vocab8"):
        tiles = g.index("k2", leaf).tiles
        got = tiles.select("n_points", "n_bits", surface.tree_stats(F.struct(*surface.PAYLOAD)).alias("t")).collect()
        assert sum(r.t.n_points for r in got) == len(facts) and all(r.t.n_points == r.n_points and r.t.n_bits == r.n_bits for r in got)


def test_views(spark):
    g = Graph(spark, spark.createDataFrame([("a", "p", "b")], SCHEMA))
    surface.register_views(g, "v")
    assert spark.sql("SELECT t.term FROM v_ids i JOIN v_terms t ON t.o_id = i.o_id").first()[0] == "b"
    assert spark.table("v_triples").count() == spark.table("v_predicates").count() == spark.table("v_tiles").count() == 1


def test_late_events_are_shut_out(spark):
    progress = []
    closed = ingest.replay(spark, DATA, lambda s: ingest.counts(s, "6 hours"), Scratch(spark), progress)
    assert ingest.dropped(progress) > 0 and closed.count() > 0
    events = spark.read.parquet(f"{DATA}/events.parquet")
    assert 0 < closed.agg(F.sum("n")).first()[0] < events.count()


def test_late_events_over_no_events(spark, tmp_path):
    spark.read.parquet(f"{DATA}/events.parquet").limit(0).write.parquet(f"{tmp_path}/events.parquet")
    assert ingest.replay(spark, str(tmp_path), lambda s: ingest.counts(s, "6 hours"), Scratch(spark)).count() == 0


def test_answers_of_bgps_and_texts(spark):
    facts = drawn(random.Random(9), 150, 20)
    g = Graph(spark, spark.createDataFrame(sorted(facts), SCHEMA))
    want = {(a[0], a[2], b[2], c[2]) for a in facts for b in facts for c in facts if a[1] == "p0" and b[1] == "p1" and c[1] == "p2" and a[2] == b[0] == c[0]}
    got = planner.solve(g, [Pattern("?x", "p0", "?y"), Pattern("?y", "p1", "?z"), Pattern("?y", "p2", "?w")])
    assert rows(got.select("x", "y", "z", "w")) == sorted(want)
    found = sparql.run(g, "SELECT DISTINCT ?x ?y WHERE { ?x <p0> ?y . ?y <p1> ?z . ?y <p2> ?w }")
    assert rows(found.select("x", "y")) == sorted({x[:2] for x in want})
    without = sparql.run(g, "SELECT DISTINCT ?x WHERE { ?x <p0> ?y . MINUS { ?x <p1> ?z } }")
    assert rows(without) == sorted({(a[0],) for a in facts if a[1] == "p0"} - {(b[0],) for b in facts if b[1] == "p1"})
