"""Dictionary, index, patterns, joins, baselines and changes on small graphs, against sets."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from bitgraph.operators import joins
from bitgraph.operators.dynamic import DynamicIndex
from bitgraph.operators.graph import Graph, open_graph
from bitgraph.operators.joins import Pattern, classify
from bitgraph.operators.predicate_index import Indexed, PredicateIndex
from bitgraph.operators.tiles import TreeIndex
from bitgraph.plans import baselines, sparql, workloads
from bitgraph.sources import graphs

DATA = "/root/testdata/sf0.001"


def facts():
    rng = random.Random(5)
    nodes = [f"n/{i}" for i in range(60)] + ["Z", "a", "é", 'ß"|']
    out = {(rng.choice(nodes[:40]), f"p{rng.randrange(4)}", rng.choice(nodes[20:])) for _ in range(400)}
    return out | {("n/0", "p0", "n/0"), ("n/30", "p1", "n/30"), ("only", "p9", "here")}


@pytest.fixture(scope="module")
def graph(spark):
    rows = sorted(facts())
    return Graph(spark, graphs.clean(spark.createDataFrame([*rows, *rows[:20], ("x", "p0", None)], "s string, p string, o string")))


def test_ids_are_dense_and_sorted_by_category(graph):
    have = facts()
    s, o = {x[0] for x in have}, {x[2] for x in have}
    key = lambda t: t.encode()
    order = [sorted(c, key=key) for c in (s & o, s - o, o - s)]
    got = {r.term: (r.role, r.s_id, r.o_id) for r in graph.terms.collect()}
    n = len(order[0])
    want = {t: ("SO", i + 1, i + 1) for i, t in enumerate(order[0])} | {t: ("S", n + i + 1, None) for i, t in enumerate(order[1])} | {t: ("O", None, n + i + 1) for i, t in enumerate(order[2])}
    assert got == want and graph.dim == max(len(s), len(o))
    assert [r.pred for r in graph.predicates.orderBy("p_id").collect()] == sorted({x[1] for x in have})


@pytest.mark.parametrize("options", [{}, {"schedule": "k4"}, {"schedule": "auto"}, {"schedule": "k2", "tile_bits": 4}, {"schedule": "k2", "leaf": "vocab8"}, {"schedule": "k2", "tile_bits": 6, "max_points": 30}])
def test_patterns_of_every_shape(graph, options):
    have, engine = facts(), graph.index(**options)
    s, p, o = sorted(have)[7]
    for bound in itertools.product((False, True), repeat=3):
        want = {x for x in have if all(not b or y == z for b, y, z in zip(bound, x, (s, p, o), strict=True))}
        got = graph.match(*[v if b else None for b, v in zip(bound, (s, p, o), strict=True)], engine=engine).collect()
        assert len(got) == len(want) and set(map(tuple, got)) == want
    assert graph.match(s="here", engine=engine).count() == graph.match(p="none", engine=engine).count() == 0
    assert {r.s_id for r in engine.diagonal().collect()} == {graph.lookup((x[0], "s"))[x[0], "s"] for x in have if x[0] == x[2]}


def test_bindings_by_both_ways(graph):
    ids = {tuple(r) for r in graph.ids.collect()}
    for columns in (["s_id"], ["o_id"], ["p_id"], ["s_id", "p_id"], ["p_id", "o_id"], ["s_id", "o_id"], ["s_id", "p_id", "o_id"]):
        b = graph.ids.where("s_id % 3 = 0").select(*columns).distinct()
        keys = {tuple(r) for r in b.collect()}
        at = [["s_id", "p_id", "o_id"].index(c) for c in columns]
        want = {x for x in ids if tuple(x[i] for i in at) in keys}
        index = graph.index("k2", "plain", tile_bits=4)
        for most in (0, 10_000):
            got = [tuple(r) for r in index.match_batch(b, most_sent=most).collect()]
            assert len(got) == len(set(got)) and set(got) == want, (columns, most)


def test_26_shapes_are_told_apart():
    strip = lambda t: Pattern(*[v[1:] if v.startswith("?") else v if v.startswith("@") else 1 for v in t])
    seen = {n: classify(strip(a), strip(b)) for n, (a, b) in workloads.TEMPLATES.items()}
    assert len(seen) == 26
    assert all(s.category == n[0].upper() and s.kind == n.rpartition("_")[2].upper() for n, s in seen.items())
    assert classify(Pattern("x", 1, "y"), Pattern("x", 2, "z")).category == "G"
    assert classify(Pattern("x", "p", 1), Pattern(2, "p", "y")).kind == "other"
    assert classify(Pattern("x", 1, "x"), Pattern("x", 1, 2)).kind == "other"


@pytest.mark.parametrize("kind", ["SS", "OO", "SO"])
def test_joins_by_every_strategy(graph, kind):
    have = facts()
    a, b = ("?x", "p0", "?y"), {"SS": ("?x", "?q", "n/30"), "OO": ("n/30", "?q", "?x"), "SO": ("n/30", "?q", "?x")}[kind]
    if kind == "OO":
        a = ("?y", "p0", "?x")
    want = set()
    for f, g in itertools.product(have, repeat=2):
        env = {}
        if all(env.setdefault(v, w) == w if v.startswith("?") else v == w for v, w in zip((*a, *b), (*f, *g), strict=True)):
            want.add((env["?x"], env["?y"], env["?q"]))
    for strategy in ("auto", "chain", "merge", "per_predicate"):
        got = graph.join(Pattern(*a), Pattern(*b), strategy=strategy).select("x", "y", "q").collect()
        assert len(got) == len(want) and set(map(tuple, got)) == want
    assert want


@pytest.mark.parametrize("sent", [0, 1000])
def test_a_side_without_constants_is_merged_once(spark, graph, monkeypatch, sent):
    monkeypatch.setattr(joins, "MOST_SENT", sent)
    have, given = facts(), [(i, o) for i, o in enumerate(["n/25", "n/30", "n/33", "none"])]
    k = spark.createDataFrame(given, "i int, o string")
    for a, b in ((("?x", "p0", "@o"), ("?x", "?q", "?y")), (("?y", "?q", "?x"), ("?x", "?p", "@o"))):
        fixed, c = (a, 0) if "@o" in a else (b, 2)
        want = {(i, f[0], g[1], g[2 - c]) for i, o in given for f in have for g in have if f[2] == o and fixed[1] in (f[1], "?p") and f[0] == g[c]}
        df = graph.join(Pattern(*a), Pattern(*b), constants=k, strategy="merge").select("i", "x", "q", "y")
        got = [tuple(r) for r in df.distinct().collect()]
        assert want and set(got) == want
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_list_bits_are_measured_once_a_pair(spark, graph, monkeypatch):
    wide = [(1, 1, 5), (1, 1, 200), (1, 1, 65_535), (1, 1, 65_536), (1, 1, 90_000), (2, 1, 5), (2, 7, 1 << 33), (70_000, 1, 6), (140_000, 1, 6)]
    for rows in ([tuple(r) for r in graph.ids.collect()], wide):
        ids = spark.createDataFrame(rows, "s_id bigint, p_id bigint, o_id bigint").repartition(3)
        dealt = []
        monkeypatch.setattr(type(ids), "repartition", lambda self, *a, f=type(ids).repartition: dealt.append(a) or f(self, *a))
        six, slices = (baselines.make(n, ids, graph.scratch, graph.dim) for n in ("six", "slices"))
        for engine, orders in ((six, six.ORDERS), (slices, slices.FAMILIES.values())):
            want = 0
            for k in orders:
                lists = {}
                for r in rows:
                    a, b, c = (r[("s_id", "p_id", "o_id").index(x)] for x in k)
                    lists.setdefault((a, b, c >> 16), []).append(c)
                for (*_, chunk), cs in lists.items():
                    ends = sorted(cs)
                    want += 64 + sum(8 * max(1, -(-(y - x).bit_length() // 7)) for x, y in zip([chunk << 16, *ends], ends))
            assert engine.size_bits() == want
        assert len(dealt) == 3
        monkeypatch.undo()


@pytest.mark.parametrize("name", baselines.ENGINES)
def test_engines_agree(graph, name):
    engine, ids = baselines.make(name, graph.ids, graph.scratch, graph.dim), [tuple(r) for r in graph.ids.collect()]
    s, p, o = sorted(ids)[11]
    for bound in itertools.product((False, True), repeat=3):
        args = [v if b else None for b, v in zip(bound, (s, p, o), strict=True)]
        assert sorted(map(tuple, engine.match(*args).collect())) == sorted(x for x in ids if all(a in (None, y) for a, y in zip(args, x, strict=True)))
    b = graph.ids.where("s_id % 5 = 0").select("s_id")
    assert sorted(map(tuple, engine.match_batch(b).collect())) == sorted(x for x in ids if x[0] % 5 == 0)
    assert engine.size_bits() > 0


def test_predicate_index(graph):
    engine = Indexed(graph.index(), PredicateIndex(graph.ids, graph.scratch))
    ids = [tuple(r) for r in graph.ids.collect()]
    assert sorted(map(tuple, engine.match(s=3).collect())) == sorted(x for x in ids if x[0] == 3)
    assert sorted(map(tuple, engine.match(s=3, o=sorted(ids)[5][2]).collect())) == sorted(x for x in ids if x[0] == 3 and x[2] == sorted(ids)[5][2])


def test_changes_equal_set_algebra(graph, spark):
    rng, ids = random.Random(2), {tuple(r) for r in graph.ids.collect()}
    frame = lambda rows: spark.createDataFrame(sorted(rows), "s_id long, p_id long, o_id long")
    base = TreeIndex.build(frame(ids), graph.dim, graph.n_so, graph.scratch, schedule="k2", tile_bits=4)
    d, now = DynamicIndex.of(base, graph.scratch), set(ids)
    for step in range(3):
        new = {(rng.randint(1, graph.dim), rng.randint(1, 5), rng.randint(1, graph.dim)) for _ in range(15)}
        old = set(rng.sample(sorted(now), 12))
        d, now = (d.insert(frame(new)), now | new) if step != 1 else (d.update(frame(old), frame(new)), (now - old) | new)
        d, now = (d.delete(frame(old)), now - old) if step == 2 else (d, now)
    assert sorted(map(tuple, d.match().collect())) == sorted(now)
    assert sorted(map(tuple, d.match(p=2).collect())) == sorted(x for x in now if x[1] == 2)
    assert sorted(map(tuple, d.compact().match().collect())) == sorted(now)


def test_empty_graph_and_single_fact(spark):
    schema = "s string, p string, o string"
    none = Graph(spark, spark.createDataFrame([], schema))
    assert none.terms.count() == none.ids.count() == none.index().match().count() == none.match(s="x").count() == 0
    one = Graph(spark, spark.createDataFrame([("x", "x", "x")], schema))
    assert [tuple(r) for r in one.match(s="x").collect()] == [("x", "x", "x")] and one.counts == {"n_so": 1, "n_s": 0, "n_o": 0}


def test_sparql_errors(graph):
    for text in ("SELECT ?x", "SELECT ?x WHERE { ?x <p0> }", "ASK { ?x <p0> ?y } extra", "SELECT ?x WHERE { ?x ~ ?y }"):
        with pytest.raises(ValueError):
            sparql.run(graph, text)


def test_flagship_goes_through_the_trees(spark):
    g = open_graph(spark, DATA, "star")
    df = g.join(Pattern("?c", "inNation", "nation/7"), Pattern("?o", "placedBy", "?c"))
    plan = df._jdf.queryExecution().toString()
    assert "MapInArrow" in plan and "CartesianProduct" not in plan
    want = g.triples.alias("a").join(g.triples.alias("b"), F.expr("a.s = b.o AND a.p = 'inNation' AND a.o = 'nation/7' AND b.p = 'placedBy'")).count()
    assert df.count() == want > 0
