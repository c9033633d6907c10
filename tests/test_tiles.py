"""Tiles of several sides: levels of whole matrices, patterns, bindings; walks in slices; lists and codes opened in bulk."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitgraph.functions.bits import Codes
from bitgraph.functions.geometry import Schedule
from bitgraph.operators import tiles, tree
from bitgraph.operators.tiles import TreeIndex, directory_of
from bitgraph.operators.tree import Tree, codes_of, level_bits
from bitgraph.store import Scratch

DIM = 3000


@pytest.fixture(scope="module")
def facts():
    """Predicate 1 with many points, 2 with a dense corner, others with a few over the whole side."""
    rng = np.random.default_rng(5)
    many = {(int(r), 1, int(c)) for r, c in rng.integers(1, DIM + 1, (900, 2))}
    corner = {(int(r), 2, int(c)) for r, c in rng.integers(1, 40, (700, 2))}
    return sorted(many | corner | {(int(r), int(p), int(c)) for r, p, c in zip(rng.integers(1, DIM + 1, 120), rng.integers(3, 9, 120), rng.integers(1, DIM + 1, 120), strict=True)})


@pytest.fixture(scope="module")
def ids(spark, facts):
    return spark.createDataFrame(facts, "s_id bigint, p_id bigint, o_id bigint").cache()


@pytest.fixture
def small(monkeypatch):
    monkeypatch.setattr(tiles, "TILE_BITS", 6)
    monkeypatch.setattr(tiles, "WHOLE", 100)


@pytest.mark.parametrize("schedule", ["k2", "k4", "hybrid"])
def test_levels_of_cut_tiles_are_those_of_whole_matrices(spark, facts, ids, small, schedule):
    s = Schedule.named(schedule, DIM)
    want = np.zeros(len(s.factors), int)
    for p in {p for _, p, _ in facts}:
        points = np.array([(a - 1, b - 1) for a, q, b in facts if q == p])
        want += [len(x) for x in level_bits(np.unique(codes_of(points[:, 0], points[:, 1], s)), s)]
    for max_points in (60, 1 << 20):
        index = TreeIndex.build(ids, DIM, 0, Scratch(spark), schedule, "plain", max_points=max_points)
        assert index.tiles.where("p_id = 1").count() > 1
        assert {r["level"]: r["n_bits"] for r in index.level_bits().collect()} == dict(enumerate(want.tolist()))


def test_patterns_and_bindings_on_tiles_of_several_sides(spark, facts, ids, small):
    index = TreeIndex.build(ids, DIM, 0, Scratch(spark), max_points=60)
    assert index.tiles.where("p_id > 2").count() == len({p for _, p, _ in facts if p > 2})
    assert sorted(map(tuple, index.match().collect())) == facts
    for columns in (["s_id"], ["o_id"], ["s_id", "o_id"], ["p_id", "s_id"], ["p_id"]):
        some = ids.where("p_id % 2 = 1").select(*columns)
        keys = set(map(tuple, some.collect()))
        want = [f for f in facts if tuple(f["spo".index(c[0])] for c in columns) in keys]
        for most_sent in (0, 10_000):
            assert sorted(map(tuple, index.match_batch(some, most_sent).collect())) == want


def test_bindings_of_over_a_thousand_predicates(spark):
    facts = [(1 + p % 7, p, 1 + p % 5) for p in range(1, 1301)]
    index = TreeIndex.build(spark.createDataFrame(facts, "s_id bigint, p_id bigint, o_id bigint"), 8, 0, Scratch(spark))
    asked = spark.range(1, 1102).select(F.col("id").alias("p_id"))
    assert sorted(map(tuple, index.match_batch(asked).collect())) == sorted(f for f in facts if f[1] < 1102)


def test_walks_in_slices(monkeypatch):
    rng = np.random.default_rng(3)
    points = np.unique(rng.integers(0, 500, (4000, 2)), axis=0)
    s = Schedule.hybrid(2100)
    t = Tree.build(np.unique(codes_of(points[:, 0], points[:, 1], s)), s, "auto")
    box = np.array([(0, s.side - 1, 0, s.side - 1), (100, 300, 7, 400)]).T
    whole = t.ranges(*box)
    monkeypatch.setattr(tree, "FRONTIER", 8)
    parts = list(t.pieces(*box))
    assert max(len(q) for q, *_ in parts) <= 8 * 16 * 64
    for a, b in zip(whole[:3], t.ranges(*box)[:3], strict=True):
        assert np.array_equal(a, b)
    assert sorted(map(tuple, np.stack(whole[1:3], 1)[whole[0] == 0].tolist())) == sorted(map(tuple, points.tolist()))


def test_directory_without_trees(spark, ids):
    built = TreeIndex.build(ids, DIM, 0, Scratch(spark), "k2", "plain", tile_bits=6).directory()
    alone = directory_of(ids, 6)
    assert sorted(map(tuple, alone.collect())) == sorted(map(tuple, built.select(*alone.columns).collect()))


@pytest.mark.parametrize("b", [2, 4, 8, 16])
def test_short_codes_are_those_of_one_list(b):
    from bitgraph.sources.surface import _short_codes, _short_get

    rng = np.random.default_rng(b)
    lists = [rng.integers(0, 1 << rng.integers(1, 40, n)) for n in (0, 1, 4, 63, 64, 65, 130, 512, 0, 2)]
    got = _short_codes(lists, b)
    for x, planes in zip(lists, got, strict=True):
        assert planes == [{"chunks": c.tobytes(), "more": m.words.tobytes(), "rank": m.directory.tobytes()} for c, m in Codes.encode(x, b).planes]
    held = [k for k, x in enumerate(lists) if len(x)]
    at = np.array([rng.integers(0, len(lists[k])) for k in held])
    assert _short_get([got[k] for k in held], b, at).tolist() == [int(lists[k][i]) for k, i in zip(held, at, strict=True)]
