"""Bits, codes and the local tree against naive counterparts, and the worked example."""

import numpy as np
import pytest

from bitgraph.functions.bits import Bits, Codes
from bitgraph.functions.geometry import Schedule, dimension
from bitgraph.operators import tree
from bitgraph.operators.tree import Tree, codes_of, level_bits

POINTS = np.array([(1, 3), (0, 4), (2, 5)])


def text(bits, k):
    return ["".join("01"[int(x)] for x in bits[i : i + k * k]) for i in range(0, len(bits), k * k)]


def test_worked_example():
    for name, k, want in (("k4", 4, [["1100000000000000"], ["0000000100000000", "1000000001000000"]]), ("k2", 2, [["1100"], ["0100", "1010"], ["0001", "1000", "0100"]])):
        s = Schedule.named(name, dimension(1, 2, 5))
        codes = np.sort(codes_of(POINTS[:, 0], POINTS[:, 1], s))
        assert [text(x, k) for x in level_bits(codes, s)] == want
        assert Tree.build(codes, s).n_bits(directory=False) == sum(len(x) * k * k for x in want)
    assert Schedule.hybrid(6) == Schedule((4, 4))


def test_sides():
    assert [Schedule.uniform(2, d).side for d in (1, 2, 4, 5, 16, 17, 1024, 1025)] == [2, 2, 4, 8, 16, 32, 1024, 2048]
    assert Schedule.hybrid(1024).factors == (4,) * 5 and Schedule.hybrid(1025).factors == (4, 4, 4, 4, 4, 2)
    with pytest.raises(ValueError):
        Schedule((3,))


def test_rank():
    rng = np.random.default_rng(1)
    for n in (0, 1, 63, 64, 511, 512, 513, 5000):
        bits = rng.random(n) < 0.3
        b, at = Bits.of(bits), np.arange(n + 1)
        assert np.array_equal(b.rank(at), np.concatenate(([0], np.cumsum(bits))))
        assert np.array_equal(b.get(at[:-1]), bits)


@pytest.mark.parametrize("b", [2, 4, 8, 16])
def test_codes(b):
    rng = np.random.default_rng(b)
    edge = np.array([0, 1, 2**b - 1, 2**b, 2 ** (2 * b), 255, 256, 65535, 65536])
    for symbols in (edge, rng.integers(0, 1 << rng.integers(1, 40, 3000)), np.zeros(0, np.int64)):
        c = Codes.encode(symbols, b)
        at = rng.permutation(len(symbols))
        assert np.array_equal(c.get(at), symbols[at])


def matrices():
    rng = np.random.default_rng(7)
    n = 100
    yield np.zeros((0, 2), int)
    yield np.array([[0, 0]])
    yield np.array([[n - 1, n - 1], [0, n - 1], [n - 1, 0]])
    yield np.array([(i, j) for i in range(40, 60) for j in range(40, 60)])
    yield np.array([(i, i) for i in range(n)])
    yield np.array([(7, j) for j in range(n)] + [(j, 9) for j in range(n)])
    yield np.unique(rng.integers(0, n, (800, 2)), axis=0)


@pytest.mark.parametrize("schedule", [Schedule.uniform(2, 100), Schedule.uniform(4, 100), Schedule.hybrid(2100), Schedule((8, 4, 2, 2, 2)), Schedule((128,))])
@pytest.mark.parametrize("leaf", ["plain", "vocab8", "auto"])
def test_walks(schedule, leaf):
    for points in matrices():
        points = np.unique(points, axis=0) if len(points) else points
        have = {tuple(map(int, x)) for x in points}
        codes = np.sort(codes_of(points[:, 0], points[:, 1], schedule))
        tree = Tree.build(codes, schedule, leaf)
        side = schedule.side - 1
        queries = [(0, side, 0, side), (7, 7, 0, side), (0, side, 9, 9), (40, 50, 45, 70), (7, 7, 9, 9), (99, 99, 99, 99), (side, side, side, side)]
        q, r, c, looked = tree.ranges(*np.array(queries).T)
        for i, (r1, r2, c1, c2) in enumerate(queries):
            got = list(zip(r[q == i].tolist(), c[q == i].tolist(), strict=True))
            assert sorted(got) == sorted((a, b) for a, b in have if r1 <= a <= r2 and c1 <= b <= c2)
            if r1 == r2 or c1 == c2:
                assert got == sorted(got)
        for limit in (0, 50, side + 1):
            assert sorted(tree.diagonal(limit).tolist()) == sorted(a for a, b in have if a == b and a < limit)


def test_bindings_that_outnumber_the_points():
    """Reading a tile and looking its points up gives what a walk for each binding gives."""
    from bitgraph.operators.tiles import _walk_bindings

    rng = np.random.default_rng(12)
    schedule = Schedule.named("k2", 64)
    cells = {(int(r), int(c)) for r, c in rng.integers(0, 64, (40, 2))}
    rows, cols = (np.array(v) for v in zip(*sorted(cells), strict=True))
    tree = Tree.build(np.unique(codes_of(rows, cols, schedule)), schedule)
    x = {"row0": 128, "col0": 64}
    ids = np.arange(100, 300)
    pairs = np.array([(s, o) for s in range(125, 200) for o in range(60, 140)])
    for n in (20, len(ids)):
        s, o = rng.choice(ids, n, replace=False), rng.choice(ids, n, replace=False)
        for a, b, want in ((s, None, {z for z in cells if z[0] + 129 in s}), (None, o, {z for z in cells if z[1] + 65 in o})):
            r, c = _walk_bindings(tree, x, a, b)
            assert len(r) == len(want) and set(zip(r.tolist(), c.tolist(), strict=True)) == want
    for n in (10, 3000):
        part = rng.permutation(pairs)[:n]
        r, c = _walk_bindings(tree, x, part[:, 0], part[:, 1])
        want = {z for z in cells if (z[0] + 129, z[1] + 65) in set(map(tuple, part.tolist()))}
        assert len(r) == len(want) and set(zip(r.tolist(), c.tolist(), strict=True)) == want


@pytest.mark.parametrize("frontier", [3, 1 << 15])
def test_a_walk_of_the_whole_tree_checks_no_ranges(monkeypatch, frontier):
    def checked(*_):
        raise AssertionError("ranges are compared node by node")

    monkeypatch.setattr(tree, "_children", checked)
    monkeypatch.setattr(tree, "FRONTIER", frontier)
    for points in matrices():
        for name, leaf in (("k2", "plain"), ("k2", "vocab8"), ("k4", "plain"), ("hybrid", "vocab8")):
            s = Schedule.named(name, 100)
            codes = np.unique(codes_of(points[:, 0], points[:, 1], s))
            q, r, c, _ = Tree.build(codes, s, leaf).ranges([0], [s.side - 1], [0], [s.side - 1])
            assert not q.any() and np.array_equal(codes_of(r, c, s), codes)
