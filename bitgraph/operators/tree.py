"""A local k2-tree in numpy: built from sorted cell codes, walked for batches of ranges at once.

Levels above the leaves lie in one bit array T, top down; the bits of a node's children start where the ones before it
put them. Leaves are the last level's bits, or 8x8 blocks named by their rank among the tile's patterns, in directly
addressable codes.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from bitgraph.functions.bits import Bits, Codes, pack
from bitgraph.functions.geometry import Schedule

#: Binary levels that an 8x8 leaf block takes the place of.
BLOCK_LEVELS = 3
#: Nodes whose children a walk opens at a time.
FRONTIER = 1 << 15
_NOTHING = (np.zeros(0, np.int64),) * 3


def codes_of(rows: np.ndarray, cols: np.ndarray, schedule: Schedule) -> np.ndarray:
    out, below = np.zeros(len(rows), np.int64), sum(schedule.bits)
    for b in schedule.bits:
        below -= b
        mask = (1 << b) - 1
        out = (out << (2 * b)) | (((rows >> below) & mask) << b) | ((cols >> below) & mask)
    return out


def _changes(x: np.ndarray) -> np.ndarray:
    """Where a sorted array has a value for the first time, as booleans."""
    new = np.ones(len(x), bool)
    np.not_equal(x[1:], x[:-1], out=new[1:])
    return new


def distinct(codes: np.ndarray) -> np.ndarray:
    codes = np.sort(codes)
    return codes[_changes(codes)]


def level_bits(codes: np.ndarray, schedule: Schedule) -> list[np.ndarray]:
    """The bits of each level, top down, from sorted distinct codes: a level's nodes are the prefixes of those below it, sorted as they are."""
    if not len(codes):
        return [np.zeros(0 if level else 1 << (2 * b), bool) for level, b in enumerate(schedule.bits)]
    out, nodes = [], codes
    for b in reversed(schedule.bits):
        parents = nodes >> (2 * b)
        new = _changes(parents)
        bits = np.zeros(int(np.count_nonzero(new)) << (2 * b), bool)
        bits[((np.cumsum(new) - 1) << (2 * b)) | (nodes & ((1 << (2 * b)) - 1))] = True
        out.append(bits)
        nodes = parents[new]
    return out[::-1]


@dataclass
class Tree:
    schedule: Schedule  # down to single cells
    inner: tuple[int, ...]  # bits a digit of each level in T
    starts: np.ndarray  # where each level starts in T, and T's length
    t: Bits
    n_points: int
    leaf_bits: np.ndarray | None = None  # packed words of the last level
    vocabulary: np.ndarray | None = None  # 64-bit patterns of 8x8 blocks, most frequent first
    leaf_codes: Codes | None = None

    @classmethod
    def build(cls, codes: np.ndarray, schedule: Schedule, leaf: str = "plain", chunk: int = 8) -> Tree:
        """From sorted distinct codes. ``leaf``: plain, vocab8, or auto for the smaller one."""
        levels = level_bits(codes, schedule)
        blocks = leaf != "plain" and len(schedule.bits) > BLOCK_LEVELS and set(schedule.bits[-BLOCK_LEVELS:]) == {1}
        plain = cls._with(levels[:-1], schedule.bits[:-1], schedule, len(codes), leaf_bits=pack(levels[-1]))
        if not blocks:
            return plain
        patterns = np.bitwise_or.reduceat(np.uint64(1) << (codes & 63).astype(np.uint64), np.flatnonzero(_changes(codes >> 6)))
        values, symbol, times = np.unique(patterns, return_inverse=True, return_counts=True)
        order = np.lexsort((values, -times))
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        coded = cls._with(levels[:-BLOCK_LEVELS], schedule.bits[:-BLOCK_LEVELS], schedule, len(codes), vocabulary=values[order], leaf_codes=Codes.encode(rank[symbol], chunk))
        return coded if leaf == "vocab8" or coded.n_bits() < plain.n_bits() else plain

    @classmethod
    def _with(cls, levels: list[np.ndarray], inner: tuple[int, ...], schedule: Schedule, n: int, **leaf) -> Tree:
        starts = np.concatenate(([0], np.cumsum([len(x) for x in levels]))).astype(np.int64)
        return cls(schedule, tuple(inner), starts, Bits.of(np.concatenate(levels) if levels else np.zeros(0, bool)), n, **leaf)

    @property
    def leaf_levels(self) -> tuple[int, ...]:
        return self.schedule.bits[len(self.inner) :]

    @property
    def n_leaves(self) -> int:
        if not self.inner:
            return 1
        return int(self.t.rank(self.starts[-1:])[0] - self.t.rank(self.starts[-2:-1])[0])

    def n_bits(self, directory: bool = True) -> int:
        """Bits of T and leaves, with vocabulary and codes; with rank directories unless told otherwise."""
        out = int(self.starts[-1]) + (32 * len(self.t.directory) if directory else 0)
        if self.leaf_bits is not None:
            return out + self.n_leaves * (1 << (2 * sum(self.leaf_levels)))
        out += 64 * len(self.vocabulary) + self.leaf_codes.n_bits(self.n_leaves)
        return out + (32 * sum(len(m.directory) for _, m in self.leaf_codes.planes) if directory else 0)

    def pieces(self, r1, r2, c1, c2) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, int]]:
        """(query, row, column) of the points in each [r1, r2] x [c1, c2], in query and tree order; and bits looked at.

        All queries go down a level together: a frontier of nodes, of which only children that meet the range are read.
        A frontier over ``FRONTIER`` nodes goes down in slices, one to its end before the next, so that the memory of a
        walk depends on the tree's height and not on its points.
        """
        r1, r2, c1, c2 = (np.asarray(x, np.int64) for x in (r1, r2, c1, c2))
        below, sizes = sum(self.schedule.bits), []
        for b in self.inner:
            below -= b
            sizes.append(below)
        n, last = len(r1), self.schedule.side - 1
        if n == 1 and self.inner and r1[0] <= 0 and c1[0] <= 0 and r2[0] >= last and c2[0] >= last:
            yield from self._all(0, 0, np.zeros(1, np.int64), np.zeros(1, np.int64))
            return
        first = np.zeros(n, np.int64)  # where the node's children start in T, or the node's leaf number
        yield from self._down(0, sizes, np.arange(n), np.zeros(n, np.int64), np.zeros(n, np.int64), first, (r1, r2, c1, c2))

    def _down(self, level: int, sizes: list[int], q, row, col, first, box) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, int]]:
        if len(q) > FRONTIER:
            for k in range(0, len(q), FRONTIER):
                yield from self._down(level, sizes, *(x[k : k + FRONTIER] for x in (q, row, col, first)), box)
        elif not len(q):
            return
        elif level == len(self.inner):
            yield self._leaves(q, row, col, first, box)
        else:
            b = self.inner[level]
            q, row, col, child, kept = _children(q, row, col, b, sizes[level], *box)
            at = first[kept] + child
            yield (*_NOTHING, len(at))
            on = self.t.get(at)
            q, row, col, at = q[on], row[on], col[on], at[on]
            number = self.t.rank(at) - self.t.rank(self.starts[level : level + 1])
            first = self.starts[level + 1] + (number << (2 * self.inner[level + 1])) if level + 1 < len(self.inner) else number
            yield from self._down(level + 1, sizes, q, row, col, first, box)

    def _all(self, level: int, number: int, row, col) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, int]]:
        """Points below neighbouring nodes of a level, the first its ``number``-th: their children lie together, so neither ranges nor ranks of nodes are needed."""
        for k in range(0, len(row), FRONTIER):
            r, c = row[k : k + FRONTIER], col[k : k + FRONTIER]
            if level == len(self.inner):
                yield self._all_leaves(number + k, r, c)
                continue
            b = self.inner[level]
            first = int(self.starts[level]) + ((number + k) << (2 * b))
            n = len(r) << (2 * b)
            yield (*_NOTHING, n)
            r, c = _opened(_ones(self.t.words, first, n), r, c, b)
            before = self.t.rank(np.array([first, self.starts[level]]))
            yield from self._all(level + 1, int(before[0] - before[1]), r, c)

    def _all_leaves(self, number: int, row, col) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        if self.leaf_bits is not None:
            b = self.leaf_levels[0]
            n = len(row) << (2 * b)
            row, col = _opened(_ones(self.leaf_bits, number << (2 * b), n), row, col, b)
        else:
            n = len(row) << (2 * BLOCK_LEVELS)
            at = _ones(self.vocabulary[self.leaf_codes.get(np.arange(number, number + len(row)))], 0, n)
            cell = at & 63  # a digit of row and column a level
            side = [sum(((cell >> (2 * i + axis)) & 1) << i for i in range(BLOCK_LEVELS)) for axis in (1, 0)]
            row, col = ((x[at >> 6] << BLOCK_LEVELS) | y for x, y in zip((row, col), side, strict=True))
        return np.zeros(len(row), np.int64), row, col, n

    def _leaves(self, q, row, col, leaf, box) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        if self.leaf_bits is not None:
            b = self.leaf_levels[0]
            q, row, col, child, kept = _children(q, row, col, b, 0, *box)
            at = (leaf[kept] << (2 * b)) + child
            on = ((self.leaf_bits[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)
            return q[on], row[on], col[on], len(at)
        words = self.vocabulary[self.leaf_codes.get(leaf)]
        for below in range(BLOCK_LEVELS - 1, -1, -1):
            q, row, col, child, kept = _children(q, row, col, 1, below, *box)
            words, path = words[kept], child if below == BLOCK_LEVELS - 1 else (path[kept] << 2) | child  # noqa: F821
        on = ((words >> path.astype(np.uint64)) & np.uint64(1)).astype(bool)
        return q[on], row[on], col[on], len(words)

    def ranges(self, r1, r2, c1, c2) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """``pieces`` at once."""
        q, row, col, looked = zip((*_NOTHING, 0), *self.pieces(r1, r2, c1, c2), strict=True)
        return np.concatenate(q), np.concatenate(row), np.concatenate(col), sum(looked)

    def diagonal(self, limit: int) -> np.ndarray:
        """Cells (x, x) that are set, x < limit: a walk that only follows nodes on the diagonal."""
        row, first = np.zeros(1, np.int64), np.zeros(1, np.int64)
        below, n_inner = sum(self.schedule.bits), len(self.inner)
        for level, b in enumerate(self.inner):
            below -= b
            d = np.arange(1 << b)
            row = (row[:, None] | (d << below)).ravel()
            at = (first[:, None] + (d << b | d)).ravel()
            on = (row < limit) & self.t.get(at)
            row, at = row[on], at[on]
            number = self.t.rank(at) - self.t.rank(self.starts[level : level + 1])
            first = self.starts[level + 1] + (number << (2 * self.inner[level + 1])) if level + 1 < n_inner else number
        side = 1 << sum(self.leaf_levels)
        x = (row[:, None] | np.arange(side)).ravel()
        q, _, _, _ = self.ranges(x, x, x, x)
        found = x[q]
        return found[found < limit]


def _ones(words: np.ndarray, first: int, n: int) -> np.ndarray:
    """Places of the ones among ``n`` bits of packed words from ``first`` on."""
    part = words[first >> 6 : (first + n + 63) >> 6]
    off = first & 63
    return np.flatnonzero(np.unpackbits(part.view(np.uint8), bitorder="little")[off : off + n])


def _opened(at: np.ndarray, row: np.ndarray, col: np.ndarray, b: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of children in units of their own side, by their place among those of all nodes."""
    node, child = at >> (2 * b), at & ((1 << (2 * b)) - 1)
    return (row[node] << b) | (child >> b), (col[node] << b) | (child & ((1 << b) - 1))


def _children(q, row, col, b: int, below: int, r1, r2, c1, c2):
    """Those of the nodes' children that meet their query's range: query, row and column, child number, index of the node."""
    k = 1 << b
    child = np.tile(np.arange(k * k), len(q))
    node = np.repeat(np.arange(len(q)), k * k)
    cq, crow, ccol = q[node], row[node] | (child >> b << below), col[node] | ((child & (k - 1)) << below)
    size = (1 << below) - 1
    keep = (crow <= r2[cq]) & (crow + size >= r1[cq]) & (ccol <= c2[cq]) & (ccol + size >= c1[cq])
    return cq[keep], crow[keep], ccol[keep], child[keep], node[keep]
