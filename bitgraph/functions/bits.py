"""Packed bit arrays with a rank directory, and directly addressable codes, in numpy."""

from __future__ import annotations

import numpy as np

#: Bits between two counters of the rank directory.
BLOCK = 512


def pack(bits: np.ndarray) -> np.ndarray:
    """Booleans as little-endian 64-bit words, bit i of the array in bit i % 64 of word i // 64."""
    raw = np.packbits(bits.astype(np.uint8), bitorder="little")
    return np.concatenate((raw, np.zeros(-len(raw) % 8, np.uint8))).view("<u8")


def rank_index(words: np.ndarray) -> np.ndarray:
    """Ones before each block."""
    per_block = BLOCK // 64
    counts = np.bitwise_count(np.concatenate((words, np.zeros(-len(words) % per_block, "<u8")))).reshape(-1, per_block).sum(axis=1)
    return np.concatenate(([0], np.cumsum(counts)[:-1])).astype("<u4") if len(counts) else np.zeros(0, "<u4")


class Bits:
    def __init__(self, words: np.ndarray, directory: np.ndarray | None = None):
        self.words = words
        self.directory = rank_index(words) if directory is None else directory

    @classmethod
    def of(cls, bits: np.ndarray) -> Bits:
        return cls(pack(bits))

    def get(self, at: np.ndarray) -> np.ndarray:
        return ((self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)

    def rank(self, at: np.ndarray) -> np.ndarray:
        """Ones before each position."""
        word = at >> 6
        block = at // BLOCK
        out = np.zeros(len(at), np.int64)
        if not len(self.words):
            return out
        inside = block < len(self.directory)
        out += self.directory[np.minimum(block, len(self.directory) - 1)]
        last = len(self.words) - 1
        if not inside.all():  # just behind the last block
            out += np.where(inside, 0, int(np.bitwise_count(self.words[(len(self.directory) - 1) * (BLOCK // 64) :]).sum()))
        first = block * (BLOCK // 64)
        for k in range(BLOCK // 64):
            w = first + k
            out += np.where(inside & (w < word) & (w <= last), np.bitwise_count(self.words[np.minimum(w, last)]), 0)
        mask = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return out + np.where(word <= last, np.bitwise_count(self.words[np.minimum(word, last)] & mask), 0)


def _pack_chunks(chunks: np.ndarray, b: int) -> np.ndarray:
    if b == 8:
        return chunks.astype(np.uint8)
    if b == 16:
        return chunks.astype("<u2").view(np.uint8)
    per = 8 // b
    padded = np.concatenate((chunks, np.zeros(-len(chunks) % per, chunks.dtype))).astype(np.uint8).reshape(-1, per)
    return (padded << (np.arange(per, dtype=np.uint8) * b)).sum(axis=1).astype(np.uint8)


class Codes:
    """Directly addressable codes: chunks of b bits in planes, each with a bitmap of the codes that go on."""

    def __init__(self, b: int, planes: list[tuple[np.ndarray, Bits]]):
        self.b, self.planes = b, planes

    @classmethod
    def encode(cls, symbols: np.ndarray, b: int = 8) -> Codes:
        if b not in (2, 4, 8, 16):
            raise ValueError("chunks of 2, 4, 8 or 16 bits")
        planes, left = [], np.asarray(symbols, np.int64)
        while len(left):
            more = left >> b > 0
            planes.append((_pack_chunks(left & ((1 << b) - 1), b), Bits.of(more)))
            left = left[more] >> b
        return cls(b, planes)

    def _chunk(self, plane: np.ndarray, at: np.ndarray) -> np.ndarray:
        if self.b == 8:
            return plane[at].astype(np.int64)
        if self.b == 16:
            return plane.view("<u2")[at].astype(np.int64)
        per = 8 // self.b
        return (plane[at // per] >> (at % per * self.b).astype(np.uint8)).astype(np.int64) & ((1 << self.b) - 1)

    def get(self, at: np.ndarray) -> np.ndarray:
        out, at, open_ = np.zeros(len(at), np.int64), np.asarray(at, np.int64), np.arange(len(at))
        for level, (chunks, more) in enumerate(self.planes):
            if not len(at):
                break
            out[open_] |= self._chunk(chunks, at) << (self.b * level)
            on = more.get(at)
            at, open_ = more.rank(at[on]), open_[on]
        return out

    def n_bits(self, n: int) -> int:
        """Bits of the n codes: chunks and bitmaps, no directory."""
        total, left = 0, n
        for _, more in self.planes:
            total += left * (self.b + 1)
            left = int(np.bitwise_count(more.words).sum())
        return total
