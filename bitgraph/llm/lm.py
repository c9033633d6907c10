"""Language-model scoring with a probabilistic suffix tree over words.

Symbols are the lower-cased words of a text and one end. The root of the tree is the smoothed unigram distribution of all
training symbols. Deeper states are contexts of one to DEPTH preceding symbols (a text's start counts as one). A context
is a candidate if it has enough places, the square root of the number of all symbols over ROOT_PART, and stays if the
divergence of its next-symbol distribution from that of the longest shorter state is LEAST_DIVERGENCE or more. A state
spells out the next symbols with one place for every NEXT_PART that a candidate needs, smoothed by the shorter state, and
leaves the rest to that state in proportion. A text is scored symbol by symbol from the state of its longest suffix in
the tree. Candidates of an order are found among the counted pairs of the order before, so the tree is grown in DEPTH
passes over the texts as arrays of symbols.

The tree grows with the corpus, and what is broadcast stays small: n symbols give at most ROOT_PART * sqrt(n) candidates
an order and NEXT_PART times as many next symbols, and at most 1 / HEAD_SHARE frequent words with their counts. Counts
cover all training texts. The counts of the other words are never broadcast: a text's rare words are joined with them, each
(text, word) pair once.

Defined results: null text is empty, only its end is scored; a null id counts as training; repeated rows count and are
scored each by itself; without training texts every symbol has probability 1 by the base's formula; an empty table gives
an empty result; columns of other names are dropped.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

ADD = 0.1
HEAD_SHARE = 5e-7
DEPTH = 4
#: Places that a context needs: sqrt(symbols) / ROOT_PART, LEAST_PLACES at least; and the part of them that a next symbol needs.
ROOT_PART, LEAST_PLACES, NEXT_PART = 16, 8, 16
LEAST_DIVERGENCE = 0.02
#: Weight of the shorter state in a state's smoothed counts.
MASS = 20.0
#: Hashes and counts a worker holds before it passes them on, and symbols that it goes through at once.
REMEMBERED = 1 << 17
HELD = 1 << 19
AT_ONCE = 1 << 18
#: Stands for the end of a text among the hashes of words, which are other numbers but for a chance of 2 ** -64 each.
END = 0x454E44


class Hasher:
    def __init__(self):
        self.known: dict[bytes, int] = {}

    def __call__(self, text: str | None) -> np.ndarray:
        """Signed 64-bit hashes of a text's words, and END."""
        known, out = self.known, []
        if len(known) > REMEMBERED:
            known.clear()
        for w in (text or "").encode("utf-8", "surrogatepass").lower().split():
            h = known.get(w)
            if h is None:
                h = known[w] = xxhash.xxh64_intdigest(w)
            out.append(h)
        out.append(END)
        return np.array(out, np.uint64).view(np.int64)


def _totals(keys: list[np.ndarray], counts: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    k = np.concatenate(keys) if keys else np.empty(0, np.int64)
    if counts is None:
        return np.unique(k, return_counts=True)
    u, at = np.unique(k, return_inverse=True)
    return u, np.bincount(at, np.concatenate(counts) if counts else None, len(u)).astype(np.int64)


def counting(keys_of):
    """Partial counts of the integer keys that keys_of() makes of a column, array by array, at most HELD of them held at once."""
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = keys_of()
        held_k, held_n, pending, size = [], [], [], 0

        def fold() -> None:
            nonlocal held_k, held_n, pending, size
            k, n = _totals(pending)
            if held_k:
                k, n = _totals([*held_k, k], [*held_n, n])
            held_k, held_n, pending, size = [k], [n], [], 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(held_k[0]), pa.array(held_n[0], pa.int64())], names=["k", "n"])

        for batch in it:
            for keys in make(batch.column(0)):
                pending.append(keys)
                size += len(keys)
                if size > HELD:
                    fold()
                    if len(held_k[0]) > HELD:
                        yield out()
                        held_k, held_n = [], []
        if pending:
            fold()
        if held_k:
            yield out()

    return batches


def word_hashes():
    hashes = Hasher()
    return lambda column: (hashes(t) for t in column.to_pylist())


def in_groups(texts: list, size_of) -> Iterator[list]:
    """Runs of the list of some AT_ONCE symbols together."""
    group, n = [], 0
    for t in texts:
        group.append(t)
        n += size_of(t)
        if n >= AT_ONCE:
            yield group
            group, n = [], 0
    if group:
        yield group


def _places(lengths: np.ndarray) -> np.ndarray:
    """The place of each symbol in its text, texts of these lengths one after the other."""
    return np.arange(lengths.sum()) - np.repeat(np.cumsum(lengths) - lengths, lengths)


def symbol_groups(column: pa.ListArray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(symbols, places in their texts) of groups of rows of a column of symbol lists."""
    ends, values = column.offsets.to_numpy(), column.values.to_numpy(zero_copy_only=False)
    for group in in_groups(list(range(len(column))), lambda i: ends[i + 1] - ends[i]):
        a, b = group[0], group[-1] + 1
        yield values[ends[a] : ends[b]].astype(np.int64), _places(np.diff(ends[a : b + 1]))


def _none() -> np.ndarray:
    return np.empty(0, np.int64)


@dataclass
class Tree:
    """States are numbered from 1, the root is 0. Logarithms are to base 10, relative to the root's probabilities.

    A candidate of order m + 1 is named by (number of its suffix of order m) * n_contexts + (its first symbol); its place
    among the sorted names of the order is its number.
    """

    heads: np.ndarray  # hashes of the frequent words, sorted
    head_log: np.ndarray  # log10(count + ADD) of each
    n: int = 0
    v: int = 0
    context_of: np.ndarray = field(default_factory=_none)  # by head: number of the word as a context, or -1
    start: int = -1
    n_contexts: int = 0
    names: list[np.ndarray] = field(default_factory=list)  # by order from 2
    states: list[np.ndarray] = field(default_factory=list)  # by order from 1 and candidate: its state, 0 if not retained
    suffix: np.ndarray = field(default_factory=lambda: np.zeros(1, np.int64))  # by state: the longest shorter state
    spelled: np.ndarray = field(default_factory=_none)  # sorted state * len(heads) + symbol
    gain: np.ndarray = field(default_factory=lambda: np.empty(0))
    back: np.ndarray = field(default_factory=lambda: np.zeros(1))  # by state: log10 of what a symbol left to the shorter state costs

    def find(self, table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(table, keys), max(len(table) - 1, 0))
        return at, table[at] == keys if len(table) else np.zeros(len(keys), bool)

    def symbols(self, hashes: np.ndarray) -> np.ndarray:
        at, ok = self.find(self.heads, hashes)
        return np.where(ok, at, -1)

    def candidates(self, symbols: np.ndarray, places: np.ndarray) -> Iterator[np.ndarray]:
        """By order, the number of the candidate before each symbol, or -1."""
        own = np.where(symbols >= 0, self.context_of[symbols], -1) if len(self.heads) else np.full(len(symbols), -1)

        def before(m: int) -> np.ndarray:
            out = np.full(len(own), -1)
            out[m:] = own[:-m]
            out[places < m] = -1
            out[places == m - 1] = self.start
            return out

        now = before(1)
        yield now
        for m, names in enumerate(self.names, 2):
            further = before(m)
            at, ok = self.find(names, now * self.n_contexts + further)
            now = np.where(ok & (now >= 0) & (further >= 0), at, -1)
            yield now

    def states_at(self, symbols: np.ndarray, places: np.ndarray) -> np.ndarray:
        out = np.zeros(len(symbols), np.int64)
        for states, number in zip(self.states, self.candidates(symbols, places), strict=False):
            here = np.flatnonzero(number >= 0)
            found = states[number[here]]
            out[here[found > 0]] = found[found > 0]
        return out

    def gains(self, symbols: np.ndarray, states: np.ndarray) -> np.ndarray:
        """log10 of each symbol's probability in its state over its probability at the root."""
        out, todo = np.zeros(len(symbols)), np.flatnonzero(states > 0)
        state = states[todo]
        while len(todo):
            sym = symbols[todo]
            at, ok = self.find(self.spelled, state * len(self.heads) + sym)
            ok &= sym >= 0
            out[todo] += np.where(ok, self.gain[at] if len(self.gain) else 0.0, self.back[state])
            state = self.suffix[state]
            on = ~ok & (state > 0)
            todo, state = todo[on], state[on]
        return out

    def root_log(self, symbols: np.ndarray) -> np.ndarray:
        return self.head_log[symbols] - np.log10(self.n + ADD * (self.v + 1))

    def grow(self, places: np.ndarray, shorter: np.ndarray, context: np.ndarray, sym: np.ndarray, times: np.ndarray) -> np.ndarray:
        """Adds the next order: those of its candidates that pass the divergence test. Returns the longest state of each.

        ``places`` and ``shorter``, by candidate: its places and the longest state of its suffix. (context, sym, times),
        sorted: the next symbols that it would spell out.
        """
        root = self.root_log(sym)
        low = 10 ** (root + self.gains(sym, shorter[context]))
        p = (times + MASS * low) / (places[context] + MASS)
        together = lambda x: np.bincount(context, x, len(places))
        rest, low_rest = np.maximum(1 - together(p), 1e-9), np.maximum(1 - together(low), 1e-9)
        kept = together(p * np.log(p / low)) + rest * np.log(rest / low_rest) >= LEAST_DIVERGENCE
        state = np.where(kept, len(self.suffix) - 1 + np.cumsum(kept), 0)
        mine = kept[context]
        self.spelled = np.concatenate([self.spelled, state[context[mine]] * len(self.heads) + sym[mine]])
        self.gain = np.concatenate([self.gain, (np.log10(p) - root)[mine]])
        self.back = np.concatenate([self.back, np.log10(rest / low_rest)[kept]])
        self.suffix = np.concatenate([self.suffix, shorter[kept]])
        self.states.append(state)
        return np.where(kept, state, shorter)


class SuffixTree:
    def __init__(self, tree: Tree, counts: DataFrame):
        self.tree, self.counts = tree, counts

    @classmethod
    def fit(cls, texts: DataFrame, scratch: Scratch, text: str = "text", depth: int = DEPTH) -> SuffixTree:
        texts = texts.select(F.col(text).alias("text"))
        context = texts.sparkSession.sparkContext
        total = lambda df, keys_of: df.mapInArrow(counting(keys_of), "k bigint, n bigint").groupBy("k").agg(F.sum("n").alias("n"))
        counts = scratch.keep(total(texts, word_hashes))
        n, v = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
        head = counts.where(F.col("n") >= max(HEAD_SHARE * n, 1)).toArrow()
        order = np.argsort(head.column("k").to_numpy())
        heads, head_n = head.column("k").to_numpy()[order], head.column("n").to_numpy()[order]
        tree = Tree(heads, np.log10(head_n + ADD), n, v)
        if not n:
            return cls(tree, counts)
        least = max(LEAST_PLACES, math.sqrt(n) / ROOT_PART)
        as_context = np.flatnonzero((head_n >= least) & (heads != END))
        tree.context_of = np.full(len(heads), -1, np.int64)
        tree.context_of[as_context] = np.arange(len(as_context))
        tree.n_contexts = len(as_context) + 1
        n_texts = int(head_n[heads == END].sum())
        tree.start = len(as_context) if n_texts >= least else -1

        shared = context.broadcast(vars(tree).copy())

        def as_symbols(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, hashes = Tree(**shared.value), Hasher()
            for batch in it:
                for group in in_groups([hashes(t) for t in batch.column(0).to_pylist()], len):
                    ends = np.cumsum([0, *map(len, group)])
                    symbols = own.symbols(np.concatenate(group)).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(symbols))], names=["symbols"])

        lines = scratch.keep(texts.mapInArrow(as_symbols, "symbols array<int>"))
        places = np.append(head_n[as_context], n_texts)
        shorter = np.zeros(len(places), np.int64)
        symbols_of = np.arange(len(places))[:, None]  # by candidate: its symbols as contexts, the last one first
        for m in range(1, depth + 1):
            sent = context.broadcast(vars(tree).copy())

            def keys_of(sent=sent, m=m):
                own = Tree(**sent.value)

                def make(column: pa.Array) -> Iterator[np.ndarray]:
                    for s, at in symbol_groups(column):
                        *_, number = own.candidates(s, at)
                        yield (number * len(own.heads) + s)[(number >= 0) & (s >= 0)]

                return make

            got = total(lines, keys_of).where(F.col("n") >= max(2, least / NEXT_PART)).toArrow()
            order = np.argsort(got.column("k").to_numpy())
            key, times = got.column("k").to_numpy()[order], got.column("n").to_numpy()[order]
            before, sym = key // len(heads), key % len(heads)
            longest = tree.grow(places, shorter, before, sym, times.astype(float))
            often = np.flatnonzero((times >= least) & (tree.context_of[sym] >= 0))
            if m == depth or not len(often):
                break
            new = np.column_stack([tree.context_of[sym[often]], symbols_of[before[often]]])
            suffix = new[:, 0]
            for names, further in zip(tree.names, new.T[1:-1], strict=True):
                suffix, _ = tree.find(names, suffix * tree.n_contexts + further)  # each has as many places, so is there
            name = suffix * tree.n_contexts + new[:, -1]
            order = np.argsort(name)
            tree.names.append(name[order])
            places, shorter, symbols_of = times[often][order], longest[suffix[order]], new[order]
        scratch.drop(lines)
        return cls(tree, counts)

    def score(self, docs: DataFrame, scratch: Scratch, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
        """doc_id, n_tokens, n_known, train_tokens, base_score, score of each row."""
        model = docs.sparkSession.sparkContext.broadcast(vars(self.tree).copy())  # plain values: they need no package on the executors
        tree = self.tree
        kind = docs.schema[doc_id].dataType.simpleString()

        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, hashes = Tree(**model.value), Hasher()
            row = TaskContext.get().partitionId() << 40
            for batch in it:
                done = 0
                for group in in_groups([hashes(t) for t in batch.column(1).to_pylist()], len):
                    lengths = np.array([len(h) for h in group])
                    s = own.symbols(np.concatenate(group))
                    known, of = s >= 0, np.repeat(np.arange(len(group)), lengths)
                    root = np.zeros(len(s))
                    root[known] = own.head_log[s[known]]
                    gain = own.gains(s, own.states_at(s, _places(lengths)))
                    together = lambda x: np.bincount(of, x, len(group))  # noqa: B023, E731
                    n_head = together(known).astype(np.int64)
                    rare = [np.unique(h[~own.find(own.heads, h)[1]], return_counts=True) if n_head[i] < len(h) else (_none(), _none()) for i, h in enumerate(group)]
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).slice(done, len(group)), pa.array(np.arange(row, row + len(group))), pa.array(lengths, pa.int64()), pa.array(n_head), pa.array(together(root)), pa.array(together(gain)), pa.array([r for r, _ in rare], pa.list_(pa.int64())), pa.array([c for _, c in rare], pa.list_(pa.int64()))],
                        names=["doc_id", "row", "n_tokens", "n_head", "base", "gain", "rare", "times"],
                    )
                    done, row = done + len(group), row + len(group)

        schema = f"doc_id {kind}, row bigint, n_tokens bigint, n_head bigint, base double, gain double, rare array<bigint>, times array<bigint>"
        rows = scratch.keep(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(batches, schema))
        rare = rows.select("row", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("row", F.col("x.rare").alias("k"), F.col("x.times").alias("m"))
        found = rare.join(self.counts, "k", "left").select("row", F.col("m"), F.coalesce("n", F.lit(0)).alias("n"))
        sums = found.groupBy("row").agg(F.sum(F.col("m") * F.log10(F.col("n") + ADD)).alias("rare_log"), F.sum(F.when(F.col("n") > 0, F.col("m")).otherwise(0)).alias("rare_known"))
        out = rows.select("doc_id", "row", "n_tokens", "n_head", "base", "gain").join(sums, "row", "left")
        whole = float(np.log10(tree.n + ADD * (tree.v + 1)))
        base = F.col("base") + F.coalesce("rare_log", F.lit(0.0)) - F.col("n_tokens") * F.lit(whole)
        return out.select("doc_id", "n_tokens", (F.col("n_head") + F.coalesce("rare_known", F.lit(0))).alias("n_known"), F.lit(tree.n).cast("long").alias("train_tokens"), base.alias("base_score"), (base + F.col("gain")).alias("score"))
