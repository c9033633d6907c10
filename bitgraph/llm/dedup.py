"""Near-duplicate detection with bottom-k sketches from one hash function.

Every text becomes its set of hashed word shingles; equal sets form a class, and everything after works on classes. A
class keeps its SKETCH smallest hashes. Inverted lists hold, for each class, the rarest kept values, as many as may be
unshared and one more: values ordered by how many sketches hold them, so that common words and shared lines make long
lists only for texts of little else. Two sets at or over the threshold share such a value: for sets that fit a sketch
this is the prefix filter and certain, for larger ones it fails if more are unshared than DEVIATIONS allow for. Of two
sketches as many values of one as of the other are unshared, so the two places of a shared value are bounded each by
itself, and by the case in which one set contains the other, where most values are unshared. A list entry also carries a
signature of a few bits of its whole set, by which most pairs far below the threshold end before they are made.

A list is not expanded into all its pairs. Each member is compared with two pivots of the list, its smallest set and its
first class. A class is undecided if a list holds another one that it may be like, in another component; a semi-join
finds these without making the pairs. They get sketches of WIDE values, longer signatures and lists of their own, and at
most ROUNDS times each is compared with PIVOTS random members of its lists in other components, which joins most that can
be joined. Then all pairs of a list that are still in different components are compared; those inside a component could
join nothing. The longer signatures end with parities, by which a pair somewhat below the threshold ends too. A pair is made in the list of the first value that it shares, hardly in those of the others: an entry knows
the BEFORE values that its class lists before, and of two entries with a common one the pair is left to that one's list.
The first place is also the one where the filter lets through most. A pair's similarity is estimated on the union sketch,
which for sets that fit a sketch is exact. Bitmaps of the full sets then end most pairs below the threshold and none
other, and only the sets of those left are sent to be counted. Components come from alternating stars. Nothing is
collected to the driver.

Defined results: text without words (null, empty) is linked with nothing; a text of fewer words than a shingle is one
shingle; repeated rows are one class; a null id takes part, but names no component unless no other id does; an empty
table gives an empty result; columns of other names are dropped.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ROW_KEY, Scratch, row_key, slices, whole
from .components import components

WIDTH = 5
THRESHOLD = (80, 100)
SKETCH = 32
#: Values in the sketch of an undecided class.
WIDE = 512
#: Rounds of comparison with random members of a list, and how many of them a round. A round that joins fewer than one in
#: FRUITFUL of the undecided classes is the last.
ROUNDS, PIVOTS, FRUITFUL = 3, 16, 50
#: Pairs whose estimate on a union sketch of 32 is this far below the threshold are over it with the chance that 22 values or more of 32 are unshared.
LEAST_ESTIMATE = 0.34
#: Standard deviations of the number of unshared values of a sketch that are allowed for.
DEVIATIONS = 6.5
#: Bits of a signature (a multiple of 64) by the size of the sketch beside it, and the greatest chance that a pair at the threshold fails its test.
SIGNED, SIGNED_LOSS = {SKETCH: 128, WIDE: 512}, 1e-10
#: Bits of the parities that a wide signature ends with (a multiple of 64).
PARITY = 512
#: Values of a class before an entry of the widest lists that the entry knows.
BEFORE = 4
#: Least bits of a set's bitmap for each of its values; the number of bits is a power of two.
BITMAP = 8
#: Keys of texts that may be broadcast (24 bytes each); more are joined by a shuffle.
MOST_BROADCAST = 1_000_000
#: Bytes of full sets that may be broadcast; more are joined by a shuffle.
MOST_SET_BYTES = 16 << 20
#: Hashes of words that a worker remembers.
REMEMBERED = 1 << 17


class Shingler:
    """Sorted distinct 64-bit shingle hashes of texts; remembers the hashes of words."""

    def __init__(self, width: int):
        self.width, self.known = width, {}

    def words(self, text: str) -> np.ndarray:
        known, out = self.known, []
        if len(known) > REMEMBERED:
            known.clear()
        for w in text.encode("utf-8", "surrogatepass").lower().split():
            h = known.get(w)
            if h is None:
                h = known[w] = xxhash.xxh64_intdigest(w)
            out.append(h)
        return np.array(out, dtype=np.uint64)

    def __call__(self, text: str | None) -> np.ndarray:
        h = self.words(text or "")
        n = min(self.width, len(h))
        if not n:
            return np.empty(0, np.int64)
        mixed = np.zeros(len(h) - n + 1, np.uint64)
        for k in range(n):
            mixed = (mixed ^ h[k : k + len(mixed)]) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(29)
        mixed = mixed * np.uint64(0xBF58476D1CE4E5B9)
        return np.unique((mixed ^ (mixed >> np.uint64(32))).view(np.int64))


def signature(hashes: np.ndarray, bits: int) -> np.ndarray:
    """Bits of a sorted set as 64-bit integers: the values fall in as many bins, and the least of a bin gives its bit."""
    out = np.zeros(bits, np.uint8)
    least_last = hashes[::-1]
    out[least_last & (bits - 1)] = (least_last >> 20) & 1  # of equal places the last one written stays
    return np.packbits(out).view(np.int64)


def parities(hashes: np.ndarray, bits: int = PARITY) -> np.ndarray:
    """Bits of a set as 64-bit integers: the values fall in as many bins, and a bin's bit tells if they are odd in number.

    Bits of two sets that differ are no more than the values that only one of them holds, and hardly fewer where these
    are few to the bins: a bin with an even number of such values, or none, has the same bit in both.
    """
    odd = np.bincount(hashes & (bits - 1), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def wide_signature(hashes: np.ndarray) -> np.ndarray:
    return np.concatenate([signature(hashes, SIGNED[WIDE]), parities(hashes)])


def bitmap(hashes: np.ndarray) -> bytes:
    """A bit for each value of a set, in places by the value's low bits; values may fall together."""
    bits = max(64, 1 << (BITMAP * len(hashes) - 1).bit_length())
    out = np.zeros(bits, np.uint8)
    out[hashes & (bits - 1)] = 1
    return np.packbits(out).tobytes()


def least_apart(p: np.ndarray, q: np.ndarray) -> int:
    """Values at least that only one of two sets holds, from their bitmaps: a bit that differs needs one of its own."""
    p, q = (np.bitwise_or.reduce(x.reshape(-1, min(len(p), len(q)))) for x in (p, q))
    return int(np.bitwise_count(p ^ q).sum())


def most_different(over: int, under: int, bits: int) -> int:
    """Bits that may differ between signatures at the threshold; more do with a chance of at most SIGNED_LOSS.

    The least value of a bin is in one set only with a chance of at most one less the similarity, and then its bit differs
    every second time.
    """
    p, chance, k = (1 - over / under) / 2, 0.0, bits
    while k:
        chance += math.comb(bits, k) * p**k * (1 - p) ** (bits - k)
        if chance > SIGNED_LOSS:
            break
        k -= 1
    return k


def _listed(over: int, under: int, size: int) -> int:
    """Values listed of a sketch of a larger set: one more than may be unshared at the threshold, where a set holds the other."""
    p = 1 - over / under
    return min(size, int(size * p + DEVIATIONS * math.sqrt(size * p * (1 - p))) + 1)


def _sketches(width: int, size: int):
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingles = Shingler(width)
        for batch in slices(it):
            sets = [shingles(t) for t in batch.column(2).to_pylist()]
            cid = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets]
            lists, signs = pa.array([s[:size] for s in sets], pa.list_(pa.int64())), pa.array([signature(s, SIGNED[size]) for s in sets], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([len(s) for s in sets], pa.int64()), pa.array(cid, pa.binary()), lists, signs], names=["doc_id", "key", "n", "cid", "sketch", "sign"])

    return batches


def _sets(width: int):
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingles = Shingler(width)
        for batch in slices(it):
            sets = [shingles(t) for t in batch.column(2).to_pylist()]
            lists, signs = pa.array(sets, pa.list_(pa.int64())), pa.array([wide_signature(s) for s in sets], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), signs, pa.array([bitmap(s) for s in sets], pa.binary()), lists, batch.column(3)], names=["c", "n", "sign", "bitmap", "hashes", "many"])

    return batches


def _near(over: int, under: int):
    """(a, b, n, m, bitmap of a, bitmap of b) to those (a, b) that may be at the threshold; no pair at or over it is lost."""
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(it):
            both = (batch.column(2).to_numpy() + batch.column(3).to_numpy()).tolist()
            # common / together >= over / under, where common + together = both and together - common = apart
            near = [(under + over) * least_apart(*(np.frombuffer(v.as_buffer(), np.uint8) for v in (x, y))) <= (under - over) * k for x, y, k in zip(batch.column(4), batch.column(5), both, strict=True)]
            yield batch.select([0, 1]).filter(pa.array(near, pa.bool_()))

    return batches


def _common(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, b, hashes of a, hashes of b) to (a, b, common, together)."""
    for batch in slices(it):
        common, together = [], []
        for x, y in zip(batch.column(2), batch.column(3), strict=True):
            p, q = (v.values.to_numpy() for v in (x, y))
            c = len(np.intersect1d(p, q, assume_unique=True))
            common.append(c)
            together.append(len(p) + len(q) - c)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(common, pa.int64()), pa.array(together, pa.int64())], names=["a", "b", "common", "together"])


def estimate(p: str, q: str) -> Column:
    """Jaccard similarity estimated on the smallest values of the union of two sketches; exact where both hold whole sets."""
    whole_sets = (F.size(p) < SKETCH) & (F.size(q) < SKETCH)
    union = F.slice(F.array_sort(F.array_union(p, q)), F.lit(1), F.when(whole_sets, F.lit(2 * SKETCH)).otherwise(SKETCH))
    return F.size(F.array_intersect(F.array_intersect(p, q), union)) / F.size(union)


class NearDuplicates:
    """Classes, links and components of the rows of ``docs``."""

    def __init__(self, docs: DataFrame, scratch: Scratch, width: int = WIDTH, threshold: tuple[int, int] = THRESHOLD, doc_id: str = "doc_id", text: str = "text"):
        self.scratch, self.width, self.threshold, self.roots = scratch, width, threshold, None
        self.texts = docs.select(F.col(doc_id).alias("doc_id"), row_key(F.col(doc_id), whole(text)).alias("key"), F.col(text).alias("text"))
        schema = f"doc_id {docs.schema[doc_id].dataType.simpleString()}, key {ROW_KEY}, n bigint, cid binary, sketch array<bigint>, sign array<bigint>"
        sketched = scratch.keep(self.texts.mapInArrow(_sketches(width, SKETCH), schema))
        grouped = sketched.where("cid IS NOT NULL").groupBy("cid").agg(F.min("doc_id").alias("rep"), F.min("key").alias("key"), F.first("n").alias("n"), F.first("sketch").alias("sketch"), F.first("sign").alias("sign"), (F.count("*") > 1).alias("many"))
        self.classes = scratch.keep(grouped.withColumn("c", F.monotonically_increasing_id()))  # numbers, a third of the bytes of a hash
        self.rows = scratch.keep(sketched.select("doc_id", "key", "n", "cid"))  # sketches stay with the classes only
        scratch.drop(sketched)

    def lists(self, classes: DataFrame, size: int) -> DataFrame:
        """(v, c, n, at, before, sign): the inverted lists, of values that two of ``classes`` or more list. ``at``: values of the class before v, ``before``: the last of them in lists."""
        kept = classes.select("c", F.explode("sketch").alias("v"))
        held = kept.withColumn("held", F.count("*").over(Window.partitionBy("v"))).where("held > 1")  # one shuffle, and it spills
        mine = held.groupBy("c").agg(F.sort_array(F.collect_list(F.struct("held", "v"))).alias("vs"))  # a sketch at most
        mine = mine.join(classes.select("c", "n", "sign"), "c")
        fits = F.col("n") * self.threshold[1] <= F.lit(size * self.threshold[0])  # and so do all sets that may be like it
        part = F.when(fits, F.col("n") - F.ceil(F.col("n") * self.threshold[0] / self.threshold[1]) + 1).otherwise(_listed(*self.threshold, size))
        alone = F.least(F.col("n"), F.lit(size)) - F.size("vs")  # values of no other class come first in the order
        left = F.greatest(part - alone, F.lit(0)).cast("int")
        last = lambda i: F.slice("vs.v", F.greatest(i - BEFORE, F.lit(0)) + 1, F.least(i, F.lit(BEFORE)))
        placed = F.transform(F.slice("vs", F.lit(1), left), lambda x, i: F.struct(x["v"].alias("v"), (i + alone).alias("at"), last(i).alias("before")))
        return mine.select("c", "n", "sign", F.explode(placed).alias("x")).select("x.v", "c", "n", "x.at", "x.before", "sign")

    def _alike(self, size: int, n: Column, at: Column, sign: Column, m: Column, bt: Column, mark: Column) -> Column:
        """Length, positional, signature and parity filter of two classes of n and m values that meet at places at and bt of a list.

        At the first value they share, what lies before it is in one of the two sketches only: exact for sets that fit a
        sketch. For larger ones its expected number in each, at the threshold, is that of the larger set's own values.
        """
        over, under = self.threshold
        least, most = F.least(n, m), F.greatest(n, m)
        common = F.least(n - at, m - bt)
        exact = under * common >= over * (n + m - common)
        own = 1 - (1 + least / most) * (over / (over + under))  # share of the larger set's values that the other lacks
        likely = F.greatest(at, bt) <= size * own + DEVIATIONS * F.sqrt(size * own * (1 - own))
        bits = SIGNED[size]
        differ = lambda first, end: sum((F.bit_count(sign[i].bitwiseXOR(mark[i])) for i in range(first // 64, end // 64)), F.lit(0))
        signed = (most <= SKETCH) | (differ(0, bits) <= most_different(over, under, bits))
        if size == WIDE:  # values apart at the threshold are the share of _near, and the parities that differ are no more
            signed &= (under + over) * differ(bits, bits + PARITY) <= (under - over) * (n + m)
        return (under * least >= over * most) & F.when(most <= size, exact).otherwise(likely) & signed

    def _full_sets(self, wanted: DataFrame) -> DataFrame:
        """(c, n, sign, bitmap, hashes) of the classes ``wanted`` (c)."""
        wanted = self.scratch.keep(wanted.distinct().join(self.classes.select("c", "key", "n", "many"), "c"))
        sent = F.broadcast(wanted) if wanted.count() <= MOST_BROADCAST else wanted
        texts = self.texts.select("key", "text").join(sent, "key").select("c", "n", "text", "many")
        sets = texts.mapInArrow(_sets(self.width), "c bigint, n bigint, sign array<bigint>, bitmap binary, hashes array<bigint>, many boolean")
        sets = self.scratch.keep(sets)
        again = self.scratch.keep(sets.where("many").dropDuplicates(["c"]))  # the key of a repeated row finds it as often
        self.scratch.drop(wanted)
        out = sets.where("NOT many").union(again).drop("many")
        out.parts = (sets, again)
        return out

    def _estimated(self, pairs: DataFrame) -> DataFrame:
        """Those of ``pairs`` that the union sketch does not put far below the threshold."""
        sketch = self.classes.select("c", "sketch")
        of = lambda side: sketch.select(F.col("c").alias(side), F.col("sketch").alias(f"{side}_sketch"))
        whole_sets = (F.size("a_sketch") < SKETCH) & (F.size("b_sketch") < SKETCH)
        least = F.when(whole_sets, F.lit(self.threshold[0] / self.threshold[1] - 1e-9)).otherwise(LEAST_ESTIMATE)
        return pairs.join(of("a"), "a").join(of("b"), "b").where(estimate("a_sketch", "b_sketch") >= least).select("a", "b")

    def verify(self, pairs: DataFrame, sets: DataFrame | None = None) -> DataFrame:
        """(a, b, common, together) of those of the distinct ``pairs`` (a, b) at or over the threshold. ``sets``: the full ones, if there."""
        own = sets is None
        likely = self.scratch.keep(self._estimated(pairs) if own else pairs)  # the wide signatures told as much
        if own:
            sets = self._full_sets(likely.select(F.col("a").alias("c")).union(likely.select(F.col("b").alias("c"))))
        near = self.scratch.keep(self._with(likely, sets, "n", "bitmap", size=F.octet_length("bitmap")).select("a", "b", "a_n", "b_n", "a_bitmap", "b_bitmap").mapInArrow(_near(*self.threshold), "a bigint, b bigint"))
        ends = self.scratch.keep(near.select(F.col("a").alias("c")).union(near.select(F.col("b").alias("c"))).distinct())
        used = sets.join(F.broadcast(ends), "c", "left_semi") if ends.count() <= MOST_BROADCAST else sets
        full = self._with(near, used, "hashes", size=8 * F.col("n")).select("a", "b", "a_hashes", "b_hashes")
        counted = full.mapInArrow(_common, "a bigint, b bigint, common bigint, together bigint")
        out = self.scratch.keep(counted.where(F.col("common") * self.threshold[1] >= F.col("together") * self.threshold[0]))
        self.scratch.drop(likely, near, ends, *(sets.parts if own else ()))
        return out

    @staticmethod
    def _with(pairs: DataFrame, sets: DataFrame, *columns: str, size: Column) -> DataFrame:
        """``pairs`` with columns of the sets of both ends, as a_... and b_...; ``size``: bytes that a set takes."""
        sent = F.broadcast if sets.agg(F.coalesce(F.sum(size), F.lit(0))).first()[0] <= MOST_SET_BYTES else lambda t: t  # a set may be in many pairs
        for s in ("a", "b"):
            pairs = pairs.join(sent(sets.select(F.col("c").alias(s), *[F.col(k).alias(f"{s}_{k}") for k in columns])), s)
        return pairs

    def _rooted(self, lists: DataFrame, roots: DataFrame) -> DataFrame:
        """The lists that hold classes of different components, with the component r."""
        rooted = lists.join(roots, lists["c"] == roots["node"], "left").select(*lists.columns, F.coalesce("root", "c").alias("r"))
        mixed = rooted.groupBy("v").agg(F.min("r").alias("x"), F.max("r").alias("y")).where("x <> y").select("v")
        return self.scratch.keep(rooted.join(mixed, "v"))

    def _across(self, size: int) -> Column:
        """Of two list entries, (c, n, at, sign, r) and (b, m, bt, mark, q): whether they may be links between components."""
        return (F.col("c") != F.col("b")) & (F.col("r") != F.col("q")) & self._alike(size, F.col("n"), F.col("at"), F.col("sign"), F.col("m"), F.col("bt"), F.col("mark"))

    @staticmethod
    def _other(lists: DataFrame, *more: Column) -> DataFrame:
        return lists.select("v", F.col("c").alias("b"), F.col("n").alias("m"), F.col("at").alias("bt"), F.col("sign").alias("mark"), F.col("r").alias("q"), *more)

    def pairs_across(self, lists: DataFrame) -> DataFrame:
        """(a, b), a > b: all pairs of the widest lists that may be links between components, seldom more than once."""
        meet = lists.join(self._other(lists, F.col("before").alias("prior")), "v")
        first = ~F.arrays_overlap("before", "prior")
        return meet.where((F.col("c") > F.col("b")) & self._across(WIDE) & first).select(F.col("c").alias("a"), "b")

    def links(self) -> Iterator[DataFrame]:
        """Tables (a, b, common, together) of verified links, enough to connect all that are connected. Leaves ``roots``."""
        other, pair = self._other, (F.greatest("c", "b").alias("a"), F.least("c", "b").alias("b"))
        lists = self.scratch.keep(self.lists(self.classes, SKETCH).drop("before").withColumn("r", F.col("c")))
        ends = lists.groupBy("v").agg(F.min(F.struct("c", "n", "at", "sign", "r")).alias("f"), F.min(F.struct("n", "c", "at", "sign", "r")).alias("g"))
        entry = lambda x: F.struct(*[F.col(f"{x}.{k}").alias(k) for k in ("c", "n", "at", "sign", "r")])
        pivots = ends.select("v", F.explode(F.array(entry("f"), entry("g"))).alias("x")).select("v", "x.*")
        yield self._join_in(self.verify(lists.join(other(pivots), "v").where(self._across(SKETCH)).select(*pair).distinct()))

        mixed = self._rooted(lists.drop("r"), self.roots)
        left = mixed.join(ends.select("v", F.col("f.c").alias("first"), F.col("g.c").alias("small")), "v").where("c <> first AND c <> small")  # pairs with the pivots are done
        left = self.scratch.keep(left.select("v", "c", "n", "at", "sign", "r"))
        self.scratch.drop(lists, mixed)
        on = other(left).withColumnRenamed("v", "w")
        undecided = left.join(on, (F.col("v") == F.col("w")) & self._across(SKETCH), "left_semi").select("c")
        sets = self._full_sets(undecided)
        self.scratch.drop(left)
        wide = self.scratch.keep(self.lists(sets.select("c", "n", "sign", F.slice("hashes", 1, WIDE).alias("sketch")), WIDE))

        turn, n_undecided = 0, sets.count()
        joined = n_undecided
        while turn < ROUNDS and joined * FRUITFUL >= n_undecided > 0:
            mixed = self._rooted(wide.drop("before"), self.roots)
            drawn = mixed.withColumn("h", F.xxhash64("c", "v", F.lit(turn)))
            pivots = drawn.groupBy("v", F.pmod("h", F.lit(PIVOTS)).alias("place")).agg(F.min(F.struct("h", "c", "n", "at", "sign", "r")).alias("x")).select("v", "x.*")
            found = self._join_in(self.verify(mixed.join(other(pivots), "v").where(self._across(WIDE)).select(*pair).distinct(), sets))
            turn, joined = turn + 1, found.count()
            yield found
            self.scratch.drop(mixed)

        mixed = self._rooted(wide, self.roots)
        yield self._join_in(self.verify(self.pairs_across(mixed).distinct(), sets))
        self.scratch.drop(wide, mixed, *sets.parts)

    def _join_in(self, found: DataFrame) -> DataFrame:
        """Puts links into the components so far. Only links between components count, with the roots as nodes."""
        edges, old, most = found.select("a", "b"), self.roots, found.count()
        if old is None:
            self.roots = components(edges, self.scratch, most=most)
            return found
        for side in ("a", "b"):
            root = old.select(F.col("node").alias(side), F.col("root").alias("up"))
            edges = edges.join(root, side, "left").withColumn(side, F.coalesce("up", side)).select("a", "b")
        merged = components(edges, self.scratch, most=most)
        moved = old.join(merged.select(F.col("node").alias("root"), F.col("root").alias("up")), "root", "left").select("node", F.coalesce("up", "root").alias("root"))
        self.roots = self.scratch.keep(moved.union(merged))
        return found

    def result(self) -> DataFrame:
        """doc_id, key, n_shingles, cid, component, component_id, kept of every row; the class ``cid`` is null without words."""
        for _ in self.links():
            pass
        roots = self.roots
        placed = self.classes.select("cid", "rep", "c").join(roots, F.col("c") == F.col("node"), "left").select("cid", "rep", F.coalesce("root", "c").alias("component"))
        least = placed.groupBy("component").agg(F.min("rep").alias("component_id"))
        by_class = placed.join(least, "component").select("cid", "component", "component_id")
        out = self.rows.select("doc_id", "key", "n", "cid").join(by_class, "cid", "left")
        component = F.when(F.col("cid").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
        return out.select("doc_id", "key", F.col("n").alias("n_shingles"), "cid", "component", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def representatives(docs: DataFrame, scratch: Scratch, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row of docs from each component, of its smallest id; rows without words all stay, but equal ones once."""
    found = near_duplicates(docs, scratch, doc_id=doc_id, text=text, **options)
    alone = found.where("cid IS NULL").groupBy("key").agg(F.count("*").alias("times"))
    by_key = found.where("cid IS NOT NULL AND kept").groupBy("component", "key").agg(F.count("*").alias("times"))
    one = by_key.groupBy("component").agg(F.min(F.struct("key", "times")).alias("x")).select("x.key", "x.times")
    chosen = scratch.keep(alone.union(one).groupBy("key").agg(F.max("times").alias("__times")).withColumnRenamed("key", "__key"))
    sent = F.broadcast(chosen) if chosen.count() <= MOST_BROADCAST else chosen
    keyed = docs.withColumn("__key", row_key(F.col(doc_id), whole(text))).join(sent, "__key")
    # only repeated rows are dealt out by key: texts are long
    return keyed.where("__times = 1").union(keyed.where("__times > 1").dropDuplicates(["__key"])).select(*docs.columns)


def near_duplicates(docs: DataFrame, scratch: Scratch, **options) -> DataFrame:
    return NearDuplicates(docs, scratch, **options).result()
