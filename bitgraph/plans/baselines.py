"""The alternatives that the tree index is compared with, behind the same calls: match, match_batch, size_bits."""

from __future__ import annotations

from collections.abc import Iterator
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitgraph.functions.geometry import Schedule, cell_code
from bitgraph.store import Scratch

IDS = ("s_id", "p_id", "o_id")
#: Predicates share this many files, never a folder each.
BUNDLES = 16
#: Bits of an ID by which gap-coded lists are cut into chunks.
CHUNK_BITS = 16
#: log2 of the list entries that are opened together.
OPEN_BITS = 18


def _bound(s, p, o) -> dict[str, int]:
    return {k: v for k, v in zip(IDS, (s, p, o), strict=True) if v is not None}


def varbyte_bits(gap: Column) -> Column:
    """Bits of a gap in bytes that carry seven bits each."""
    return 8 * reduce(lambda n, i: n + (F.shiftright(gap, 7 * i) > 0).cast("bigint"), range(1, 9), F.lit(1).cast("bigint"))


def _sorted_bits(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bits of gap-coded lists with their chunks, a sum a batch of sorted (a, b, c): a list is what (a, b) has in one chunk."""
    last = np.full((3, 1), -1, np.int64)  # before the first row: no ID is negative
    for batch in it:
        if not batch.num_rows:
            continue
        rows = np.stack([x.to_numpy() for x in batch.columns])
        before, last = np.concatenate((last, rows[:, :-1]), axis=1), rows[:, -1:]
        c, chunk = rows[2], rows[2] >> CHUNK_BITS
        new = (rows[0] != before[0]) | (rows[1] != before[1]) | (chunk != before[2] >> CHUNK_BITS)
        gap = c - np.where(new, chunk << CHUNK_BITS, before[2])
        n_bytes = len(c) + sum(int(np.count_nonzero(gap >> (7 * i))) for i in range(1, 9))
        yield pa.RecordBatch.from_arrays([pa.array([8 * n_bytes + 64 * int(np.count_nonzero(new))])], names=["n_bits"])


class Engine:
    """Facts in a table with the ID columns; subclasses choose tables by what a pattern binds."""

    name = "engine"

    def __init__(self, ids: DataFrame, scratch: Scratch):
        self.ids, self.scratch = ids, scratch

    def source(self, bound: frozenset[str]) -> DataFrame:
        raise NotImplementedError

    def match(self, s: int | None = None, p: int | None = None, o: int | None = None) -> DataFrame:
        t = self.source(frozenset(b := _bound(s, p, o)))
        for k, v in b.items():
            t = t.where(F.col(k) == v)
        if "p_id" in b and "bundle" in t.columns:
            t = t.where(F.col("bundle") == b["p_id"] % BUNDLES)
        return t.select(*IDS)

    def match_batch(self, bindings: DataFrame) -> DataFrame:
        on = [c for c in IDS if c in bindings.columns]
        if not on:
            return self.match() if bindings.limit(1).count() else self.match().limit(0)
        return self.source(frozenset(on)).join(bindings.select(*on).dropDuplicates(), on).select(*IDS)

    def size_bits(self) -> int:
        raise NotImplementedError


class TripleTable(Engine):
    """One table of three columns."""

    name = "triple_table"

    def source(self, bound):
        return self.ids

    def size_bits(self):
        return 96 * self.ids.count()


class ColumnPartitions(Engine):
    """A table of two columns per predicate, sorted by subject then object; with ``object_order`` a copy in the other order."""

    def __init__(self, ids, scratch, object_order: bool = False):
        super().__init__(ids, scratch)
        self.object_order = object_order
        self.name = "colpart_os" if object_order else "colpart"

    def _sorted(self, *order: str) -> DataFrame:
        rows = self.ids.withColumn("bundle", F.pmod("p_id", F.lit(BUNDLES)).cast("int"))
        path = f"{self.scratch.root}/{self.name}-{order[0]}"
        rows.repartition("bundle").sortWithinPartitions("p_id", *order).write.partitionBy("bundle").parquet(path)
        return self.ids.sparkSession.read.parquet(path)

    @cached_property
    def by_subject(self) -> DataFrame:
        return self._sorted("s_id", "o_id")

    @cached_property
    def by_object(self) -> DataFrame:
        return self._sorted("o_id", "s_id")

    def source(self, bound):
        return self.by_object if self.object_order and "o_id" in bound and "s_id" not in bound else self.by_subject

    def size_bits(self):
        return (128 if self.object_order else 64) * self.ids.count()


class ClusteredTables(Engine):
    """Tables of three columns, one for each set of predicates that ``min_support`` subjects have together."""

    name = "clustered"

    def __init__(self, ids, scratch, min_support: int = 20):
        super().__init__(ids, scratch)
        self.min_support = min_support

    @cached_property
    def table(self) -> DataFrame:
        sets = self.ids.groupBy("s_id").agg(F.sort_array(F.collect_set("p_id")).alias("ps"))
        common = sets.groupBy("ps").agg(F.count("*").alias("n")).where(F.col("n") >= self.min_support).select("ps", F.xxhash64("ps").alias("cluster"))
        clustered = self.ids.join(sets.join(common, "ps", "left").select("s_id", F.coalesce("cluster", F.lit(0)).alias("cluster")), "s_id")
        return self.scratch.keep(clustered.repartition("cluster").sortWithinPartitions("cluster", "p_id", "s_id", "o_id"))

    @cached_property
    def clusters_of(self) -> DataFrame:
        return self.scratch.keep(self.table.select("p_id", "cluster").distinct())

    def match(self, s=None, p=None, o=None):
        if p is None:
            return super().match(s, p, o)
        mine = [r["cluster"] for r in self.clusters_of.where(F.col("p_id") == p).collect()]  # sets of predicates, not data
        t = self.table.where(F.col("cluster").isin(mine))
        for k, v in _bound(s, p, o).items():
            t = t.where(F.col(k) == v)
        return t.select(*IDS)

    def source(self, bound):
        return self.table

    def size_bits(self):
        return 96 * self.ids.count()


class _Gaps(Engine):
    """Lists of a third coordinate for each pair of the others, as gaps."""

    def _gaps(self, a: str, b: str, c: str) -> DataFrame:
        parts = self.ids.withColumn("chunk", F.shiftright(c, CHUNK_BITS))
        lists = parts.groupBy(a, b, "chunk").agg(F.sort_array(F.collect_list(c)).alias("l"))  # 2 ** CHUNK_BITS at most
        gaps = F.transform("l", lambda x, i: F.when(i == 0, x - F.shiftleft("chunk", CHUNK_BITS)).otherwise(x - F.get("l", i - 1)))
        return lists.select(a, b, "chunk", gaps.alias("gaps"))

    def _lists(self, a: str, b: str, c: str) -> DataFrame:
        return self.scratch.keep(self._gaps(a, b, c).repartitionByRange(a, b).sortWithinPartitions(a, b, "chunk"))

    def _pick(self, bound: frozenset[str]) -> tuple[DataFrame, tuple[str, str, str]]:
        """The lists for what a pattern binds, and the order of their coordinates."""
        raise NotImplementedError

    def source(self, bound):
        return self._open(*self._pick(bound))

    def match(self, s=None, p=None, o=None):
        b = _bound(s, p, o)
        lists, k = self._pick(frozenset(b))
        for c in k[:2]:
            lists = lists.where(F.col(c) == b[c]) if c in b else lists
        found = self._open(lists, k)
        return found.where(F.col(k[2]) == b[k[2]]) if k[2] in b else found

    def match_batch(self, bindings):
        """Only lists that a binding names are opened."""
        on = [c for c in IDS if c in bindings.columns]
        if not on:
            return super().match_batch(bindings)
        lists, k = self._pick(frozenset(on))
        wanted = bindings.select(*on).dropDuplicates()
        if keys := [c for c in k[:2] if c in on]:
            lists = lists.join(wanted.select(*keys), keys, "left_semi")
        found = self._open(lists, k)
        return found.join(wanted, on).select(*IDS) if k[2] in on else found

    @staticmethod
    def _open(lists: DataFrame, k: tuple[str, str, str]) -> DataFrame:
        a, b, c = k

        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in it:
                n = batch.column("gaps").value_lengths().to_numpy()
                together = np.cumsum(n) >> OPEN_BITS
                cuts = [0, *(np.flatnonzero(together[1:] != together[:-1]) + 1).tolist(), len(n)]
                for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                    part, m = batch.slice(i, j - i), n[i:j]
                    running = np.concatenate(([0], np.cumsum(part.column("gaps").flatten().to_numpy())))
                    start = (part.column("chunk").to_numpy() << CHUNK_BITS) - running[np.cumsum(m) - m]
                    out = {a: np.repeat(part.column(a).to_numpy(), m), b: np.repeat(part.column(b).to_numpy(), m), c: running[1:] + np.repeat(start, m)}
                    yield pa.RecordBatch.from_arrays([pa.array(out[x]) for x in IDS], names=list(IDS))

        return lists.select(a, b, "chunk", "gaps").mapInArrow(batches, "s_id bigint, p_id bigint, o_id bigint")

    def _list_bits(self, k: tuple[str, str, str]) -> int:
        """Bits of the lists of an order, with 64 of their chunk each; no list is written for it.

        A pair has the same lists in either order of its coordinates, so engines on the same facts measure those of a
        pair once.
        """
        a, b, c = k
        measured = self.ids.__dict__.setdefault("_list_bits", {})
        if (key := (frozenset((a, b)), c)) not in measured:
            dealt = self.ids.select(a, b, c).repartition(a, b, F.shiftright(c, CHUNK_BITS)).sortWithinPartitions(a, b, c)
            bits = dealt.mapInArrow(_sorted_bits, "n_bits bigint")
            measured[key] = bits.agg(F.coalesce(F.sum("n_bits"), F.lit(0))).first()[0]
        return measured[key]

    @staticmethod
    def _gap_bits(lists: DataFrame) -> int:
        total = F.aggregate(F.transform("gaps", varbyte_bits), F.lit(0).cast("bigint"), lambda a, g: a + g)
        return lists.agg(F.coalesce(F.sum(total), F.lit(0))).first()[0]


class SixOrder(_Gaps):
    """All six orders of the coordinates; a pattern reads the one that begins with what it binds."""

    ORDERS = (("s_id", "p_id", "o_id"), ("s_id", "o_id", "p_id"), ("p_id", "s_id", "o_id"), ("p_id", "o_id", "s_id"), ("o_id", "p_id", "s_id"), ("o_id", "s_id", "p_id"))

    def __init__(self, ids, scratch, gaps: bool = True):
        super().__init__(ids, scratch)
        self.gaps, self.name, self._made = gaps, "six" if gaps else "six_plain", {}

    def order(self, k: tuple[str, str, str]) -> DataFrame:
        if k not in self._made:
            self._made[k] = self._lists(*k) if self.gaps else self.scratch.keep(self.ids.select(*k).repartitionByRange(*k).sortWithinPartitions(*k))
        return self._made[k]

    def _pick(self, bound):
        k = next(k for k in self.ORDERS if set(k[: len(bound)]) == bound)
        return self.order(k), k

    def source(self, bound):
        return super().source(bound) if self.gaps else self._pick(bound)[0]

    def match(self, s=None, p=None, o=None):
        return super().match(s, p, o) if self.gaps else Engine.match(self, s, p, o)

    def match_batch(self, bindings):
        return super().match_batch(bindings) if self.gaps else Engine.match_batch(self, bindings)

    def size_bits(self):
        if not self.gaps:
            return 6 * 96 * self.ids.count()
        return sum(self._list_bits(k) for k in self.ORDERS)


class BitSlices(_Gaps):
    """The S x P x O bit cube cut into subject-object and object-subject slices per predicate, and slices per subject and object."""

    name = "slices"
    FAMILIES = {"SO": ("p_id", "s_id", "o_id"), "OS": ("p_id", "o_id", "s_id"), "PO": ("s_id", "p_id", "o_id"), "PS": ("o_id", "p_id", "s_id")}

    @cached_property
    def _made(self) -> dict[str, DataFrame]:
        return {}

    def family(self, name: str) -> DataFrame:
        if name not in self._made:
            self._made[name] = self._lists(*self.FAMILIES[name])
        return self._made[name]

    def _pick(self, bound):
        if "p_id" in bound:
            name = "OS" if "o_id" in bound and "s_id" not in bound else "SO"
        else:
            name = "PO" if "s_id" in bound else "PS" if "o_id" in bound else "SO"
        return self.family(name), self.FAMILIES[name]

    def size_bits(self):
        return sum(self._list_bits(k) for k in self.FAMILIES.values())


class SqlTables(Engine):
    """SQL text over a view."""

    name = "sql"

    def match(self, s=None, p=None, o=None):
        where = " AND ".join(f"{k} = {int(v)}" for k, v in _bound(s, p, o).items()) or "true"
        return self.ids.sparkSession.sql(f"SELECT s_id, p_id, o_id FROM {{facts}} WHERE {where}", facts=self.ids)

    def match_batch(self, bindings):
        on = [c for c in IDS if c in bindings.columns]
        if not on:
            return super().match_batch(bindings)
        return self.ids.sparkSession.sql(f"SELECT f.s_id, f.p_id, f.o_id FROM {{facts}} f WHERE EXISTS (SELECT 1 FROM {{b}} b WHERE {' AND '.join(f'b.{c} = f.{c}' for c in on)})", facts=self.ids, b=bindings)

    def size_bits(self):
        return 96 * self.ids.count()


class ZOrderPartitions(Engine):
    """Points sorted by interleaved code, without a tree: only statistics skip."""

    name = "zorder"

    def __init__(self, ids, scratch, dim: int):
        super().__init__(ids, scratch)
        self.dim = dim

    @cached_property
    def table(self) -> DataFrame:
        code = cell_code(F.col("s_id") - 1, F.col("o_id") - 1, Schedule.uniform(2, self.dim))
        return self.scratch.keep(self.ids.withColumn("z", code).repartitionByRange("p_id", "z").sortWithinPartitions("p_id", "z").select(*IDS))

    def source(self, bound):
        return self.table

    def size_bits(self):
        return 64 * self.ids.count()


ENGINES = ("triple_table", "colpart", "colpart_os", "clustered", "six", "six_plain", "slices", "sql", "zorder")


def make(name: str, ids: DataFrame, scratch: Scratch, dim: int) -> Engine:
    return {
        "triple_table": lambda: TripleTable(ids, scratch), "colpart": lambda: ColumnPartitions(ids, scratch), "colpart_os": lambda: ColumnPartitions(ids, scratch, True), "clustered": lambda: ClusteredTables(ids, scratch),
        "six": lambda: SixOrder(ids, scratch), "six_plain": lambda: SixOrder(ids, scratch, False), "slices": lambda: BitSlices(ids, scratch), "sql": lambda: SqlTables(ids, scratch), "zorder": lambda: ZOrderPartitions(ids, scratch, dim),
    }[name]()
