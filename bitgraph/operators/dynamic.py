"""Changes on a static index: insertions in a delta, deletions as tombstones, compaction of the tiles they touch."""

from __future__ import annotations

from dataclasses import dataclass
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitgraph.operators import dictionary
from bitgraph.operators.tiles import TreeIndex
from bitgraph.store import Scratch

if TYPE_CHECKING:
    from bitgraph.operators.graph import Graph

IDS = ["s_id", "p_id", "o_id"]


@dataclass
class DynamicIndex:
    """Facts of ``base`` and ``added`` without ``removed``. Each change gives a new value; nothing is changed in place."""

    base: TreeIndex
    added: DataFrame
    removed: DataFrame
    scratch: Scratch
    name: str = "dynamic"

    @classmethod
    def of(cls, base: TreeIndex, scratch: Scratch) -> DynamicIndex:
        none = base.tiles.sparkSession.createDataFrame([], "s_id bigint, p_id bigint, o_id bigint")
        return cls(base, none, none, scratch)

    def insert(self, facts: DataFrame) -> DynamicIndex:
        facts = facts.select(*IDS).dropDuplicates()
        added = self.added.union(facts).dropDuplicates()
        return DynamicIndex(self.base, self.scratch.keep(added), self.scratch.keep(self.removed.join(facts, IDS, "left_anti")), self.scratch)

    def delete(self, facts: DataFrame) -> DynamicIndex:
        facts = facts.select(*IDS).dropDuplicates()
        return DynamicIndex(self.base, self.scratch.keep(self.added.join(facts, IDS, "left_anti")), self.scratch.keep(self.removed.union(facts).dropDuplicates()), self.scratch)

    def update(self, old: DataFrame, new: DataFrame) -> DynamicIndex:
        return self.delete(old).insert(new)

    def _with(self, found: DataFrame, added: DataFrame) -> DataFrame:
        return found.union(added.select(*IDS)).dropDuplicates().join(self.removed, IDS, "left_anti").select(*IDS)

    def match(self, s=None, p=None, o=None) -> DataFrame:
        mine = self.added
        for c, v in zip(IDS, (s, p, o), strict=True):
            mine = mine.where(F.col(c) == v) if v is not None else mine
        return self._with(self.base.match(s, p, o), mine)

    def match_batch(self, bindings: DataFrame) -> DataFrame:
        on = [c for c in IDS if c in bindings.columns]
        mine = self.added.join(bindings.select(*on).dropDuplicates(), on) if on else self.added
        return self._with(self.base.match_batch(bindings), mine)

    def compact(self, dim: int | None = None) -> TreeIndex:
        """A static index again. Tiles that no change touches are kept as they are; IDs may have grown beyond the old side.

        What is rebuilt is as wide as the largest tile: a predicate, where one tile can hold a whole matrix.
        """
        b = self.base.bits
        changed = self.added.union(self.removed).select("p_id", F.shiftright(F.col("s_id") - 1, b).alias("br"), F.shiftright(F.col("o_id") - 1, b).alias("bc")).distinct()
        placed = self.base.tiles.withColumns({"br": F.shiftright("row0", b), "bc": F.shiftright("col0", b)})
        same = placed.join(changed, ["p_id", "br", "bc"], "left_anti").drop("br", "bc")
        touched = TreeIndex(placed.join(changed, ["p_id", "br", "bc"], "left_semi").drop("br", "bc"), b, self.base.dim, self.base.n_so)
        facts = self._with(touched.match(), self.added)
        side = 1 << b
        rebuilt = TreeIndex.build(facts, side, self.base.n_so, self.scratch)
        return TreeIndex(self.scratch.keep(same.select(*rebuilt.tiles.columns).union(rebuilt.tiles)), b, max(dim or 0, self.base.dim), self.base.n_so)


@dataclass
class DynamicGraph:
    """A graph that takes facts of terms, known or new, without a new dictionary.

    A term that a role is new for gets the next ID of that role, as a row of its own beside the old ones: the large table
    of terms is not rewritten. Its two IDs may then differ, and ``aliases`` pairs them; the pairs grow with what was
    inserted. ``compact`` numbers everything anew, as a term that moves to the shared range shifts all behind it.
    """

    terms: DataFrame
    predicates: DataFrame
    index: DynamicIndex
    n_so: int
    tops: dict[str, int]
    aliases: DataFrame
    scratch: Scratch

    @classmethod
    def of(cls, graph: Graph, scratch: Scratch) -> DynamicGraph:
        c = graph.counts
        none = graph.spark.createDataFrame([], "o_id bigint, s_id bigint")
        tops = {"s": c["n_so"] + c["n_s"], "o": c["n_so"] + c["n_o"], "p": graph.n_p}
        return cls(graph.terms, graph.predicates, DynamicIndex.of(graph.index(), scratch), graph.n_so, tops, none, scratch)

    def _numbered(self, fresh: DataFrame, role: str, tops: dict[str, int]) -> DataFrame:
        """(term, id) of terms that the role is new for, in the order of terms behind the IDs given so far."""
        rows, sizes = dictionary._dense(fresh.select("term").distinct(), self.scratch, F.lit(0), "term")
        first = tops[role] + 1
        tops[role] += sizes.get(0, 0)
        return self.scratch.keep(rows.select("term", (F.col("at") + first).alias("id")))

    def insert(self, facts: DataFrame) -> DynamicGraph:
        """Facts (s, p, o) of terms. Rows with a null are dropped; facts that are there already change nothing."""
        facts = self.scratch.keep(facts.select("s", "p", "o").dropna().dropDuplicates())
        tops, none = dict(self.tops), F.lit(None).cast("bigint")
        new = {}
        for role in "so":
            known = self.terms.where(f"{role}_id IS NOT NULL").select("term")
            new[role] = self._numbered(facts.select(F.col(role).alias("term")).join(known, "term", "left_anti"), role, tops)
        fresh = new["s"].select("term", F.lit("S").alias("role"), F.col("id").alias("s_id"), none.alias("o_id")).union(new["o"].select("term", F.lit("O").alias("role"), none.alias("s_id"), F.col("id").alias("o_id")))
        terms = self.terms.select("term", "role", "s_id", "o_id").union(fresh)
        p_new = self._numbered(facts.select(F.col("p").alias("term")).join(self.predicates.select(F.col("pred").alias("term")), "term", "left_anti"), "p", tops)
        predicates = self.predicates.select("pred", "p_id").union(p_new.select("term", "id"))
        # A pair has at least one new ID, so one side is always among the new rows.
        subjects, objects = (terms.where(f"{r}_id IS NOT NULL").select("term", f"{r}_id") for r in "so")
        by_object = new["o"].select("term", F.col("id").alias("o_id")).join(subjects, "term").select("o_id", "s_id")
        by_subject = new["s"].select("term", F.col("id").alias("s_id")).join(objects, "term").select("o_id", "s_id")
        aliases = self.scratch.keep(self.aliases.union(by_object).union(by_subject).dropDuplicates())
        ids = dictionary.encode(facts, terms, predicates)
        return DynamicGraph(terms, predicates, self.index.insert(ids), self.n_so, tops, aliases, self.scratch)

    def delete(self, facts: DataFrame) -> DynamicGraph:
        """Facts of terms; those that name an unknown term match nothing. IDs stay until the graph is compacted."""
        ids = dictionary.encode(facts.select("s", "p", "o").dropna().dropDuplicates(), self.terms, self.predicates)
        return DynamicGraph(self.terms, self.predicates, self.index.delete(ids), self.n_so, self.tops, self.aliases, self.scratch)

    def match(self, s: str | None = None, p: str | None = None, o: str | None = None) -> DataFrame:
        """Facts (s, p, o) of a pattern of terms."""
        return self.decode(self._ids(s, p, o))

    def _ids(self, s=None, p=None, o=None) -> DataFrame:
        asked = [(v, k) for k, v in (("s", s), ("p", p), ("o", o)) if v is not None]
        found = dictionary.lookup(self.terms, self.predicates, asked)
        return self.index.match(**{k: found[v, k] for v, k in asked}) if len(found) == len(asked) else self.index.added.limit(0)

    def decode(self, ids: DataFrame) -> DataFrame:
        out = dictionary.decode(ids, self.terms, self.predicates, {"s_id": "s", "p_id": "p", "o_id": "o"})
        return out.select(F.col("s_id").alias("s"), F.col("p_id").alias("p"), F.col("o_id").alias("o"))

    def as_subject(self, df: DataFrame, column: str) -> DataFrame:
        """df with an object ID replaced by the subject ID of its term; rows whose term is no subject go."""
        pair = dictionary._maybe_broadcast(self.aliases.select(F.col("o_id").alias("__o"), F.col("s_id").alias("__s")))
        joined = df.join(pair, df[column] == F.col("__o"), "left")
        return joined.withColumn(column, F.coalesce("__s", F.when(F.col(column) <= self.n_so, F.col(column)))).where(F.col(column).isNotNull()).drop("__o", "__s")

    def chain(self, first: dict, second: dict) -> DataFrame:
        """(s, x, o): facts of the first pattern whose object x is the subject of a fact of the second."""
        left = self.as_subject(self._ids(**first), "o_id").select(F.col("s_id").alias("s"), F.col("o_id").alias("x"))
        right = self._ids(**second).select(F.col("s_id").alias("x"), F.col("o_id").alias("o"))
        return dictionary.decode(left.join(right, "x").distinct(), self.terms, self.predicates, {"s": "s", "x": "s", "o": "o"}).select("s", "x", "o")

    def compact(self, name: str = "graph") -> Graph:
        """A static graph with dense IDs in the order of terms; terms that no fact uses are gone."""
        from bitgraph.operators.graph import Graph

        return Graph(self.terms.sparkSession, self.match(), name)
