"""Which predicates a subject or an object has: prunes patterns with a free predicate from all trees to those that can answer.

Identical lists are stored once: most subjects of a kind share one.
"""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitgraph.store import Scratch


class PredicateIndex:
    def __init__(self, ids: DataFrame, scratch: Scratch):
        self.ids, self.scratch = ids, scratch

    def _lists(self, axis: str) -> tuple[DataFrame, DataFrame]:
        lists = self.ids.groupBy(axis).agg(F.sort_array(F.collect_set("p_id")).alias("preds"))  # n_p at most
        named = lists.withColumn("list_id", F.xxhash64("preds"))
        return self.scratch.keep(named.select(axis, "list_id").sort(axis)), self.scratch.keep(named.select("list_id", "preds").dropDuplicates(["list_id"]))

    @cached_property
    def subjects(self) -> tuple[DataFrame, DataFrame]:
        return self._lists("s_id")

    @cached_property
    def objects(self) -> tuple[DataFrame, DataFrame]:
        return self._lists("o_id")

    def lists(self, axis: str) -> DataFrame:
        """(axis, preds)."""
        nodes, vocabulary = self.subjects if axis == "s_id" else self.objects
        return nodes.join(vocabulary, "list_id").select(axis, "preds")

    def expand(self, bindings: DataFrame) -> DataFrame:
        """bindings without p_id, with one for every predicate that its bound ends have."""
        out = bindings
        for axis in ("s_id", "o_id"):
            if axis in bindings.columns:
                have = self.lists(axis).select(axis, F.explode("preds").alias("p_id"))
                out = out.join(have, [axis, "p_id"] if "p_id" in out.columns else [axis])
        return out


class Indexed:
    """An engine whose patterns with a free predicate go through the predicate index."""

    def __init__(self, engine, index: PredicateIndex):
        self.engine, self.index, self.name = engine, index, f"{engine.name}+pidx"

    def match_batch(self, bindings: DataFrame) -> DataFrame:
        bound = [c for c in ("s_id", "p_id", "o_id") if c in bindings.columns]
        if "p_id" in bound or not bound:
            return self.engine.match_batch(bindings)
        return self.engine.match_batch(self.index.expand(bindings.select(*bound).dropDuplicates()))

    def match(self, s=None, p=None, o=None) -> DataFrame:
        if p is not None or s is None and o is None:
            return self.engine.match(s, p, o)
        row = self.index.ids.sparkSession.range(1).select(*[F.lit(v).cast("bigint").alias(k) for k, v in (("s_id", s), ("o_id", o)) if v is not None])
        return self.match_batch(row)
