"""A graph with its dictionary, ids and engines, built once for a session, a folder and a name."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitgraph.functions.geometry import dimension
from bitgraph.operators import dictionary, joins
from bitgraph.operators.tiles import TreeIndex
from bitgraph.sources import graphs
from bitgraph.store import Scratch

_open: dict[tuple[str, str, str], Graph] = {}


def open_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _open:
        _open[key] = Graph(spark, graphs.triples(spark, sf_dir, name), name)
    return _open[key]


class Graph:
    def __init__(self, spark: SparkSession, triples: DataFrame, name: str = "graph"):
        self.spark, self.name, self.scratch = spark, name, Scratch(spark)
        self._triples = triples
        self._indexes: dict[tuple, TreeIndex] = {}

    @cached_property
    def triples(self) -> DataFrame:
        return self.scratch.keep(self._triples)

    @cached_property
    def _dictionary(self) -> tuple[DataFrame, dict[str, int]]:
        return dictionary.assign(dictionary.roles(self.triples), self.scratch)

    @property
    def terms(self) -> DataFrame:
        return self._dictionary[0]

    @property
    def counts(self) -> dict[str, int]:
        return self._dictionary[1]

    @property
    def n_so(self) -> int:
        return self.counts["n_so"]

    @cached_property
    def predicates(self) -> DataFrame:
        return dictionary.predicates(self.triples, self.scratch)

    @cached_property
    def _names(self) -> DataFrame:
        return dictionary.predicate_names(self.triples, self.scratch)

    @property
    def names(self) -> DataFrame:
        """(pred, p_id, ...): the predicates, with counts only if they were asked for before."""
        return self.__dict__["predicates"] if "predicates" in self.__dict__ else self._names

    @cached_property
    def n_p(self) -> int:
        return self.names.count()

    @cached_property
    def ids(self) -> DataFrame:
        return self.scratch.keep(dictionary.encode(self.triples, self.terms, self.names).sortWithinPartitions("p_id", "s_id", "o_id"))

    @property
    def dim(self) -> int:
        return dimension(**self.counts)

    def index(self, schedule: str = "hybrid", leaf: str = "auto", **options) -> TreeIndex:
        key = (schedule, leaf, *sorted(options.items()))
        if key not in self._indexes:
            self._indexes[key] = TreeIndex.build(self.ids, self.dim, self.n_so, self.scratch, schedule, leaf, **options)
        return self._indexes[key]

    def engine(self) -> TreeIndex | OnDemand:
        """The index if it was built, else one that builds the trees of a predicate when a pattern needs them."""
        return self._indexes.get(("hybrid", "auto")) or self._on_demand

    @cached_property
    def _on_demand(self) -> OnDemand:
        return OnDemand(self)

    def adopt(self, terms: DataFrame, preds: DataFrame, counts: dict[str, int], index: TreeIndex) -> None:
        """Takes a dictionary and an index that were built elsewhere."""
        self.__dict__ |= {"_dictionary": (terms, counts), "predicates": preds}
        self._indexes["hybrid", "auto"] = index

    # Terms ---------------------------------------------------------------------------------------------------------------

    def lookup(self, *constants: tuple[str, str]) -> dict[tuple[str, str], int]:
        return dictionary.lookup(self.terms, self.names, list(constants))

    def decode(self, df: DataFrame, **columns: str) -> DataFrame:
        return dictionary.decode(df, self.terms, self.names, columns)

    def match(self, s: str | None = None, p: str | None = None, o: str | None = None, engine=None) -> DataFrame:
        """Facts (s, p, o) that a pattern of terms matches; a term that never plays its role matches nothing."""
        asked = [(v, k) for k, v in (("s", s), ("p", p), ("o", o)) if v is not None]
        found = self.lookup(*asked)
        engine = engine or self.index()
        if len(found) < len(asked):
            ids = engine.match().limit(0)
        else:
            ids = engine.match(**{k: found[v, k] for v, k in asked})
        return self.decode(ids, s_id="s", p_id="p", o_id="o").select(F.col("s_id").alias("s"), F.col("p_id").alias("p"), F.col("o_id").alias("o"))

    def encode_constants(self, constants: DataFrame, roles: dict[str, str]) -> DataFrame:
        """constants with terms replaced by IDs; rows with a term that never plays its role are dropped."""
        for name, role in roles.items():
            if role == "p":
                ids = self.names.select(F.col("pred").alias("__t"), F.col("p_id").alias("__i"))
            else:
                ids = self.terms.where(f"{role}_id IS NOT NULL").select(F.col("term").alias("__t"), F.col(f"{role}_id").alias("__i"))
            constants = constants.join(ids, F.col(name) == F.col("__t")).drop("__t", name).withColumnRenamed("__i", name)
        return constants

    def join(self, left: joins.Pattern, right: joins.Pattern, constants: DataFrame | None = None, engine=None, strategy: str = "auto") -> DataFrame:
        """Join of patterns of terms. In ``constants`` every column named in a pattern holds terms; others are kept."""
        spec = [(k, getattr(t, k)) for t in (left, right) for k in joins.POSITIONS]
        plain = sorted({(v, k) for k, v in spec if isinstance(v, str) and not v.startswith(("@", "?"))})
        ids = self.lookup(*plain)
        columns = {v[1:]: k for k, v in spec if isinstance(v, str) and v.startswith("@")}
        put = lambda t: joins.Pattern(*[v if (v := getattr(t, k)).startswith("@") else v[1:] if v.startswith("?") else ids.get((v, k), -1) for k in joins.POSITIONS])
        a, b = put(left), put(right)
        given = constants if constants is not None else self.spark.range(1).select(F.lit(0).alias("i"))
        kept = [c for c in given.columns if c not in columns]
        bound = self.encode_constants(given, columns)
        bound = self.scratch.keep(bound) if columns else bound  # both patterns and the join read it, and each time it takes passes over all terms
        out = joins.join(engine or self.index(), a, b, bound, self.n_so, strategy, self.n_p)
        roles = {}
        for t in (a, b):
            for k in joins.POSITIONS:
                if t.is_var(k):
                    roles.setdefault(getattr(t, k), k)
        out = self.decode(out.select(*kept, *roles), **roles)
        return out.select(*kept, *roles) if constants is not None else out.select(*roles)


class OnDemand:
    """Trees of the predicates that patterns need, built at first need; for few patterns on a graph of many predicates.

    A free predicate stands for those that the bound subjects or objects have. Patterns that need more than ``most``
    predicates, or more than ``most_nodes`` nodes for that, and those that bind nothing, use the whole index.
    """

    name = "tree"

    def __init__(self, graph: Graph, most: int = 1000, most_nodes: int = 10_000):
        self.graph, self.most, self.most_nodes = graph, most, most_nodes
        self.built: set[int] = set()
        self.trees: TreeIndex | None = None

    def match_batch(self, bindings: DataFrame) -> DataFrame:
        bound = [c for c in ("s_id", "p_id", "o_id") if c in bindings.columns]
        needed = self._needed(bindings.select(*bound).dropDuplicates(), bound) if bound else None
        return (self.graph.index() if needed is None else self._of(needed)).match_batch(bindings)

    def _needed(self, bindings: DataFrame, bound: list[str]) -> set[int] | None:
        g = self.graph
        if "p_id" in bound:
            found = bindings.select("p_id").where("p_id IS NOT NULL").distinct()
        else:
            axis = bound[0]
            nodes = bindings.select(axis).distinct().limit(self.most_nodes + 1).toArrow()
            if nodes.num_rows > self.most_nodes:
                return None
            asked = F.broadcast(g.spark.createDataFrame([(v,) for v in nodes.column(0).to_pylist()], f"{axis} bigint"))
            terms = g.terms.join(asked, axis, "left_semi").select(F.col("term").alias(axis[0]))
            found = g.triples.join(F.broadcast(terms), axis[0], "left_semi").select("p").distinct().join(g.names, F.col("p") == F.col("pred")).select("p_id")
        out = {r[0] for r in found.limit(self.most + 1).collect()}
        return out if len(out) <= self.most else None

    def _of(self, needed: set[int]) -> TreeIndex:
        g, new = self.graph, sorted(needed - self.built)
        if new or self.trees is None:
            named = F.broadcast(g.names.where(F.col("p_id").isin(new)).select(F.col("pred").alias("p")))
            ids = g.scratch.keep(dictionary.encode(g.triples.join(named, "p", "left_semi"), g.terms, g.names))
            made = TreeIndex.build(ids, g.dim, g.n_so, g.scratch)
            self.trees = made if self.trees is None else TreeIndex(self.trees.tiles.union(made.tiles), made.bits, g.dim, g.n_so)
            self.built |= {*new}
        return self.trees
