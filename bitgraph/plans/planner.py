"""Conjunctions of patterns: a greedy left-deep order by bound positions and estimated rows, solved step by step.

The next pattern is the one that joins what is known and is estimated to return fewest rows. With few rows known its
values are put in it (chain); with many, the pattern is solved by itself and joined (merge).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitgraph.operators import joins
from bitgraph.operators.graph import Graph
from bitgraph.operators.joins import POSITIONS, Pattern

#: Known rows up to which their values are put in the next pattern.
MOST_CHAINED = 50_000


def estimate(pattern: Pattern, known: set[str], stats: dict[int, tuple[int, int, int]], total: tuple[int, int, int]) -> float:
    """Rows of a pattern for one row of what is known, from facts, subjects and objects of its predicate."""
    bound = {k: not pattern.is_var(k) or getattr(pattern, k) in known for k in POSITIONS}
    n, subjects, objects = stats.get(pattern.p, total) if isinstance(pattern.p, int) else total
    rows = float(n)
    if bound["s"]:
        rows /= max(subjects, 1)
    if bound["o"]:
        rows /= max(objects, 1)
    return rows / (max(len(stats), 1) if bound["p"] and not isinstance(pattern.p, int) else 1)


def order(patterns: list[Pattern], stats: dict[int, tuple[int, int, int]]) -> list[Pattern]:
    total = tuple(sum(x[i] for x in stats.values()) for i in range(3)) if stats else (0, 0, 0)
    left, known, out = list(patterns), set(), []
    while left:
        linked = [t for t in left if known & set(t.variables())] or left
        best = min(linked, key=lambda t: (estimate(t, known, stats, total), left.index(t)))
        left.remove(best)
        out.append(best)
        known |= set(best.variables())
    return out


def solve(graph: Graph, patterns: list[Pattern], engine=None, decode: bool = True) -> DataFrame:
    """The variables of a conjunction of patterns of terms, a column each. ? marks variables."""
    engine = engine or graph.index()
    asked = sorted({(getattr(t, k), k) for t in patterns for k in POSITIONS if not getattr(t, k).startswith("?")})
    ids = graph.lookup(*asked)
    put = lambda t: Pattern(*[v[1:] if (v := getattr(t, k)).startswith("?") else ids.get((v, k), -1) for k in POSITIONS])
    stats = {r["p_id"]: (r["n_triples"], r["n_subj"], r["n_obj"]) for r in graph.predicates.collect()} if graph.n_p <= 100_000 else {}
    roles: dict[str, set[str]] = {}
    for t in map(put, patterns):
        for k in POSITIONS:
            if t.is_var(k):
                roles.setdefault(getattr(t, k), set()).add(k)
    out, known = graph.spark.range(1).select(F.lit(0).alias("__one")), set()
    for t in order([put(t) for t in patterns], stats):
        using = [v for v in t.variables() if v in known]
        if using and out.limit(MOST_CHAINED + 1).count() <= MOST_CHAINED:
            out = joins.solve(engine, t, out, using=tuple(using))
        else:
            alone = joins.solve(engine, t, graph.spark.range(1).select(F.lit(0).alias("__one")))
            out = out.join(alone, ["__one", *using])
        for v in t.variables():
            if roles[v] >= {"s", "o"}:
                out = out.where(F.col(v) <= graph.n_so)
        known |= set(t.variables())
        out = graph.scratch.keep(out)
    out = out.select(*roles)
    if any(r >= {"p"} and len(r) > 1 for r in roles.values()):
        raise ValueError("a variable is a predicate in one place and a node in another")
    return graph.decode(out, **{v: min(r) for v, r in roles.items()}).select(*roles) if decode else out
