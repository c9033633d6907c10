"""Patterns and two-pattern joins: classification into the categories A to F, and their strategies.

A pattern's positions are IDs, columns of a table of constants (``@name``), or variables (other strings). A join runs for
all rows of constants at once. Any engine with ``match_batch`` can serve it.

A to C solve both patterns and meet on the join variable. D to F solve the pattern without the other free node first and
put each of its values in the other one (``chain``), or solve both (``merge``). In a subject-object join only the joined
coordinate is bounded by the shared IDs: the other node may be of one role only.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a solved side that are fetched once and sent to every task, so that the other side is not dealt out for the join.
MOST_SENT = 500_000
POSITIONS = ("s", "p", "o")


@dataclass(frozen=True)
class Pattern:
    s: int | str
    p: int | str
    o: int | str

    def is_var(self, position: str) -> bool:
        v = getattr(self, position)
        return isinstance(v, str) and not v.startswith("@")

    def variables(self) -> list[str]:
        return [getattr(self, k) for k in POSITIONS if self.is_var(k)]


@dataclass(frozen=True)
class Shape:
    kind: str  # SS, OO, SO, or other
    category: str  # A to F, G for what lies outside them
    variable: str | None
    chained: int | None = None  # of D to F: the pattern solved first


def classify(left: Pattern, right: Pattern) -> Shape:
    shared = [v for v in left.variables() if v in right.variables()]
    if len(set(shared)) != 1 or len(set(left.variables())) != len(left.variables()) or len(set(right.variables())) != len(right.variables()):
        return Shape("other", "G", shared[0] if shared else None)
    x = shared[0]
    at = ["".join(k for k in POSITIONS if getattr(t, k) == x) for t in (left, right)]
    if "p" in at:
        return Shape("other", "G", x)
    kind = {"ss": "SS", "oo": "OO"}.get("".join(at), "SO")
    free = [t.is_var("o" if k == "s" else "s") for t, k in zip((left, right), at, strict=True)]
    unbound = left.is_var("p") + right.is_var("p")
    if sum(free) == 2:
        return Shape(kind, "G", x)
    if sum(free) == 0:
        return Shape(kind, "ABC"[unbound], x)
    return Shape(kind, "DEF"[unbound], x, chained=free.index(False))


def _constants(pattern: Pattern, constants: DataFrame, extra: dict[str, str] | None = None) -> tuple[DataFrame, dict[str, str]]:
    """Bindings of a pattern's bound positions, from constants and from columns that hold values of variables."""
    bound = {}
    for k in POSITIONS:
        v = getattr(pattern, k)
        if isinstance(v, int):
            bound[k] = F.lit(v).cast("bigint")
        elif v.startswith("@"):
            bound[k] = F.col(v[1:])
        elif extra and v in extra:
            bound[k] = F.col(extra[v])
    return constants.select(*[c.alias(f"{k}_id") for k, c in bound.items()]) if bound else constants.select(F.lit(1).alias("__one")), bound


def solve(engine, pattern: Pattern, constants: DataFrame, using: tuple[str, ...] = (), apart: bool = False) -> DataFrame:
    """constants with the pattern's variables. ``using``: variables that are columns of constants already.

    ``apart``: the variables alone, each answer once and not once a row of constants.
    """
    bindings, bound = _constants(pattern, constants, {v: v for v in using})
    facts = engine.match_batch(bindings).select(*[F.col(f"{k}_id").alias(f"__{k}") for k in POSITIONS])
    names: dict[str, str] = {}
    for k in POSITIONS:
        if k not in bound and pattern.is_var(k):
            v = getattr(pattern, k)
            if v in names:
                facts = facts.where(F.col(f"__{names[v]}") == F.col(f"__{k}"))
            else:
                names[v] = k
    keys = [c == F.col(f"__{k}") for k, c in bound.items()]
    if apart:
        return facts.select(*[F.col(f"__{k}").alias(v) for v, k in names.items()])
    out = constants.join(facts, reduce(lambda a, b: a & b, keys)) if keys else constants.crossJoin(facts) if len(constants.columns) else facts
    return out.select(*constants.columns, *[F.col(f"__{k}").alias(v) for v, k in names.items()])


def _constant(pattern: Pattern) -> bool:
    """Whether a row of constants bears on the pattern's answers."""
    return any(isinstance(v := getattr(pattern, k), str) and v.startswith("@") for k in POSITIONS)


def _sent(df: DataFrame) -> DataFrame:
    """df, evaluated once and marked for a broadcast if it has ``MOST_SENT`` rows at most."""
    few = df.limit(MOST_SENT + 1).toArrow()
    return F.broadcast(df.sparkSession.createDataFrame(few, df.schema)) if few.num_rows <= MOST_SENT else df


def _roles(pattern: Pattern, v: str) -> set[str]:
    return {k for k in POSITIONS if getattr(pattern, k) == v}


def clip(df: DataFrame, x: str, left: Pattern, right: Pattern, n_so: int) -> DataFrame:
    """Where x is a subject on one side and an object on the other, only shared IDs mean the same term."""
    return df.where(F.col(x) <= n_so) if _roles(left, x) | _roles(right, x) >= {"s", "o"} else df


def join(engine, left: Pattern, right: Pattern, constants: DataFrame, n_so: int, strategy: str = "auto", n_p: int = 0) -> DataFrame:
    """Distinct rows of constants with the variables of both patterns.

    ``strategy``: auto, chain, merge, or per_predicate, which goes through the free predicates one by one.
    """
    shape = classify(left, right)
    x = shape.variable
    if strategy == "per_predicate":
        return _per_predicate(engine, left, right, constants, n_so, n_p)
    if x is None:
        return solve(engine, right, solve(engine, left, constants))
    if shape.category in "ABCG" or strategy == "merge":
        # A side without constants has the same answers for all their rows, which the other side has: it is solved once, apart.
        apart = [not _constant(t) for t in (left, right)]
        apart[0] &= not apart[1]
        a, b = (clip(solve(engine, t, constants, apart=p), x, left, right, n_so) for t, p in zip((left, right), apart, strict=True))
        shared = dict.fromkeys(v for v in left.variables() if v in right.variables())
        on = [*([] if any(apart) else constants.columns), *shared]
        if any(apart):
            a, b = (t if p or not _constant(of) else _sent(t) for t, p, of in zip((a, b), apart, (left, right), strict=True))
        return a.join(b, on).select(*constants.columns, *dict.fromkeys([*shared, *left.variables(), *right.variables()]))
    first, second = (left, right) if shape.chained == 0 else (right, left)
    return solve(engine, second, clip(solve(engine, first, constants), x, left, right, n_so), using=(x,))


def _per_predicate(engine, left: Pattern, right: Pattern, constants: DataFrame, n_so: int, n_p: int) -> DataFrame:
    """The literal reading: a join for each value of each free predicate. For small sets of predicates, and for tests."""
    for side, t in (("left", left), ("right", right)):
        if t.is_var("p"):
            parts = []
            for p in range(1, n_p + 1):
                fixed = Pattern(t.s, p, t.o)
                l, r = (fixed, right) if side == "left" else (left, fixed)
                parts.append(_per_predicate(engine, l, r, constants, n_so, n_p).withColumn(t.p, F.lit(p).cast("bigint")))
            return reduce(lambda a, b: a.unionByName(b), parts)
    return join(engine, left, right, constants, n_so)
