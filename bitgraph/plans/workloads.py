"""Workloads: drawn constants, the seven timed pattern shapes, and a join template for each of the 26 sub-shapes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitgraph.operators.graph import Graph
from bitgraph.operators.joins import Pattern

#: Positions that each shape binds; the dump is left out of timing.
SHAPES = {"spo": "spo", "s_o": "so", "sp": "sp", "s": "s", "po": "po", "o": "o", "p": "p"}

#: Join templates on the star graph, by sub-shape. @ marks columns of constants, ? variables.
TEMPLATES: dict[str, tuple[tuple[str, str, str], tuple[str, str, str]]] = {
    "a_ss": (("?x", "containsPart", "@p1"), ("?x", "shippedBy", "@s1")),
    "b_ss": (("?x", "?p", "@p1"), ("?x", "shippedBy", "@s1")),
    "c_ss": (("?x", "?p", "@p1"), ("?x", "?q", "@s1")),
    "d_ss": (("?x", "shippedBy", "@s1"), ("?x", "containsPart", "?y")),
    "e1_ss": (("?x", "?p", "@s1"), ("?x", "containsPart", "?y")),
    "e2_ss": (("?x", "shippedBy", "@s1"), ("?x", "?q", "?y")),
    "f_ss": (("?x", "?p", "@s1"), ("?x", "?q", "?y")),
    "a_oo": (("@o1", "containsPart", "?x"), ("@o2", "containsPart", "?x")),
    "b_oo": (("@o1", "?p", "?x"), ("@p1", "soldBy", "?x")),
    "c_oo": (("@o1", "?p", "?x"), ("@o2", "?q", "?x")),
    "d_oo": (("@p1", "soldBy", "?x"), ("?y", "shippedBy", "?x")),
    "e1_oo": (("@p1", "?p", "?x"), ("?y", "shippedBy", "?x")),
    "e2_oo": (("@p1", "soldBy", "?x"), ("?y", "?q", "?x")),
    "f_oo": (("@p1", "?p", "?x"), ("?y", "?q", "?x")),
    "a_so": (("?x", "inNation", "@n1"), ("@o1", "placedBy", "?x")),
    "b1_so": (("?x", "?p", "@n1"), ("@o1", "placedBy", "?x")),
    "b2_so": (("?x", "inNation", "@n1"), ("@o1", "?q", "?x")),
    "c_so": (("?x", "?p", "@n1"), ("@o1", "?q", "?x")),
    "d1_so": (("?x", "inNation", "@n1"), ("?y", "placedBy", "?x")),
    "d2_so": (("?x", "inNation", "?y"), ("@o1", "placedBy", "?x")),
    "e1_so": (("?x", "?p", "@n1"), ("?y", "placedBy", "?x")),
    "e2_so": (("?x", "inNation", "@n1"), ("?y", "?q", "?x")),
    "e3_so": (("?x", "inNation", "?y"), ("@o1", "?q", "?x")),
    "e4_so": (("?x", "?p", "?y"), ("@o1", "placedBy", "?x")),
    "f1_so": (("?x", "?p", "@n1"), ("?y", "?q", "?x")),
    "f2_so": (("?x", "?p", "?y"), ("@o1", "?q", "?x")),
}

#: The same sub-shapes on the daily graph, where every predicate is a day's; constants of ``dated_anchors``.
DATED: dict[str, tuple[tuple[str, str, str], tuple[str, str, str]]] = {
    "a_ss": (("?x", "@d1", "@p1"), ("?x", "@d3", "@p3")),
    "b_ss": (("?x", "?p", "@p1"), ("?x", "@d3", "@p3")),
    "c_ss": (("?x", "?p", "@p1"), ("?x", "?q", "@p3")),
    "d_ss": (("?x", "@d1", "@p1"), ("?x", "@d3", "?y")),
    "e1_ss": (("?x", "?p", "@p1"), ("?x", "@d3", "?y")),
    "e2_ss": (("?x", "@d1", "@p1"), ("?x", "?q", "?y")),
    "f_ss": (("?x", "?p", "@p1"), ("?x", "?q", "?y")),
    "a_oo": (("@o1", "@d1", "?x"), ("@o2", "@d4", "?x")),
    "b_oo": (("@o1", "?p", "?x"), ("@o2", "@d4", "?x")),
    "c_oo": (("@o1", "?p", "?x"), ("@o2", "?q", "?x")),
    "d_oo": (("@o1", "@d1", "?x"), ("?y", "@d4", "?x")),
    "e1_oo": (("@o1", "?p", "?x"), ("?y", "@d4", "?x")),
    "e2_oo": (("@o1", "@d1", "?x"), ("?y", "?q", "?x")),
    "f_oo": (("@o1", "?p", "?x"), ("?y", "?q", "?x")),
    "a_so": (("?x", "@d2", "@s1"), ("@o1", "@d1", "?x")),
    "b1_so": (("?x", "?p", "@s1"), ("@o1", "@d1", "?x")),
    "b2_so": (("?x", "@d2", "@s1"), ("@o1", "?q", "?x")),
    "c_so": (("?x", "?p", "@s1"), ("@o1", "?q", "?x")),
    "d1_so": (("?x", "@d2", "@s1"), ("?y", "@d1", "?x")),
    "d2_so": (("?x", "@d2", "?y"), ("@o1", "@d1", "?x")),
    "e1_so": (("?x", "?p", "@s1"), ("?y", "@d1", "?x")),
    "e2_so": (("?x", "@d2", "@s1"), ("?y", "?q", "?x")),
    "e3_so": (("?x", "@d2", "?y"), ("@o1", "?q", "?x")),
    "e4_so": (("?x", "?p", "?y"), ("@o1", "@d1", "?x")),
    "f1_so": (("?x", "?p", "@s1"), ("?y", "?q", "?x")),
    "f2_so": (("?x", "?p", "?y"), ("@o1", "?q", "?x")),
}

#: Outside the categories: both other nodes free.
GENERAL = {
    "g_ss": (("?x", "inNation", "?y"), ("?x", "segment", "?z")),
    "g_oo": (("?y", "inNation", "?x"), ("?z", "inRegion", "?w")),
    "g_so": (("?x", "inRegion", "?y"), ("?z", "inNation", "?x")),
}


def drawn(graph: Graph, n: int) -> DataFrame:
    """The n facts with the smallest hash; a term comes up as often as it is used, as in a log."""
    return graph.triples.orderBy(F.md5(F.concat_ws("|", "s", "p", "o"))).limit(n)


def anchors(graph: Graph, n: int = 10) -> DataFrame:
    """(i, o1, p1, s1, c1, n1, o2) of the star graph, such that every template has an answer."""
    g = graph.triples
    of = lambda p, s, o: g.where(F.col("p") == p).select(F.col("s").alias(s), F.col("o").alias(o))
    first = [(r["s"], r["o"]) for r in g.where("p = 'containsPart'").orderBy(F.md5(F.concat_ws("|", "s", "p", "o"))).limit(n).collect()]
    k = graph.spark.createDataFrame([(i + 1, *x) for i, x in enumerate(first)] or [(0, "", "")], "i bigint, o1 string, p1 string").where("i > 0").coalesce(1)
    sold = k.join(of("shippedBy", "o1", "s1"), "o1").join(of("soldBy", "p1", "s1"), ["p1", "s1"]).groupBy("i").agg(F.min("s1").alias("s1"))
    buyer = k.join(of("placedBy", "o1", "c1"), "o1").join(of("inNation", "c1", "n1"), "c1").groupBy("i").agg(F.min("c1").alias("c1"), F.min("n1").alias("n1"))
    other = k.join(of("containsPart", "o2", "p1"), "p1").where("o2 <> o1").groupBy("i").agg(F.min("o2").alias("o2"))
    return k.join(sold, "i", "left").join(buyer, "i", "left").join(other, "i", "left")


def dated_anchors(graph: Graph, n: int = 10) -> DataFrame:
    """(i, o1, d1, p1, d2, s1, d3, p3, d4, o2) of the daily graph: an order's part on a day, a day when it was sold, another
    part of the order, and another order with the part; null where there is none, which matches nothing."""
    g = graph.triples
    first = [(r["s"], r["p"], r["o"]) for r in g.where("p LIKE 'shippedOn/%'").orderBy(F.md5(F.concat_ws("|", "s", "p", "o"))).limit(n).collect()]
    k = graph.spark.createDataFrame([(i + 1, *x) for i, x in enumerate(first)] or [(0, "", "", "")], "i bigint, o1 string, d1 string, p1 string").where("i > 0").coalesce(1)
    orders, parts = [x[0] for x in first], [x[2] for x in first]
    g = graph.scratch.keep(g.where(F.col("s").isin(orders + parts) | F.col("o").isin(parts)))  # what lies beside them, in one pass
    least = lambda rows, p, x: rows.groupBy("i").agg(F.min(F.struct("p", "v")).alias("m")).select("i", F.col("m.p").alias(p), F.col("m.v").alias(x))
    sold = least(k.join(g.where("p LIKE 'soldOn/%'"), F.col("s") == F.col("p1")).select("i", "p", F.col("o").alias("v")), "d2", "s1")
    beside = least(k.join(g, F.col("s") == F.col("o1")).where("o <> p1").select("i", "p", F.col("o").alias("v")), "d3", "p3")
    other = least(k.join(g, F.col("o") == F.col("p1")).where("s <> o1").select("i", "p", F.col("s").alias("v")), "d4", "o2")
    return k.join(sold, "i", "left").join(beside, "i", "left").join(other, "i", "left")


def patterns(template: tuple) -> tuple[Pattern, Pattern]:
    return Pattern(*template[0]), Pattern(*template[1])


def run_join(graph: Graph, template: tuple, engine=None, strategy: str = "auto", constants: DataFrame | None = None) -> DataFrame:
    """(i, variables) of a template for all constants at once."""
    given = anchors(graph) if constants is None else constants
    used = sorted({v[1:] for t in template for v in t if v.startswith("@")})
    return graph.join(*patterns(template), constants=given.select("i", *used), engine=engine, strategy=strategy)


def join_sql(template: tuple, first_only: bool = False) -> str:
    """The template as a self-join over CTEs g and k; terms are compared, so roles need no care."""
    seen: dict[str, str] = {}
    where, used = [], False
    for alias, t in zip("ab", template, strict=True):
        for position, v in zip("spo", t, strict=True):
            here = f"{alias}.{position}"
            if v.startswith("@"):
                where.append(f"{here} = k.{v[1:]}")
                used = True
            elif v.startswith("?"):
                if v[1:] in seen:
                    where.append(f"{here} = {seen[v[1:]]}")
                else:
                    seen[v[1:]] = here
            else:
                where.append(f"{here} = '{v}'")
    assert used or not first_only
    return f"SELECT k.i AS i, {', '.join(f'{c} AS {v}' for v, c in seen.items())} FROM k, g a, g b WHERE {' AND '.join(where)}" + (" AND k.i = 1" if first_only else "")


def run_shape(graph: Graph, shape: str, n: int, engine=None) -> DataFrame:
    """(s, p, o): facts that agree with one of n drawn facts on the shape's positions."""
    facts = drawn(graph, n)
    positions = SHAPES[shape]
    ids = graph.encode_constants(facts.select(*positions), {c: c for c in positions})
    found = (engine or graph.index()).match_batch(ids.select(*[F.col(c).alias(f"{c}_id") for c in positions]))
    return graph.decode(found, s_id="s", p_id="p", o_id="o").select(F.col("s_id").alias("s"), F.col("p_id").alias("p"), F.col("o_id").alias("o"))


def shape_sql(shape: str, n: int) -> str:
    on = " AND ".join(f"k.{c} = g.{c}" for c in SHAPES[shape])
    return f", k AS (SELECT s, p, o FROM g ORDER BY md5(concat_ws('|', s, p, o)) LIMIT {n}) SELECT g.s, g.p, g.o FROM g WHERE EXISTS (SELECT 1 FROM k WHERE {on})"
