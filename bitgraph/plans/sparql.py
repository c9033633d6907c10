"""A subset of SPARQL over a graph: SELECT, ASK and COUNT with groups of patterns, FILTER, OPTIONAL, UNION and MINUS.

Text becomes a small algebra, runs of patterns go to the planner, and the rest is DataFrame operations on terms. Resources
are written <kind/key>, predicates too, literals in double quotes.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitgraph.operators.graph import Graph
from bitgraph.operators.joins import Pattern
from bitgraph.plans import planner

TOKEN = re.compile(r'\s*(?:(?P<term><[^>]*>|"[^"]*")|(?P<var>\?\w+)|(?P<num>-?\d+(?:\.\d+)?)|(?P<word>[A-Za-z]+)|(?P<op><=|>=|!=|&&|\|\||[{}().;*=<>!]))')


@dataclass
class Group:
    patterns: list[Pattern] = field(default_factory=list)
    filters: list[Column] = field(default_factory=list)
    parts: list[tuple[str, list[Group]]] = field(default_factory=list)


@dataclass
class Query:
    ask: bool
    distinct: bool
    variables: list[str]
    count: tuple[str | None, str] | None
    where: Group
    group_by: list[str]
    order_by: list[Column]
    limit: int | None
    offset: int


class Parser:
    def __init__(self, text: str):
        self.tokens, at = [], 0
        text = text.strip()
        while at < len(text):
            m = TOKEN.match(text, at)
            if not m:
                raise ValueError(f"can't read {text[at : at + 20]!r}")
            self.tokens.append((m.lastgroup, m[m.lastgroup]))
            at = m.end()
        self.at = 0

    def peek(self, *words: str) -> bool:
        return self.at < len(self.tokens) and self.tokens[self.at][1].upper() in words

    def take(self, *words: str) -> str:
        if self.at >= len(self.tokens) or words and not self.peek(*words):
            raise ValueError(f"expected {' or '.join(words) or 'more'} at token {self.at}")
        self.at += 1
        return self.tokens[self.at - 1][1]

    def skip(self, *words: str) -> bool:
        if self.peek(*words):
            self.at += 1
            return True
        return False

    def kind(self) -> str | None:
        return self.tokens[self.at][0] if self.at < len(self.tokens) else None

    def query(self) -> Query:
        ask = self.take("SELECT", "ASK").upper() == "ASK"
        distinct, variables, count = self.skip("DISTINCT"), [], None
        while not ask and not self.peek("WHERE", "{"):
            if self.skip("*"):
                break
            if self.skip("("):
                self.take("COUNT"), self.take("(")
                of = None if self.skip("*") else self.take()[1:]
                self.take(")"), self.take("AS")
                count = (of, self.take()[1:])
                self.take(")")
            else:
                variables.append(self.take()[1:])
        self.skip("WHERE")
        where = self.group()
        group_by, order_by, limit, offset = [], [], None, 0
        if self.skip("GROUP"):
            self.take("BY")
            while self.kind() == "var":
                group_by.append(self.take()[1:])
        if self.skip("ORDER"):
            self.take("BY")
            while self.kind() == "var" or self.peek("ASC", "DESC"):
                down = self.peek("DESC")
                if self.skip("ASC", "DESC"):
                    self.take("(")
                    c = F.col(self.take()[1:])
                    self.take(")")
                else:
                    c = F.col(self.take()[1:])
                order_by.append(c.desc() if down else c.asc())
        while self.peek("LIMIT", "OFFSET"):
            word, n = self.take().upper(), int(self.take())
            limit, offset = (n, offset) if word == "LIMIT" else (limit, n)
        if self.at < len(self.tokens):
            raise ValueError(f"unexpected {self.tokens[self.at][1]!r}")
        return Query(ask, distinct, variables, count, where, group_by, order_by, limit, offset)

    def node(self) -> str:
        kind, text = self.kind(), self.take()
        return text if kind == "var" else text[1:-1] if text.startswith("<") else text

    def group(self) -> Group:
        out = Group()
        self.take("{")
        while not self.skip("}"):
            if self.skip("FILTER"):
                self.take("(")
                out.filters.append(self.either())
                self.take(")")
            elif self.peek("OPTIONAL", "MINUS"):
                out.parts.append((self.take().upper(), [self.group()]))
            elif self.peek("{"):
                options = [self.group()]
                while self.skip("UNION"):
                    options.append(self.group())
                out.parts.append(("UNION", options))
            else:
                s, p, o = self.node(), self.node(), self.node()
                out.patterns.append(Pattern(s, p, o))
                while self.skip(";"):
                    out.patterns.append(Pattern(s, self.node(), self.node()))
            self.skip(".")
        return out

    def either(self) -> Column:
        left = self.both()
        while self.skip("||"):
            left = left | self.both()
        return left

    def both(self) -> Column:
        left = self.comparison()
        while self.skip("&&"):
            left = left & self.comparison()
        return left

    def comparison(self) -> Column:
        if self.skip("!"):
            return ~self.comparison()
        if self.skip("("):
            inner = self.either()
            self.take(")")
            return inner
        (a, a_num), op, (b, b_num) = self.value(), self.take("=", "!=", "<", "<=", ">", ">="), self.value()
        if a_num or b_num:  # a literal's text as a number, null where it is none
            number = lambda c, is_num: c if is_num else F.regexp_replace(c, '^"|"$', "").try_cast("double")
            a, b = number(a, a_num), number(b, b_num)
        return {"=": a == b, "!=": a != b, "<": a < b, "<=": a <= b, ">": a > b, ">=": a >= b}[op]

    def value(self) -> tuple[Column, bool]:
        kind = self.kind()
        if kind == "num":
            return F.lit(float(self.take())), True
        text = self.node()
        return (F.col(text[1:]) if kind == "var" else F.lit(text)), False


def _solve(graph: Graph, group: Group, engine) -> DataFrame:
    out = planner.solve(graph, group.patterns, engine) if group.patterns else None
    for kind, options in group.parts:
        if kind == "UNION":
            made = [_solve(graph, g, engine) for g in options]
            part = made[0]
            for m in made[1:]:
                part = part.unionByName(m, allowMissingColumns=True)
            out = part if out is None else _meet(out, part, "inner")
        else:
            out = _meet(out, _solve(graph, options[0], engine), "left" if kind == "OPTIONAL" else "left_anti")
    for f in group.filters:
        out = out.where(f)
    return out


def _meet(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
    on = [c for c in left.columns if c in right.columns]
    if not on:
        return left if how == "left_anti" else left.crossJoin(right) if how == "inner" else left.join(right, F.lit(True), how)
    return left.join(right, on, how)


def run(graph: Graph, text: str, engine=None) -> DataFrame:
    """The answer as columns of terms; ASK gives one row ``ask``."""
    q = Parser(text).query()
    out = _solve(graph, q.where, engine)
    if q.ask:
        return out.limit(1).agg((F.count("*") > 0).alias("ask"))
    if q.count:
        of, name = q.count
        n = (F.count("*") if of is None else F.countDistinct(of) if q.distinct else F.count(of)).alias(name)
        out = out.groupBy(*q.group_by).agg(n)
    else:
        out = out.select(*(q.variables or out.columns))
        out = out.distinct() if q.distinct else out
    if q.order_by:
        out = out.orderBy(*q.order_by)
    out = out.offset(q.offset) if q.offset else out
    return out.limit(q.limit) if q.limit is not None else out
