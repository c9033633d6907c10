"""Quality rules as a short-circuit cascade, in DataFrame expressions only.

A rule is a condition on counts of a text. ``Cascade.fit`` measures the cost of each rule and counts its rejections on a
random sample, and ``Cascade.apply`` goes through the rules, the best rejection per cost first. A count is computed just
before the first rule that needs it, and only for rows that no rule before has rejected; of the others it is null, unless
the caller asks for it always. The order changes cost and the reported reason, never the verdict.

Defined results: null or empty text has no words and fails ``few_words``; repeated rows are judged each by itself;
an empty table gives an empty result; columns of other names pass through, and those named like a count or a part of one
are replaced.
"""

from __future__ import annotations

import re
import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import covered, gram_hashes, let, plain_words, whole

WINDOW = 5
#: As a class of a regular expression.
SYMBOLS = r"#*$%&|<>"
#: Rows, on average, that costs and selectivities are estimated on, how often each is gone through in a run, and runs a rule.
SAMPLE_ROWS, TIMES, REPEATS = 512, 16, 3
SEED = 10


@dataclass(frozen=True)
class Rule:
    """A row fails when ``fails`` (SQL over the names of FEATURES) is true."""

    name: str
    fails: str

    @property
    def needs(self) -> list[str]:
        return [f for f in FEATURES if re.search(rf"\b{f}\b", self.fails)]


#: Junk of the usual kinds: too short, repeated, symbols after words, tables, shouting, odd word lengths.
RULES = (
    Rule("few_words", "n_words < 10"),
    Rule("repeated_windows", "100 * n_repeat_words > 20 * n_words"),
    Rule("symbols", "10 * n_symbols > 4 * n_words"),
    Rule("repeated_lines", "10 * n_dup_lines > 4 * n_lines"),
    Rule("word_length", "word_chars < 2 * n_words OR word_chars > 16 * n_words"),
    Rule("shouting", "2 * n_upper > word_chars"),
    Rule("exclaiming", "10 * n_exclaim > 4 * n_words"),
)


def repeat_words(grams: str) -> Column:
    """Words inside windows that the text has twice or more, from the hashes of its windows in order.

    Most texts repeat none, which their number of distinct hashes tells; the others sort hashes with positions.
    """
    h = F.col(grams)

    def exact(rows: Column) -> Column:
        same = lambda k, d: F.coalesce(F.get(rows, k)["h"] == F.get(rows, k + d)["h"], F.lit(False))
        twice = F.filter(F.sequence(F.lit(0), F.size(rows) - 1), lambda k: same(k, -1) | same(k, 1))
        return covered(F.sort_array(F.transform(twice, lambda k: F.get(rows, k)["i"])), WINDOW)

    rows = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(let(rows, exact)).cast("long")


def _count(text: Column, chars: str) -> Column:
    """Number of the text's characters in the regular expression class ``chars``."""
    return F.length(F.regexp_replace(text, f"[^{chars}]+", "")).cast("long")


def _lines(text: Column) -> Column:
    """Lines with a word."""
    return F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))


#: What counts are made of, in an order in which each needs those before it only.
PARTS = {
    "__w": ((), lambda: plain_words(F.col("__t"))),
    "__lines": ((), lambda: _lines(F.col("__t"))),
    "__g": (("__w",), lambda: gram_hashes(F.col("__w"), WINDOW)),
}
#: The counts of a text: the parts that each needs, and its expression.
FEATURES = {
    "n_words": (("__w",), lambda: F.size("__w").cast("long")),
    "word_chars": (("__w",), lambda: F.length(F.array_join("__w", "")).cast("long")),
    "n_symbols": ((), lambda: _count(F.col("__t"), SYMBOLS)),
    "n_lines": (("__lines",), lambda: F.size("__lines").cast("long")),
    "n_dup_lines": (("__lines",), lambda: (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long")),
    "n_repeat_words": (("__w", "__g"), lambda: repeat_words("__g")),
    "n_upper": ((), lambda: _count(F.col("__t"), "A-Z")),
    "n_exclaim": ((), lambda: (F.length("__t") - F.length(F.replace(F.col("__t"), F.lit("!"), F.lit("")))).cast("long")),
}


def _with(df: DataFrame, wanted: list[str], where: Column | None = None) -> DataFrame:
    """df (with ``__t``) with those of the counts ``wanted``, and of their parts, that it lacks; null where ``where`` is not true."""
    for table in (PARTS, FEATURES):
        for name, (_, make) in table.items():
            asked = name in wanted if table is FEATURES else any(name in FEATURES[f][0] for f in wanted)
            if asked and name not in df.columns:
                df = df.withColumn(name, make() if where is None else F.when(where, make()))
    return df


def _texts(docs: DataFrame, text: str) -> DataFrame:
    kept = [c for c in docs.columns if c not in FEATURES and c not in PARTS and c != "__t"]
    return docs.select(*kept, whole(text).alias("__t"))


def features(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with all counts of each row."""
    return _with(_texts(docs, text), list(FEATURES)).drop("__t", *PARTS)


@dataclass(frozen=True)
class Cascade:
    rules: tuple[Rule, ...]
    report: tuple[tuple[str, float, float], ...] = ()

    @classmethod
    def fit(cls, docs: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES, sample_rows: int = SAMPLE_ROWS) -> Cascade:
        """Orders the rules by rejections per second on ``sample_rows`` rows drawn from the whole table.

        A rule's cost is the time of the counts that it needs, the least of REPEATS runs through the drawn rows less that
        of runs without a rule, which is the start of a job.
        """
        share = sample_rows / max(docs.count(), 1)
        sample = docs.where(F.rand(SEED) < share).select(F.col(text).alias("text")).cache()  # some sample_rows rows
        try:
            rows = max(sample.count(), 1)

            def seconds(of: Column, needs: list[str]) -> tuple[float, int]:
                again = sample.withColumn("again", F.explode(F.sequence(F.lit(1), F.lit(TIMES))))
                job = _with(_texts(again, "text"), needs).agg(of.alias("n"))
                taken = []
                for _ in range(REPEATS):
                    began = time.perf_counter()
                    n = job.first()["n"]
                    taken.append(time.perf_counter() - began)
                return min(taken) / TIMES, n / TIMES

            start, _ = seconds(F.coalesce(F.max(F.length("__t")), F.lit(0)), [])
            report = []
            for rule in rules:
                spent, rejected = seconds(F.count_if(F.expr(rule.fails)), rule.needs)
                report.append((rule.name, rejected / rows, max(spent - start, 0.0) / rows))
        finally:
            sample.unpersist()
        place = {name: (-(rejected / max(cost, 1e-6)), i) for i, (name, rejected, cost) in enumerate(report)}
        return cls(tuple(sorted(rules, key=lambda r: place[r.name])), tuple(report))

    def apply(self, docs: DataFrame, text: str = "text", always: tuple[str, ...] = ()) -> DataFrame:
        """docs with ``failed_rule`` (null if none), ``kept`` and the counts: those of ``always`` in every row, others where they were needed."""
        out = _with(_texts(docs, text), list(always)).withColumn("failed_rule", F.lit(None).cast("string"))
        for rule in self.rules:
            open_yet = F.col("failed_rule").isNull()
            out = _with(out, rule.needs, open_yet)
            out = out.withColumn("failed_rule", F.when(open_yet & F.expr(rule.fails), F.lit(rule.name)).otherwise(F.col("failed_rule")))
        return out.withColumn("kept", F.col("failed_rule").isNull()).drop("__t", *PARTS)
