"""Secret scans with multipart credential linking.

Base patterns find assigned secrets, access identifiers and long hexadecimal strings. Weak parts (identifiers, random
looking strings, endpoints) count only together: an identifier is paired with the random strings of its scope, however
far apart and however long, and the endpoints of a scope with such a pair join it. A scope ends at a blank line. A lone
weak part is never reported.

Defined results: null text is empty and has no spans; repeated rows are scanned each by itself; an empty table gives an
empty result; other columns pass through unless named like a result. Positions are code points, ends exclusive. A text of
any length is scanned whole: the cost is linear, plus a sort of the parts.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_right
from collections.abc import Callable, Iterable, Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import slices

KINDS = ("assign", "access", "hex", "linked_id", "linked_secret", "linked_endpoint")
#: The base patterns; ASCII letters of the first match in either case.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
MIN_ASSIGN, MIN_ACCESS = 12, 18

WEAK_ID = re.compile(r"""\b(?:access|account|client|user|app)[_-]?(?:key[_-]?)?id["']?\x20*[:=]\x20*["']?([A-Za-z0-9_.@-]{4,})""", re.ASCII | re.IGNORECASE)
ENDPOINT = re.compile(r"""\b(?:https?|ftp|s3|amqp|postgres(?:ql)?|mysql|mongodb|redis)://[^\s"'<>]{4,}""", re.ASCII)
RANDOM = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}(?![A-Za-z0-9+/_=-])", re.ASCII)
#: What ends a scope.
SCOPE = re.compile(r"\n[\x20\t]*\n")
MIN_ENTROPY = 3.5


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) by start, then kind."""
    out = []
    if ":" in text or "=" in text:
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= MIN_ASSIGN]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= MIN_ACCESS]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def entropy(s: str) -> float:
    """Bits a character."""
    return -sum(c / len(s) * math.log2(c / len(s)) for c in map(s.count, set(s)))


def looks_random(s: str) -> bool:
    return bool(re.search(r"[0-9]", s) and re.search(r"[A-Za-z]", s)) and entropy(s) >= MIN_ENTROPY


def furthest(spans: Iterable[tuple[int, int]]) -> Callable[[int], int]:
    """A function of a place: the furthest end of the spans that start there or before, -1 without one."""
    ordered = sorted(spans)
    starts, ends = [s for s, _ in ordered], [-1, *accumulate((e for _, e in ordered), max)]
    return lambda at: ends[bisect_right(starts, at)]


def linked_spans(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Weak parts that co-occur with their complement, as (start, kind, end)."""
    weak_ids = [(m.start(1), m.end(1)) for m in WEAK_ID.finditer(text)] if ":" in text or "=" in text else []
    ids = weak_ids + [(s, e) for s, k, e in base if k == 1]
    if not ids:
        return []
    ends = [m.start() for m in SCOPE.finditer(text)]
    scope = lambda at: bisect_right(ends, at)
    taken = {(s, e) for s, _, e in base} | set(weak_ids)
    reach = furthest(taken)
    weak = [(m.start(), m.end()) for m in RANDOM.finditer(text) if reach(m.start()) < m.end() and looks_random(m[0])]
    strong = [(s, e) for s, k, e in base if k != 1]
    hosts = [(m.start(), m.end()) for m in ENDPOINT.finditer(text)] if "://" in text else []
    host = furthest(hosts)
    weak = [(s, e) for s, e in weak if host(s) <= s]

    def near(parts: list[tuple[int, int]], to: list[tuple[int, int]]) -> list[tuple[int, int]]:
        """Those of ``parts`` in the same scope as one of ``to``."""
        scopes = {scope(s) for s, _ in to}
        return [(s, e) for s, e in parts if scope(s) in scopes]

    secrets = near(weak, ids)
    paired = near(ids, secrets + strong)
    linked = [(s, 3, e) for s, e in near(weak_ids, secrets + strong)] + [(s, 4, e) for s, e in secrets]
    return linked + [(s, 5, e) for s, e in near(hosts, paired)]


def render(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in sorted(spans))


def redact(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with each maximal run of span characters replaced by its first kind in brackets."""
    out, at = [], 0
    for s, k, e in sorted(spans):
        if e <= at:
            continue
        if s >= at:
            out += [text[at:s], f"[{KINDS[k].upper()}]"]
        at = e
    return "".join([*out, text[at:]])


RESULT = T.StructType([
    T.StructField("n_assign", T.LongType()), T.StructField("n_access", T.LongType()), T.StructField("n_hex", T.LongType()),
    T.StructField("base_sha256", T.StringType()), T.StructField("spans", T.StringType()), T.StructField("redacted", T.StringType()),
])


def scan(docs: DataFrame, text: str = "text", redacted: bool = False) -> DataFrame:
    """docs with the counts and spans of each text, and with its redacted text if asked for."""
    fields = [f for f in RESULT if redacted or f.name != "redacted"]
    passed = [f for f in docs.schema if f.name not in {x.name for x in fields}]
    if text not in docs.columns:
        raise ValueError(f"no column {text}")

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(it):
            rows: list[list] = [[] for _ in fields]
            for t in batch.column(batch.schema.names.index("__scan")).to_pylist():
                t = t or ""
                base = base_spans(t)
                spans = base + linked_spans(t, base)
                n = [sum(k == x for _, k, _ in base) for x in range(3)]
                got = [*n, hashlib.sha256(render(base).encode()).hexdigest(), render(spans), redact(t, spans)]
                for to, x in zip(rows, got, strict=False):
                    to.append(x)
            kinds = [pa.int64()] * 3 + [pa.string()] * 3
            yield pa.RecordBatch.from_arrays([batch.column(f.name) for f in passed] + [pa.array(r, k) for r, k in zip(rows, kinds, strict=False)], names=[f.name for f in [*passed, *fields]])

    return docs.withColumn("__scan", docs[text]).select(*[f.name for f in passed], "__scan").mapInArrow(batches, T.StructType(passed + fields))
