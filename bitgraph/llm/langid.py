"""Language identification: multinomial naive Bayes over hashed character n-grams.

Texts are lower-cased, runs of ASCII non-letters become one space, and their 1- to ORDERS-grams are hashed into BUCKETS
buckets an order. Training counts n-grams per language on the executors; the matrix of log-probabilities, whose size
BUCKETS, ORDERS and the number of languages bound, is broadcast. Scoring gathers a batch's n-grams and adds up their rows.

The training rows are a bounded sample by hash (MOST_TRAINING rows at most on average); scoring covers whole texts.

Defined results: null text, and text without a letter, is ``und`` with score 0; without any training row everything is
``und``; repeated rows get equal results; an empty table gives an empty result; other columns pass through unless named
like a result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import slices

ORDERS = 3
BUCKETS = 1 << 15
ALPHA = 0.5
UNKNOWN = "und"
MOST_TRAINING = 8_000
#: Characters that are worked on at once, so that memory doesn't follow the length of a text.
PIECE = 1 << 18
LETTER = re.compile(r"[^\W\d_]")

_SPACES = np.array([not chr(c).isalpha() for c in range(128)])
_MULTIPLIERS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)


def gram_ids(text: str) -> np.ndarray:
    """The column of each n-gram of a text: order k has the columns from k * BUCKETS on."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    c = np.where(_SPACES[np.minimum(c, 127)] & (c < 128), np.uint32(32), c)
    c = np.concatenate(([np.uint32(32)], c[~((c == 32) & (np.concatenate(([np.uint32(32)], c[:-1])) == 32))]))
    out, h = [], np.zeros(len(c), np.uint64)
    for k in range(min(ORDERS, len(c))):
        h = (h[: len(c) - k] + c[k:]) * _MULTIPLIERS[k % 3]
        h ^= h >> np.uint64(31)
        out.append((h % np.uint64(BUCKETS)).astype(np.int64) + k * BUCKETS)
    return np.concatenate(out)


def pieces(text: str) -> Iterator[str]:
    """Parts of a text that overlap so that no n-gram is lost."""
    for at in range(0, max(len(text), 1), PIECE):
        yield text[at : at + PIECE + ORDERS - 1]


def bounded_sample(rows: DataFrame, key: str, most: int) -> DataFrame:
    """Of rows of which there may be any number, ``most`` on average, chosen by a hash of ``key``."""
    n = rows.count()
    return rows if n <= most else rows.where(F.pmod(F.xxhash64(F.col(key), F.lit(77)), F.lit(1_000_003)) < int(1_000_003 * most / n))


class NaiveBayes:
    def __init__(self, languages: list[str], weights: np.ndarray, prior: np.ndarray):
        self.languages, self.weights, self.prior = languages, weights, prior

    @classmethod
    def fit(cls, labelled: DataFrame, text: str = "text", lang: str = "lang") -> NaiveBayes:
        """From rows with a text and a language; rows that lack either don't count."""
        def count(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[str, np.ndarray] = {}
            for batch in it:
                for label, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    to = sums.setdefault(label, np.zeros(ORDERS * BUCKETS + 1, np.int64))
                    to[-1] += 1  # texts
                    for piece in pieces(t):
                        to[:-1] += np.bincount(gram_ids(piece), minlength=ORDERS * BUCKETS)
            for label, to in sums.items():
                at = np.flatnonzero(to)
                yield pa.RecordBatch.from_arrays([pa.array([label] * len(at), pa.string()), pa.array(at), pa.array(to[at])], names=["lang", "at", "n"])

        rows = labelled.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text"))
        counts = rows.mapInArrow(count, "lang string, at bigint, n bigint").groupBy("lang", "at").agg(F.sum("n").alias("n")).toArrow()
        names = counts.column("lang").to_pylist()
        languages = sorted(set(names))
        table = np.zeros((len(languages), ORDERS * BUCKETS + 1))
        place = {x: i for i, x in enumerate(languages)}
        np.add.at(table, ([place[x] for x in names], counts.column("at").to_numpy()), counts.column("n").to_numpy())
        prior = np.log((table[:, -1] + 1) / (table[:, -1].sum() + len(languages))) if languages else np.zeros(0)
        grams = table[:, :-1].reshape(len(languages), ORDERS, BUCKETS) + ALPHA
        weights = np.log(grams / grams.sum(axis=2, keepdims=True)).reshape(len(languages), ORDERS * BUCKETS)
        return cls(languages, np.ascontiguousarray(weights.T.astype(np.float32)), prior)

    def posterior(self, text: str) -> np.ndarray:
        total = self.prior.copy()
        for piece in pieces(text):
            total += self.weights[gram_ids(piece)].sum(axis=0, dtype=np.float64)
        e = np.exp(total - total.max())
        return e / e.sum()

    def predict(self, docs: DataFrame, text: str = "text") -> DataFrame:
        """docs with lang_pred and score, the posterior of that language."""
        model = docs.sparkSession.sparkContext.broadcast((self.languages, self.weights, self.prior))
        new = [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]
        passed = [f for f in docs.schema if f.name not in ("lang_pred", "score")]

        def score(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = NaiveBayes(*model.value)
            for batch in slices(it):
                langs, scores = [], []
                for t in batch.column(len(passed)).to_pylist():
                    if not own.languages or not t or not LETTER.search(t):
                        langs.append(UNKNOWN)
                        scores.append(0.0)
                        continue
                    p = own.posterior(t)
                    langs.append(own.languages[int(p.argmax())])
                    scores.append(float(p.max()))
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(passed)], pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[f.name for f in [*passed, *new]])

        return docs.withColumn("__text", docs[text]).select(*[f.name for f in passed], "__text").mapInArrow(score, T.StructType([*passed, *new]))
