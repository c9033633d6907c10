"""Toxicity by multiple-instance learning: noisy-or over sentences, learned from labels of whole texts.

A sentence is toxic with the logistic of its words' weights; a text is toxic if any sentence is, or by a small leak:
P = 1 - (1 - leak) * product over sentences of (1 - p). Weights maximise the likelihood of the text labels, so credit
goes to the sentences that explain them, which are then located in scoring.

Training reads a bounded sample of labelled rows. Words that tell the labels apart are found by counts on the executors;
only their places in sentences come to the driver. Scoring covers every sentence of every text.

Defined results: null and empty text score the leak; without labels everything scores 0; repeated rows get equal results;
an empty table gives an empty result; other columns pass through unless named like a result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .langid import bounded_sample

MOST_TRAINING = 12_000
#: Words with weights, of those that at least LEAST_TEXTS toxic training texts hold.
MOST_WORDS = 4096
LEAST_TEXTS = 3
#: Standard errors by which a word's rates in toxic and clean texts must differ.
LEAST_Z = 3.0
STEPS = 400
SENTENCE = re.compile(r"[^.!?\n]+")
WORD = re.compile(r"[^\W_]+")


def logistic(z):
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def sentence_words(text: str, known: dict[str, int]) -> list[tuple[int, int, list[int]]]:
    """(start, end, places in ``known`` of its distinct words) of each sentence that holds a known word."""
    if known.keys().isdisjoint(WORD.findall(text.lower())):
        return []
    out = []
    for m in SENTENCE.finditer(text):
        if words := {known[w] for w in WORD.findall(m[0].lower()) if w in known}:
            out.append((m.start(), m.end(), sorted(words)))
    return out


class NoisyOr:
    def __init__(self, words: list[str], weights: np.ndarray, bias: float, leak: float):
        self.words, self.weights, self.bias, self.leak = words, weights, bias, leak

    @classmethod
    def fit(cls, labelled: DataFrame, text: str = "text", label: str = "label", most_words: int = MOST_WORDS) -> NoisyOr:
        """From rows with a text and a label of 0 or 1."""
        rows = labelled.where(F.col(label).isNotNull()).select(F.coalesce(F.col(text), F.lit("")).alias("text"), F.col(label).cast("int").alias("label"))

        def distinct_words(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in it:
                texts, labels = batch.column(0).to_pylist(), batch.column(1).to_pylist()
                pairs = [(w, y) for t, y in zip(texts, labels, strict=True) for w in set(WORD.findall(t.lower()))]
                yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in pairs], pa.string()), pa.array([y for _, y in pairs], pa.int32())], names=["word", "label"])

        n = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count("*").alias("n")).collect()}
        n1, n0 = n.get(1, 0), n.get(0, 0)
        if not n1 or not n0:
            return cls([], np.zeros(0), -20.0, float(n1 > 0))
        held = rows.mapInArrow(distinct_words, "word string, label int").groupBy("word").agg(F.sum("label").alias("t"), F.sum(1 - F.col("label")).alias("c"))
        rate = (F.col("t") + F.col("c")) / (n1 + n0)
        z = (F.col("t") / n1 - F.col("c") / n0) / F.sqrt(rate * (1 - rate) * (1 / n1 + 1 / n0) + 1e-12)
        best = held.where(F.col("t") >= LEAST_TEXTS).withColumn("z", z).where(F.col("z") >= LEAST_Z).orderBy(F.desc("z"), "word").limit(most_words)
        words = [r["word"] for r in best.collect()]
        known = {w: i for i, w in enumerate(words)}

        def places(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in it:
                sentences = [[w for _, _, w in sentence_words(t, known)] for t in batch.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(sentences, pa.list_(pa.list_(pa.int32())))], names=["label", "sentences"])

        # Equal bags (most: texts without a known word) weigh by their number.
        bags = rows.mapInArrow(places, "label int, sentences array<array<int>>").groupBy("label", "sentences").agg(F.count("*").alias("n")).collect()
        bags.sort(key=lambda r: (r["label"], r["n"], r["sentences"]))
        return cls._learn(words, [r["sentences"] for r in bags], np.array([r["label"] for r in bags]), np.array([r["n"] for r in bags], float))

    @classmethod
    def _learn(cls, words: list[str], bags: list, y: np.ndarray, times: np.ndarray) -> NoisyOr:
        bag_of = np.array([i for i, b in enumerate(bags) for _ in b], int)
        sentence_of = np.array([k for k, s in enumerate(s for b in bags for s in b) for _ in s], int)
        word_of = np.array([w for b in bags for s in b for w in s], int)
        theta = np.concatenate([np.full(len(words), 1.0), [-1.0, -4.0]])  # weights, bias, logit of the leak
        m = v = np.zeros_like(theta)
        total = times.sum()
        for step in range(1, STEPS + 1):
            p = logistic(np.bincount(sentence_of, theta[word_of], len(bag_of)) + theta[-2])
            leak = logistic(theta[-1])
            clean = np.exp(np.log1p(-leak) + np.bincount(bag_of, np.log1p(-np.minimum(p, 1 - 1e-12)), len(bags)))
            # How the log-likelihood moves with the log of a sentence's odds: -p in clean bags, p * clean / (1 - clean) in toxic ones.
            factor = times * np.where(y == 1, clean / np.maximum(1 - clean, 1e-9), -1.0)
            by_sentence = factor[bag_of] * p
            g = np.concatenate([np.bincount(word_of, by_sentence[sentence_of], len(words)), [by_sentence.sum(), (factor * leak).sum()]]) / total
            g[: len(words)] -= 1e-5 * theta[: len(words)]
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            theta = theta + 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
        return cls(words, theta[:-2], float(theta[-2]), float(logistic(theta[-1])))

    def score(self, docs: DataFrame, text: str = "text", least: float = 0.5) -> DataFrame:
        """docs with score and ``offending``: (start, end, score) of the sentences with ``least`` or more."""
        model = docs.sparkSession.sparkContext.broadcast((self.words, self.weights, self.bias, self.leak))
        spot = T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("score", T.DoubleType())])
        new = [T.StructField("score", T.DoubleType()), T.StructField("offending", T.ArrayType(spot))]
        passed = [f for f in docs.schema if f.name not in ("score", "offending")]
        arrow_spots = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())]))

        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words, weights, bias, leak = model.value
            known = {w: i for i, w in enumerate(words)}
            for batch in it:
                scores, spots = [], []
                for t in batch.column(len(passed)).to_pylist():
                    clean, found = 1 - leak, []
                    for start, end, places in sentence_words(t or "", known):
                        p = float(logistic(weights[places].sum() + bias))
                        clean *= 1 - p
                        if p >= least:
                            found.append({"start": start, "end": end, "score": p})
                    scores.append(1 - clean)
                    spots.append(found)
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(passed)], pa.array(scores, pa.float64()), pa.array(spots, arrow_spots)], names=[f.name for f in [*passed, *new]])

        return docs.withColumn("__text", docs[text]).select(*[f.name for f in passed], "__text").mapInArrow(batches, T.StructType([*passed, *new]))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MOST_TRAINING) -> DataFrame:
    """(text, label) of a bounded sample of the labelled rows; the sample's ids are few enough to be broadcast."""
    chosen = bounded_sample(labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", F.col(label).alias("label")), "doc_id", most)
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "label")
