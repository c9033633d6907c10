"""Near duplicates against all pairs."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitgraph.llm.common import Scratch
from bitgraph.llm.components import components
from bitgraph.llm.dedup import WIDE, NearDuplicates, Shingler, bitmap, least_apart, near_duplicates, parities


def shingle_set(text, width):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    n = min(width, len(w))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()


def brute(rows, width):
    sets = [shingle_set(t, width) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            c = len(a & b)
            if c and 100 * c >= 80 * (len(a) + len(b) - c):
                root[find(i)] = find(j)
    least = defaultdict(list)
    for i, (d, _) in enumerate(rows):
        least[find(i)] += [] if d is None else [d]
    return Counter((d, len(s), (m := min(least[find(i)], default=None) if s else d), d == m) for i, ((d, _), s) in enumerate(zip(rows, sets, strict=True)))


def near_copies():
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(400)]
    rows, at = [], 1000
    for base in range(6):
        words = rng.choices(vocabulary, k=[5, 12, 60, 200, 31, 33][base])
        for copy in range(14):
            w = list(words)
            for _ in range(copy * len(w) // 90):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            rows.append((at, " ".join(w) + (" A common line that all of them share" if base % 2 else "")))
            at += 1
    return rows + [(at, "A common line that all of them share"), (at + 1, "a  COMMON line that all of them share"), (at + 2, "x"), (at + 3, "X"), (at + 4, "")]


@pytest.mark.parametrize("width", [2, 5])
def test_components_equal_all_pairs(spark, docs, odd, width):
    df = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(spark.createDataFrame(near_copies(), "doc_id long, text string"))
    rows = [(r.doc_id, r.text) for r in df.collect()]
    got = near_duplicates(df, Scratch(spark), width=width).select("doc_id", "n_shingles", "component_id", "kept").collect()
    assert Counter(map(tuple, got)) == brute(rows, width)


def test_a_text_and_its_longer_copy_meet_at_every_number_of_unshared_values(spark):
    rng, rows = random.Random(3), []
    for u in range(14, 22):
        words = [f"w{u}x{i}" for i in range(500)]
        words.sort(key=lambda w: int(Shingler(1)(w)[0]))
        low, high = rng.sample(range(32), u), rng.sample(range(32, 500), 100 - u)
        rows += [(2 * u, " ".join(words)), (2 * u + 1, " ".join(w for i, w in enumerate(words) if i not in {*low, *high}))]
    got = near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), Scratch(spark), width=1).collect()
    assert {r.doc_id: r.component_id for r in got} == {i: i // 2 * 2 for i, _ in rows}


def test_a_pair_is_made_in_the_list_of_its_first_shared_value(spark):
    rng, rows = random.Random(5), []
    for base in range(3):
        words = [f"w{base}x{i}" for i in range(300)]
        rows += [(100 * base + k, " ".join(rng.sample(words, 255))) for k in range(20)]  # as like as 0.74, below the threshold
    found = NearDuplicates(spark.createDataFrame(rows, "doc_id long, text string"), Scratch(spark), width=1)
    sets = found._full_sets(found.classes.select("c"))
    lists = found.lists(sets.selectExpr("c", "n", "sign", f"slice(hashes, 1, {WIDE}) AS sketch"), WIDE).withColumn("r", sets["c"])
    every = lists.join(found._other(lists), "v").where((lists["c"] > F.col("b")) & found._across(WIDE)).select(lists["c"].alias("a"), "b")
    made = found.pairs_across(lists)
    assert {*map(tuple, made.collect())} == {*map(tuple, every.collect())}
    assert made.count() < 1.5 * made.distinct().count() < every.count() / 10


def test_bitmaps_end_no_pair_of_fewer_values_apart():
    rng = random.Random(7)
    for n in (1, 7, 9, 40, 300, 3000):
        for _ in range(20):
            p = [rng.getrandbits(63) for _ in range(n)]
            q = rng.sample(p, rng.randint(0, n)) + [rng.getrandbits(63) for _ in range(rng.randint(0 if n > 1 else 1, n))] or p
            a, b = (np.frombuffer(bitmap(np.array(x, np.int64)), np.uint8) for x in (p, q))
            apart = len({*p} ^ {*q})
            assert apart * 0.7 - 3 <= least_apart(a, b) <= apart


def test_empty(spark, docs):
    assert near_duplicates(docs.limit(0), Scratch(spark)).count() == 0


def test_components_of_a_path_a_star_and_a_loop(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(30)] + [(7000, 7000)]
    got = dict(components(spark.createDataFrame(edges, "a long, b long"), Scratch(spark)).collect())
    assert got == {i: 0 for i in range(1, 41)} | {100 + i: 100 for i in range(1, 30)}


def test_parities_tell_no_more_values_apart_than_there_are_and_hardly_fewer():
    rng = random.Random(11)
    for n, apart in ((1, 1), (40, 9), (150, 33), (150, 60), (400, 90), (3000, 600)):
        for _ in range(20):
            p = [rng.getrandbits(63) for _ in range(n)]
            q = p[apart // 2 :] + [rng.getrandbits(63) for _ in range(apart - apart // 2)]
            a, b = (parities(np.array(x, np.int64)).view(np.uint8) for x in (p, q))
            told = int(np.bitwise_count(a ^ b).sum())
            assert told <= apart and (apart > 90 or told >= apart * 0.7 - 3)


def test_a_large_group_just_below_the_threshold_makes_few_pairs(spark):
    rng, words = random.Random(13), [f"w{i}" for i in range(150)]
    rows = [(k, " ".join(w if i not in changed else f"c{k}x{i}" for i, w in enumerate(words))) for k in range(120) for changed in [{*rng.sample(range(150), 14)}]]  # as like as 0.69
    found = NearDuplicates(spark.createDataFrame(rows, "doc_id long, text string"), Scratch(spark), width=1)
    made, verify = [], found.verify
    found.verify = lambda pairs, sets=None: (made.append(pairs.count()), verify(pairs, sets))[1]
    got = Counter((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in found.result().collect())
    assert got == brute(rows, 1)
    assert made[-1] < 120 * 119 / 2 / 10, made
