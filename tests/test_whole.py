"""Queries over whole tables, against plain Python."""

from collections import Counter, defaultdict

import pytest

from __spark_entry__ import queries

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def odd_dir(spark, tmp_path_factory):
    """Customers without orders, orders without customers or with a null one, and repeated keys."""
    d = tmp_path_factory.mktemp("odd")
    spark.createDataFrame([(1,), (2,), (3,), (6,), (7,)], "c_custkey long").write.parquet(f"{d}/customer.parquet")
    spark.createDataFrame([(1, 1), (50, 1), (51, 3), (52, 9), (100, None)], "o_orderkey long, o_custkey long").write.parquet(f"{d}/orders.parquet")
    return str(d)


def tables(spark, d, name, *cols):
    return [tuple(r) for r in spark.read.parquet(f"{d}/{name}.parquet").select(*cols).collect()]


@pytest.mark.parametrize("odd", [False, True])
def test_joins_of_whole_tables(spark, odd_dir, odd):
    d = odd_dir if odd else DATA
    customers, of = [c for c, in tables(spark, d, "customer", "c_custkey")], defaultdict(list)
    for o, c in tables(spark, d, "orders", "o_orderkey", "o_custkey"):
        of[c].append(o)
    inner = [(c, o) for c in customers for o in of.get(c, [])]
    alone, lost = [(c, None) for c in customers if c not in of], [(None, o) for c, os in of.items() if c not in customers for o in os]
    want = {"left": inner + alone, "right": inner + lost, "full": inner + alone + lost, "semi": [(c,) for c in customers if c in of], "anti": [(c,) for c, _ in alone]}
    for how, rows in want.items():
        assert Counter(map(tuple, queries()[f"join_{how}"](spark, d).collect())) == Counter(rows), how


def test_sets_of_whole_columns(spark):
    rows = tables(spark, DATA, "lineitem", "l_partkey", "l_suppkey")
    a, b = Counter(x for x, _ in rows), Counter(x for _, x in rows)
    want = {"union_all": a + b, "union": Counter({*a, *b}), "intersect": Counter({*a} & {*b}), "intersect_all": a & b, "except": Counter({*a} - {*b}), "except_all": a - b}
    for name, have in want.items():
        assert Counter(r.k for r in queries()[f"set_{name}"](spark, DATA).collect()) == have, name


def test_null_order_of_all_rows(spark):
    toxic = defaultdict(list)
    for i, t in tables(spark, DATA, "labels", "doc_id", "toxic"):
        toxic[i].append(t)
    rows = [(i, t) for i, in tables(spark, DATA, "documents", "doc_id") for t in toxic.get(i, [None])]
    assert [tuple(r) for r in queries()["sort_nulls"](spark, DATA).collect()] == sorted(rows, key=lambda r: (r[1] is None, r[1] or 0, r[0]))


def test_every_event_of_a_stream_is_matched(spark):
    of = defaultdict(list)
    for e, u in tables(spark, DATA, "events", "event_id", "user_id"):
        of[u].append(e)
    want = Counter((e, f"event/{x}") for es in of.values() for e in es for x in es)
    assert Counter(map(tuple, queries()["st_match"](spark, DATA).collect())) == want
