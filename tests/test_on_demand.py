"""Trees built at first need against the whole index."""

from collections import Counter

import pytest

from bitgraph.operators.graph import Graph, OnDemand
from bitgraph.plans import workloads
from bitgraph.sources import graphs

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def daily(spark):
    return Graph(spark, graphs.triples(spark, SF, "daily"), "daily")


def test_patterns_build_the_trees_of_their_predicates_only(daily):
    k, engine = daily.scratch.keep(workloads.dated_anchors(daily)), daily.engine()
    names = ("a_oo", "b_oo", "b_ss")
    run = lambda name, e: Counter(map(tuple, workloads.run_join(daily, workloads.DATED[name], e, constants=k).collect()))
    got = {name: run(name, engine) for name in names}
    assert isinstance(engine, OnDemand) and not daily._indexes and "predicates" not in daily.__dict__
    assert 0 < len(engine.built) == engine.trees.tiles.select("p_id").distinct().count() < daily.n_p / 5
    assert got == {name: run(name, daily.index()) for name in names} and all(got.values())
    assert run("b_oo", OnDemand(daily, most=1)) == run("b_oo", OnDemand(daily, most_nodes=1)) == got["b_oo"]  # too many: the whole index
    assert daily.engine() is daily.index()


def test_names_are_those_of_the_counted_predicates(daily):
    names = {tuple(r) for r in daily._names.select("pred", "p_id").collect()}
    assert names == {tuple(r) for r in daily.predicates.select("pred", "p_id").collect()}
