"""Queries for facts of new terms, exchange with the dictionary, bundles, list kernels, codes and late events."""

from __future__ import annotations

from functools import partial

from pyspark.sql import functions as F

from bitgraph.catalog import add, query
from bitgraph.operators.dynamic import DynamicGraph
from bitgraph.operators.graph import Graph, open_graph
from bitgraph.operators.intersect import KERNELS, intersect
from bitgraph.plans.oracles import with_graph
from bitgraph.sources import surface
from bitgraph.store import Scratch
from bitgraph.streaming import ingest

# Facts of new terms: the base has views only, all else comes later, so that users and items gain roles. --------------------------

_LATER = "p <> 'view'"


def _grown(g: Graph) -> DynamicGraph:
    if "_grown" not in g.__dict__:
        base = Graph(g.spark, g.triples.where(f"NOT ({_LATER})"), "views")
        first = DynamicGraph.of(base, g.scratch).insert(g.triples.where("p = 'by'"))
        g.__dict__["_grown"] = first.insert(g.triples.where(_LATER))
    return g.__dict__["_grown"]


def _on(name: str, f):
    return lambda spark, sf_dir: f(open_graph(spark, sf_dir, name))


add("dyn_terms_insert", _on("activity", lambda g: _grown(g).match()), with_graph("activity", "SELECT s, p, o FROM g"))
add("dyn_terms_delete", _on("activity", lambda g: _grown(g).delete(g.triples.where("p = 'by' OR o = '\"click\"'")).match()), with_graph("activity", "SELECT s, p, o FROM g WHERE p <> 'by' AND o <> '\"click\"'"))
add("dyn_terms_chain", _on("activity", lambda g: _grown(g).chain({"p": "by"}, {"p": "view"})), with_graph("activity", "SELECT a.s, a.o AS x, b.o FROM g a JOIN g b ON b.s = a.o WHERE a.p = 'by' AND b.p = 'view'"))
add("dyn_terms_compact", _on("activity", lambda g: _grown(g).compact().ids), with_graph("activity", "SELECT s_id, p_id, o_id FROM ids", ids=True))

# Exchange and layout -------------------------------------------------------------------------------------------------------------


def _exchanged(g: Graph):
    path = f"{g.scratch.root}/exchange"
    surface.export_graph(g, path)
    return surface.import_graph(g.spark, path).match()


add("exchange_dictionary", _on("threads", _exchanged), with_graph("threads", "SELECT s, p, o FROM g"))
add("tile_bundles", _on("daily", lambda g: g.index().bundles(100)), with_graph("daily", "SELECT p_id, n_points, CAST(floor((CAST(sum(n_points) OVER (ORDER BY p_id) AS BIGINT) - n_points) / 100.0) AS BIGINT) AS bundle FROM (SELECT p_id, count(*) AS n_points FROM ids GROUP BY p_id) x", ids=True))


def _bundled(g: Graph):
    path = f"{g.scratch.root}/bundled"
    g.index().write_bundled(path, 100)
    return surface.open_index(g.spark, path).match()


add("index_bundled", _on("daily", _bundled), with_graph("daily", "SELECT s_id, p_id, o_id FROM ids", ids=True))

# Kernels and codes ---------------------------------------------------------------------------------------------------------------


def _both(kernel: str, g: Graph):
    """Urgent orders that are finished: the two columns of subjects come sorted from the trees."""
    ids = g.lookup(("status", "p"), ('"F"', "o"), ("priority", "p"), ('"1-URGENT"', "o"))
    column = lambda p, o: g.index().match(p=ids.get((p, "p"), -1), o=ids.get((o, "o"), 0) or (1 << 62))
    return g.decode(intersect(column("status", '"F"'), column("priority", '"1-URGENT"'), "s_id", kernel).withColumnRenamed("s_id", "x"), x="s")


for _kernel in KERNELS:
    add(f"join_kernel_{_kernel}", _on("star", partial(_both, _kernel)), with_graph("star", "SELECT a.s AS x FROM g a JOIN g b ON b.s = a.s WHERE a.p = 'status' AND a.o = '\"F\"' AND b.p = 'priority' AND b.o = '\"1-URGENT\"'"))


def _stats(g: Graph):
    tiles = g.index("k2", "plain", tile_bits=12).tiles
    return tiles.select("p_id", surface.tree_stats(F.struct(*surface.PAYLOAD)).alias("t")).groupBy("p_id").agg(F.sum("t.n_points").alias("n_points"))


add("fn_tree_stats", _on("activity", _stats), with_graph("activity", "SELECT p_id, count(*) AS n_points FROM ids GROUP BY p_id", ids=True))

#: Objects of a block, so that no list of a hot subject is long.
_CODED = 4096


def _coded(g: Graph):
    """Object lists in blocks, coded by chunks of four bits, and the last number of each read back."""
    block = F.expr(f"(o_id - 1) DIV {_CODED}")
    lists = g.ids.groupBy("s_id", block.alias("block")).agg(F.sort_array(F.collect_set(F.col("o_id") - 1 - block * _CODED)).alias("at"))
    coded = lists.select("s_id", "block", F.size("at").cast("bigint").alias("n"), surface.dac_encode(4)("at").alias("codes"))
    return coded.select("s_id", "block", "n", surface.dac_get("codes", F.col("n") - 1).alias("last"))


add("fn_dac_get", _on("activity", _coded), with_graph("activity", f"SELECT s_id, (o_id - 1) // {_CODED} AS block, count(DISTINCT o_id) AS n, max((o_id - 1) % {_CODED}) AS last FROM ids GROUP BY s_id, block", ids=True))

# Late events ---------------------------------------------------------------------------------------------------------------------

_LATE_SQL = """WITH e AS (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2000-01-01') AS w, event_type, ts, epoch(ts) >= (epoch((SELECT min(ts) FROM events)) + epoch((SELECT max(ts) FROM events))) / 2 AS later FROM events)
SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM e WHERE later AND w + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 2 DAY GROUP BY w, event_type"""


@query("st_late", _LATE_SQL)
def _late(spark, sf_dir):
    """Windows that the watermark closes, in append mode: the earlier half arrives last and is shut out."""
    return ingest.replay(spark, sf_dir, lambda s: ingest.counts(s, "6 hours"), Scratch(spark))
