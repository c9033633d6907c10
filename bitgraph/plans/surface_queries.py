"""Queries for SPARQL text, SQL access, exchange formats and streams."""

from __future__ import annotations

from functools import partial

from pyspark.sql import functions as F

from bitgraph.catalog import add, query
from bitgraph.operators.graph import open_graph
from bitgraph.plans import sparql
from bitgraph.plans.oracles import with_graph
from bitgraph.sources import surface
from bitgraph.sources.graphs import triples_sql
from bitgraph.store import Scratch
from bitgraph.streaming import ingest

_SPARQL = {
    "sparql_bgp": ("SELECT ?x ?c WHERE { ?x <status> \"F\" ; <priority> \"1-URGENT\" . ?x <placedBy> ?c }", "SELECT a.s AS x, c.o AS c FROM g a JOIN g b ON b.s = a.s JOIN g c ON c.s = a.s WHERE a.p = 'status' AND a.o = '\"F\"' AND b.p = 'priority' AND b.o = '\"1-URGENT\"' AND c.p = 'placedBy'"),
    "sparql_filter": ("SELECT ?x ?z WHERE { ?x <size> ?z . FILTER (?z >= 20 && ?z < 24 || ?z = 1) }", "SELECT s AS x, o AS z FROM g WHERE p = 'size' AND (CAST(trim(o, '\"') AS INT) BETWEEN 20 AND 23 OR o = '\"1\"')"),
    "sparql_optional": ("SELECT ?x ?n ?s WHERE { ?x <inNation> ?n . OPTIONAL { ?x <segment> ?s } }", "SELECT a.s AS x, a.o AS n, b.o AS s FROM g a LEFT JOIN g b ON b.s = a.s AND b.p = 'segment' WHERE a.p = 'inNation'"),
    "sparql_union": ("SELECT DISTINCT ?x WHERE { { ?x <inNation> <nation/7> } UNION { ?x <segment> \"BUILDING\" } }", "SELECT s AS x FROM g WHERE p = 'inNation' AND o = 'nation/7' UNION SELECT s FROM g WHERE p = 'segment' AND o = '\"BUILDING\"'"),
    "sparql_minus": ("SELECT ?x WHERE { ?x <inNation> <nation/7> . MINUS { ?x <segment> \"BUILDING\" } }", "SELECT s AS x FROM g WHERE p = 'inNation' AND o = 'nation/7' AND s NOT IN (SELECT s FROM g WHERE p = 'segment' AND o = '\"BUILDING\"')"),
    "sparql_count": ("SELECT ?n (COUNT(?x) AS ?k) WHERE { ?x <inNation> ?n } GROUP BY ?n", "SELECT o AS n, count(*) AS k FROM g WHERE p = 'inNation' GROUP BY o"),
    "sparql_order": ("SELECT ?x WHERE { ?x <inNation> <nation/7> } ORDER BY DESC(?x) LIMIT 5 OFFSET 2", "SELECT s AS x FROM g WHERE p = 'inNation' AND o = 'nation/7' ORDER BY s DESC LIMIT 5 OFFSET 2"),
    "sparql_ask": ("ASK { ?x <inNation> <nation/7> . ?x <segment> \"BUILDING\" }", "SELECT count(*) > 0 AS ask FROM g a JOIN g b ON b.s = a.s WHERE a.p = 'inNation' AND a.o = 'nation/7' AND b.p = 'segment' AND b.o = '\"BUILDING\"'"),
}
for _n, (_text, _sql) in _SPARQL.items():
    add(_n, lambda spark, d, text=_text: sparql.run(open_graph(spark, d, "star"), text), with_graph("star", _sql))


@query("udtf_match", with_graph("threads", "SELECT s_id, p_id, o_id FROM ids WHERE p_id = 1 AND o_id = (SELECT max(o_id) FROM ids WHERE p_id = 1)", ids=True))
def _udtf(spark, sf_dir):
    """The column of the last object of the first predicate."""
    g = open_graph(spark, sf_dir, "threads")
    return surface.triples_match(g, None, 1, g.ids.where("p_id = 1").agg(F.max("o_id")).first()[0])


@query("ds_match", with_graph("threads", "SELECT s_id, p_id, o_id FROM ids WHERE p_id = 2 AND o_id IN (3, 5, 440, 441)", ids=True))
def _data_source(spark, sf_dir):
    g, scratch = open_graph(spark, sf_dir, "threads"), Scratch(spark)
    g.index().write(f"{scratch.root}/index")
    surface.register_source(spark)
    return spark.read.format("tilegraph").load(f"{scratch.root}/index").where(F.col("p_id") == 2).where(F.col("o_id").isin(3, 5, 440, 441))


@query("index_saved", with_graph("threads", "SELECT s_id, p_id, o_id FROM ids WHERE p_id = 2", ids=True))
def _saved(spark, sf_dir):
    g, scratch = open_graph(spark, sf_dir, "threads"), Scratch(spark)
    g.index("k2", "plain", tile_bits=6).write(f"{scratch.root}/index")
    return surface.open_index(spark, f"{scratch.root}/index").match(p=2)


@query("src_text_roundtrip", f"SELECT s, p, o FROM ({triples_sql('words')}) t")
def _text(spark, sf_dir):
    path = f"{Scratch(spark).root}/text"
    surface.write_ntriples(open_graph(spark, sf_dir, "words").triples, path)
    return surface.read_ntriples(spark, path)


def _formats(kind, spark, sf_dir):
    path, t = f"{Scratch(spark).root}/{kind}", open_graph(spark, sf_dir, "threads").triples
    t.write.format(kind).save(path)
    return spark.read.schema("s string, p string, o string").format(kind).load(path)


for _kind in ("csv", "json", "orc"):
    add(f"src_{_kind}", partial(_formats, _kind), f"SELECT s, p, o FROM ({triples_sql('threads')}) t")


def _stream(spark, sf_dir, of, mode="append", each=None):
    return ingest.drain(of(ingest.events(spark, sf_dir)), Scratch(spark), mode, each)


add("st_facts", partial(_stream, of=ingest.facts), f"SELECT s, p, o FROM ({triples_sql('activity')}) t")
add("st_tumbling", partial(_stream, of=lambda s: ingest.counts(s, "6 hours"), mode="complete"), "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2000-01-01'), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
add("st_sliding", partial(_stream, of=lambda s: ingest.counts(s, "6 hours", "3 hours"), mode="complete"), "SELECT strftime(b, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '2000-01-01'), time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '2000-01-01') - INTERVAL 3 HOUR]) AS b FROM events) x GROUP BY ALL")
add("st_session", partial(_stream, of=lambda s: ingest.sessions(s, "6 hours"), mode="complete"), "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) x) y GROUP BY user_id, k")
add("st_pairs", partial(_stream, of=lambda s: ingest.pairs(s, 120)), "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 120 MINUTE")


def _st_match(spark, sf_dir):
    """Each event with all events of its user: bindings of a micro-batch against the index."""
    g = open_graph(spark, sf_dir, "activity")
    by = g.lookup(("by", "p"))["by", "p"]

    def each(batch):
        users = batch.select("event_id", F.concat(F.lit("user/"), "user_id").alias("u"))
        ids = g.encode_constants(users, {"u": "o"})
        found = g.index().match_batch(ids.select(F.col("u").alias("o_id"), F.lit(by).cast("bigint").alias("p_id")))
        rows = ids.join(found, ids["u"] == found["o_id"]).select("event_id", F.col("s_id").alias("other"))
        return g.decode(rows, other="s")

    return _stream(spark, sf_dir, lambda s: s, each=each)


add("st_match", _st_match, "SELECT e.event_id, concat('event/', x.event_id) AS other FROM events e JOIN events x ON x.user_id = e.user_id")
add("st_degrees", partial(_stream, of=ingest.degrees, mode="update"), "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
