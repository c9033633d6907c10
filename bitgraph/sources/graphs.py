"""Graphs of (s, p, o) facts mapped from the given tables.

A graph is a list of rules, each a SELECT of s, p and o over one table in SQL that Spark and DuckDB both read; braces
mark tables and the few functions whose names differ. Resources are kind/key, literals stand in double quotes. Facts
with a null and repeated facts are dropped.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents labels pages conversations embeddings benchmark".split()


def _day(c: str) -> str:
    return f"CAST(CAST({c} AS DATE) AS STRING)"


def _text(c: str) -> str:
    return f"concat('\"', {c}, '\"')"


def _rule(s: str, p: str, o: str, table: str, where: str = "true") -> str:
    p = p if p.startswith(("'", "concat", "event", "substr")) else f"'{p}'"
    return f"SELECT {s} AS s, {p} AS p, {o} AS o FROM {{{table}}} WHERE {where}"


def _ref(kind: str, *keys: str) -> str:
    return "concat('%s/', %s)" % (kind, ", '/', ".join(keys))


def _daily(length: int) -> list[str]:
    """Ship dates cut to ``length`` characters: 10 a day, 7 a month, 4 a year."""
    day = f"substr({_day('l_shipdate')}, 1, {length})"
    return [
        _rule(_ref("order", "l_orderkey"), f"concat('shippedOn/', {day})", _ref("part", "l_partkey"), "lineitem"),
        _rule(_ref("part", "l_partkey"), f"concat('soldOn/', {day})", _ref("supplier", "l_suppkey"), "lineitem"),
    ]


_ITEM = "concat('item/', regexp_extract(props, '\"k\": *([0-9]+)', 1))"
_HOUR = f"concat({_day('ts')}, 'T', lpad(CAST(hour(ts) AS STRING), 2, '0'))"

RULES: dict[str, list[str]] = {
    "star": [
        _rule(_ref("order", "o_orderkey"), "placedBy", _ref("customer", "o_custkey"), "orders"),
        _rule(_ref("order", "o_orderkey"), "status", _text("o_orderstatus"), "orders"),
        _rule(_ref("order", "o_orderkey"), "priority", _text("o_orderpriority"), "orders"),
        _rule(_ref("order", "o_orderkey"), "orderedOn", _text(_day("o_orderdate")), "orders"),
        _rule(_ref("order", "l_orderkey"), "containsPart", _ref("part", "l_partkey"), "lineitem"),
        _rule(_ref("order", "l_orderkey"), "shippedBy", _ref("supplier", "l_suppkey"), "lineitem"),
        _rule(_ref("part", "l_partkey"), "soldBy", _ref("supplier", "l_suppkey"), "lineitem"),
        _rule(_ref("customer", "c_custkey"), "inNation", _ref("nation", "c_nationkey"), "customer"),
        _rule(_ref("customer", "c_custkey"), "segment", _text("c_mktsegment"), "customer"),
        _rule(_ref("supplier", "s_suppkey"), "inNation", _ref("nation", "s_nationkey"), "supplier"),
        _rule(_ref("nation", "n_nationkey"), "inRegion", _ref("region", "n_regionkey"), "nation"),
        _rule(_ref("nation", "n_nationkey"), "label", _text("n_name"), "nation"),
        _rule(_ref("region", "r_regionkey"), "label", _text("r_name"), "region"),
        _rule(_ref("part", "p_partkey"), "brand", _text("p_brand"), "part"),
        _rule(_ref("part", "p_partkey"), "type", _text("p_type"), "part"),
        _rule(_ref("part", "p_partkey"), "size", _text("p_size"), "part"),
        _rule(_ref("part", "p_partkey"), "label", _text("p_name"), "part"),
    ],
    "daily": _daily(10),
    "monthly": _daily(7),
    "yearly": _daily(4),
    "activity": [
        _rule(_ref("user", "user_id"), "event_type", _ITEM, "events"),
        _rule(_ref("event", "event_id"), "by", _ref("user", "user_id"), "events"),
        _rule(_ref("event", "event_id"), "about", _ITEM, "events"),
        _rule(_ref("event", "event_id"), "kind", _text("event_type"), "events"),
        _rule(_ref("event", "event_id"), "hour", _text(_HOUR), "events"),
    ],
    "threads": [
        _rule(_ref("turn", "conv_id", "turn"), "partOf", _ref("conv", "conv_id"), "conversations"),
        _rule(_ref("turn", "conv_id", "turn"), "role", _text("role"), "conversations"),
        "SELECT concat('turn/', a.conv_id, '/', a.turn) AS s, 'repliesTo' AS p, concat('turn/', b.conv_id, '/', b.turn) AS o FROM {conversations} a JOIN {conversations} b ON a.conv_id = b.conv_id AND b.turn = a.turn - 1",
    ],
    "words": [
        _rule(_ref("doc", "doc_id"), "lang", _text("lang"), "documents"),
        _rule(_ref("doc", "doc_id"), "source", _text("source"), "documents"),
        "SELECT s, p, concat('\"', w, '\"') AS o FROM (SELECT concat('doc/', doc_id) AS s, 'mentions' AS p, {each}(regexp_extract_all(text, '{letters}'{all})) AS w FROM {documents}) x",
        _rule(_ref("doc", "doc_id"), "quality", _text("quality"), "labels"),
        _rule(_ref("doc", "doc_id"), "toxic", _text("toxic"), "labels"),
    ],
    "links": ["SELECT url AS s, 'linksTo' AS p, h AS o FROM (SELECT url, {each}(regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)) AS h FROM {pages}) x"],
}
RULES["similar"] = [_rule(_ref("vec", "vec_id"), "label", _text("label"), "embeddings")]

_SPARK = {"each": "explode", "letters": "\\\\p{L}+", "all": ", 0"}
_DUCK = {"each": "unnest", "letters": "\\p{L}+", "all": ", 0"}


def _fill(rule: str, words: dict[str, str]) -> str:
    for k, v in words.items():
        rule = rule.replace("{%s}" % k, v)
    return rule


def triples_sql(name: str) -> str:
    """The graph as DuckDB SQL over the tables by name, distinct and without nulls."""
    rules = [_fill(r, _DUCK | {t: t for t in TABLES}) for r in RULES[name]]
    return "SELECT DISTINCT s, p, o FROM (%s) r WHERE s IS NOT NULL AND p IS NOT NULL AND o IS NOT NULL" % " UNION ALL ".join(rules)


def raw_triples(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The facts as mapped, with repeats."""
    out = None
    for rule in RULES[name]:
        used = [t for t in TABLES if "{%s}" % t in rule]
        views = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used}
        part = _sql(spark, _fill(rule, _SPARK), views)
        out = part if out is None else out.unionAll(part)
    return out


def _sql(spark: SparkSession, text: str, views: dict[str, DataFrame]) -> DataFrame:
    """The SQL over DataFrames in place of the tables in braces; braces of patterns are left alone."""
    names = {}
    for t, df in views.items():
        names[t] = f"bitgraph_{t}_{abs(hash(tuple(df.inputFiles()[:1])))}"
        df.createOrReplaceTempView(names[t])
    return spark.sql(_fill(text, names))


def clean(triples: DataFrame) -> DataFrame:
    """Distinct facts without nulls."""
    return triples.where("s IS NOT NULL AND p IS NOT NULL AND o IS NOT NULL").dropDuplicates(["s", "p", "o"])


def triples(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "similar":
        return clean(raw_triples(spark, sf_dir, name).unionByName(nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))))
    return clean(raw_triples(spark, sf_dir, name))


def nearest(vectors: DataFrame, m: int = 5, blocks: int = 16) -> DataFrame:
    """(s, 'near', o): each vector's m nearest others by cosine, ties by id.

    Vectors meet in blocks of queries against all rows; each block keeps its best m, and only those are ranked.
    """
    import numpy as np

    rows = vectors.select("vec_id", "embedding")
    queries = rows.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).groupBy("b").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("q"))
    parts = rows.withColumn("c", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).groupBy("c").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("d"))

    def best(it):
        import pyarrow as pa

        def matrix(col):
            ids = np.array([x["vec_id"] for x in col])
            v = np.array([x["embedding"] for x in col], float)
            return ids, v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)

        for batch in it:
            for q, d in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                (qi, qv), (di, dv) = matrix(q), matrix(d)
                sim = np.round(qv @ dv.T, 6)
                sim[qi[:, None] == di[None, :]] = -9
                order = np.lexsort((np.broadcast_to(di, sim.shape), -sim))[:, :m]
                a = np.repeat(qi, order.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(di[order].ravel()), pa.array(np.take_along_axis(sim, order, 1).ravel())], names=["a", "b", "sim"])

    pairs = queries.join(parts).select("q", "d").mapInArrow(best, "a bigint, b bigint, sim double").where("sim > -9")
    top = pairs.groupBy("a").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("sim")).alias("d"), "b"))), 1, m).alias("n"))
    return top.select(F.concat(F.lit("vec/"), "a").alias("s"), F.lit("near").alias("p"), F.explode(F.transform("n", lambda x: F.concat(F.lit("vec/"), x["b"]))).alias("o"))
