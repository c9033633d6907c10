"""Ways into an index from SQL: views, a table function, functions on cells, and a data source with filter pushdown."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition
from pyspark.sql.functions import pandas_udf, udtf

from bitgraph.functions.bits import BLOCK, Bits, Codes
from bitgraph.operators import dictionary
from bitgraph.operators.graph import Graph
from bitgraph.operators.tiles import PAYLOAD, TreeIndex, _walk_bindings, from_row


def register_views(graph: Graph, prefix: str) -> None:
    """Views of the facts, their IDs, the dictionary and the tiles."""
    for name, df in (("triples", graph.triples), ("ids", graph.ids), ("terms", graph.terms), ("predicates", graph.predicates), ("tiles", graph.index().tiles)):
        df.createOrReplaceTempView(f"{prefix}_{name}")


@udtf(returnType="s_id bigint, p_id bigint, o_id bigint")
class WalkTile:
    """Facts of one tile (a struct of its columns) with a subject and an object, null for any."""

    def eval(self, tile, s, o):
        x = tile.asDict(recursive=True)
        one = lambda v: None if v is None else np.array([v])
        r, c = _walk_bindings(from_row(x), x, one(s), one(o))
        for a, b in zip((r + x["row0"] + 1).tolist(), (c + x["col0"] + 1).tolist(), strict=True):
            yield a, x["p_id"], b


# Types are objects here: a type in words needs a session when the module is imported.
_STATS = T.StructType([T.StructField(c, T.LongType()) for c in ("n_points", "n_t", "n_leaves", "height", "n_bits")])
_PLANE = T.StructType([T.StructField(c, T.BinaryType()) for c in ("chunks", "more", "rank")])
_DAC = T.StructType([T.StructField("planes", T.ArrayType(_PLANE)), T.StructField("chunk", T.IntegerType())])


@pandas_udf(_STATS)
def tree_stats(tile: pd.DataFrame) -> pd.DataFrame:
    """Counts of a tile's tree (a struct of its columns); points are those that a walk finds."""
    out = []
    for x in tile.to_dict("records"):
        tree = from_row(x | {"factors": [int(k) for k in x["factors"]]})
        side = tree.schedule.side - 1
        _, r, _, _ = tree.ranges(*np.array([[0], [side], [0], [side]], np.int64))
        out.append((len(r), int(tree.starts[-1]), tree.n_leaves, len(tree.schedule.bits), tree.n_bits()))
    return pd.DataFrame(out, columns=["n_points", "n_t", "n_leaves", "height", "n_bits"])


def _starts(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def _short_codes(lists: list[np.ndarray], b: int) -> list[list[dict]]:
    """Planes of each list as ``Codes.encode`` makes them, for all lists at once; a list fits a block of the directory."""
    out: list[list[dict]] = [[] for _ in lists]
    owner = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
    left = np.concatenate(lists) if lists else np.zeros(0, np.int64)
    while len(left):
        more, n = left >> b > 0, np.bincount(owner, minlength=len(lists))
        at, per = np.arange(len(left)) - _starts(n)[owner], max(1, 8 // b)
        size, n_words = (2 * n if b == 16 else -(-n // per)), -(-n // 64)
        if b == 16:
            raw = (left & 0xFFFF).astype("<u2").tobytes()
        else:
            chunks = np.zeros(size.sum(), np.uint8)
            np.bitwise_or.at(chunks, _starts(size)[owner] + at // per, ((left & ((1 << b) - 1)) << (at % per * b)).astype(np.uint8))
            raw = chunks.tobytes()
        words = np.zeros(n_words.sum(), "<u8")
        np.bitwise_or.at(words, (_starts(n_words)[owner] + at // 64)[more], np.uint64(1) << (at[more] & 63).astype(np.uint64))
        bitmap, c, w = words.tobytes(), _starts(size).tolist(), (8 * _starts(n_words)).tolist()
        for i in np.flatnonzero(n).tolist():
            out[i].append({"chunks": raw[c[i] : c[i] + int(size[i])], "more": bitmap[w[i] : w[i] + 8 * int(n_words[i])], "rank": bytes(4)})
        left, owner = left[more] >> b, owner[more]
    return out


def _short_get(planes: list, b: int, at: np.ndarray) -> np.ndarray:
    """The at-th number of each of the codes, one plane of all codes after the other."""
    out, open_, level, per = np.zeros(len(at), np.int64), np.flatnonzero([len(p) > 0 for p in planes]), 0, max(1, 8 // b)
    at = at[open_]
    while len(open_):
        here = [planes[k][level] for k in open_]
        raw, words = np.frombuffer(b"".join(p["chunks"] for p in here), np.uint8), np.frombuffer(b"".join(p["more"] for p in here), "<u8")
        c, w = _starts(np.array([len(p["chunks"]) for p in here])), _starts(np.array([len(p["more"]) // 8 for p in here]))
        if b == 16:
            digit = raw.view("<u2")[c // 2 + at].astype(np.int64)
        else:
            digit = (raw[c + at // per].astype(np.int64) >> (at % per * b)) & ((1 << b) - 1)
        out[open_] |= digit << (b * level)
        before = np.concatenate(([0], np.cumsum(np.bitwise_count(words), dtype=np.int64)))
        word, bit = words[w + (at >> 6)], (at & 63).astype(np.uint64)
        on = ((word >> bit) & np.uint64(1)).astype(bool)
        rank = before[w + (at >> 6)] - before[w] + np.bitwise_count(word & ((np.uint64(1) << bit) - np.uint64(1)))
        open_, at, level = open_[on], rank[on], level + 1
    return out


def dac_encode(chunk: int = 8):
    """A function of an array of numbers of 0 and more to directly addressable codes."""
    @pandas_udf(_DAC)
    def encode(numbers: pd.Series) -> pd.DataFrame:
        def coded(x: np.ndarray) -> list[dict]:
            return [{"chunks": c.tobytes(), "more": m.words.tobytes(), "rank": m.directory.tobytes()} for c, m in Codes.encode(x, chunk).planes]

        lists = [np.asarray(x, np.int64) for x in numbers]
        short = [i for i, x in enumerate(lists) if len(x) <= BLOCK]
        planes = [None if len(x) <= BLOCK else coded(x) for x in lists]
        for i, x in zip(short, _short_codes([lists[i] for i in short], chunk), strict=True):
            planes[i] = x
        return pd.DataFrame({"planes": planes, "chunk": [chunk] * len(planes)})

    return encode


@pandas_udf(T.LongType())
def dac_get(codes: pd.DataFrame, i: pd.Series) -> pd.Series:
    """The i-th number of directly addressable codes, from 0, by one access in each plane that it reaches."""
    bits = lambda p: Bits(np.frombuffer(p["more"], "<u8"), np.frombuffer(p["rank"], "<u4"))
    one = lambda planes, b, at: int(Codes(b, [(np.frombuffer(p["chunks"], np.uint8), bits(p)) for p in planes]).get(np.array([at]))[0])
    short = np.array([len(p) == 0 or 8 * len(p[0]["more"]) <= BLOCK for p in codes["planes"]], bool)
    out = np.zeros(len(i), np.int64)
    for k in np.flatnonzero(~short):
        out[k] = one(codes["planes"].iloc[k], int(codes["chunk"].iloc[k]), int(i.iloc[k]))
    for b in np.unique(codes["chunk"][short]):
        mine = np.flatnonzero(short & (codes["chunk"].to_numpy() == b))
        out[mine] = _short_get([codes["planes"].iloc[k] for k in mine], int(b), i.to_numpy(np.int64)[mine])
    return pd.Series(out, dtype="int64")


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("walk_tile", WalkTile)
    spark.udf.register("tree_stats", tree_stats)
    spark.udf.register("dac_get", dac_get)


def export_graph(graph: Graph, path: str) -> None:
    """All that a reader needs: header, tiles, and the dictionary in the order of its terms."""
    graph.index().write(path)
    graph.terms.repartitionByRange("role", "term").sortWithinPartitions("role", "term").write.mode("overwrite").parquet(f"{path}/terms")
    graph.predicates.coalesce(1).write.mode("overwrite").parquet(f"{path}/predicates")
    c = graph.counts
    graph.spark.createDataFrame([(graph.name, c["n_so"], c["n_s"], c["n_o"])], "name string, n_so bigint, n_s bigint, n_o bigint").coalesce(1).write.mode("overwrite").parquet(f"{path}/counts")


def import_graph(spark: SparkSession, path: str) -> Graph:
    """A graph that export_graph wrote; facts are read from the tiles, no dictionary is built."""
    x = spark.read.parquet(f"{path}/counts").first()
    index, terms, preds = TreeIndex.open(spark, path), spark.read.parquet(f"{path}/terms"), spark.read.parquet(f"{path}/predicates")
    facts = dictionary.decode(index.match(), terms, preds, {"s_id": "s", "p_id": "p", "o_id": "o"})
    graph = Graph(spark, facts.select(F.col("s_id").alias("s"), F.col("p_id").alias("p"), F.col("o_id").alias("o")), x["name"])
    graph.adopt(terms, preds, {k: x[k] for k in ("n_so", "n_s", "n_o")}, index)
    return graph


def triples_match(graph: Graph, s: int | None, p: int | None, o: int | None) -> DataFrame:
    """A pattern in SQL by the table function."""
    register_functions(graph.spark)
    show = lambda v: "CAST(NULL AS BIGINT)" if v is None else f"CAST({int(v)} AS BIGINT)"
    fields = ", ".join(("p_id", "row0", "col0", *PAYLOAD))
    return graph.spark.sql(f"SELECT f.* FROM {{tiles}} t, LATERAL walk_tile(struct({fields}), {show(s)}, {show(o)}) f", tiles=graph.index()._select(s, p, o))


class _Files(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class TileReader(DataSourceReader):
    """Reads tile files; equality and IN on p_id, s_id and o_id are answered by the trees."""

    def __init__(self, path: str):
        self.path, self.bound = path, {}

    def pushFilters(self, filters):
        for f in filters:
            values = [f.value] if isinstance(f, EqualTo) else list(f.value) if isinstance(f, In) else None
            if values is not None and f.attribute in (("s_id",), ("p_id",), ("o_id",)) and f.attribute[0] not in self.bound:
                self.bound[f.attribute[0]] = sorted(set(values))
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
        return [_Files(x.path) for x in system.get_file_info(fs.FileSelector(root)) if x.path.endswith(".parquet")]

    def read(self, partition):
        import pyarrow.parquet as pq

        for batch in pq.ParquetFile(partition.value).iter_batches(batch_size=64):
            for x in batch.to_pylist():
                if "p_id" in self.bound and x["p_id"] not in self.bound["p_id"]:
                    continue
                s, o = (np.array(self.bound[k]) if k in self.bound else None for k in ("s_id", "o_id"))
                if s is not None and o is not None:
                    s, o = np.repeat(s, len(o)), np.tile(o, len(s))
                r, c = _walk_bindings(from_row(x), x, s, o)
                if len(r):
                    yield pa.RecordBatch.from_arrays([pa.array(r + x["row0"] + 1), pa.array(np.full(len(r), x["p_id"])), pa.array(c + x["col0"] + 1)], names=["s_id", "p_id", "o_id"])


class TileGraph(DataSource):
    """``spark.read.format("tilegraph").load(path)`` over the tiles that TreeIndex.write left there."""

    @classmethod
    def name(cls):
        return "tilegraph"

    def schema(self):
        return "s_id bigint, p_id bigint, o_id bigint"

    def reader(self, schema):
        return TileReader(self.options["path"].rstrip("/") + "/tiles")


def register_source(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TileGraph)


def write_ntriples(triples: DataFrame, path: str) -> None:
    """A fact a line, tab separated, with tabs, line ends and backslashes escaped."""
    safe = lambda c: F.replace(F.replace(F.replace(F.col(c), F.lit("\\"), F.lit("\\\\")), F.lit("\t"), F.lit("\\t")), F.lit("\n"), F.lit("\\n"))
    triples.select(F.concat_ws("\t", safe("s"), safe("p"), safe("o"), F.lit(".")).alias("value")).write.mode("overwrite").text(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    part = F.split("value", "\t")
    plain = lambda i: F.replace(F.replace(F.replace(F.replace(part[i], F.lit("\\\\"), F.lit("\x00")), F.lit("\\t"), F.lit("\t")), F.lit("\\n"), F.lit("\n")), F.lit("\x00"), F.lit("\\"))
    return spark.read.text(path).select(plain(0).alias("s"), plain(1).alias("p"), plain(2).alias("o"))


def open_index(spark: SparkSession, path: str) -> TreeIndex:
    return TreeIndex.open(spark, path)
