"""Distributed k2-tree index: matrices cut into tiles, one compressed tree a row.

The upper levels of every predicate's tree are the directory of its tiles: an absent tile is a zero. Tiles with more
points than a task should hold are cut again. Trees are built and walked in Arrow batches on the executors; the driver
sees counts only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bitgraph.functions.bits import Bits, Codes
from bitgraph.functions.geometry import Schedule, cell_code
from bitgraph.operators.tree import Tree, codes_of, distinct
from bitgraph.store import Scratch

TILE_BITS = 16
MAX_POINTS = 1 << 20
#: Points of a predicate whose matrix is one tile, however wide: with thousands of predicates, tiles of one side for all
#: would hold a few points each.
WHOLE = 1 << 18
#: Rows of a batch that a walk gives out, and tiles of which it holds the payload.
OUT, HELD = 1 << 16, 64
#: Bindings that are sent to every task; more are routed to the tiles by a join.
MOST_SENT = 200_000
#: Bindings that one call of a tile's kernel takes.
CHUNK = 20_000

_PLANES = pa.list_(pa.struct([("chunks", pa.binary()), ("more", pa.binary()), ("rank", pa.binary())]))
SCHEMA = pa.schema([
    ("p_id", pa.int64()), ("row0", pa.int64()), ("col0", pa.int64()), ("n_points", pa.int64()), ("n_bits", pa.int64()), ("n_t", pa.int64()), ("n_l", pa.int64()), ("leaf", pa.string()), ("factors", pa.list_(pa.int32())), ("starts", pa.list_(pa.int64())),
    ("t_bits", pa.binary()), ("t_rank", pa.binary()), ("leaf_bits", pa.binary()), ("vocabulary", pa.binary()), ("planes", _PLANES), ("chunk", pa.int32()), ("row_min", pa.int64()), ("row_max", pa.int64()), ("col_min", pa.int64()), ("col_max", pa.int64()),
])
SPARK_SCHEMA = """p_id bigint, row0 bigint, col0 bigint, n_points bigint, n_bits bigint, n_t bigint, n_l bigint, leaf string, factors array<int>, starts array<bigint>, t_bits binary, t_rank binary,
leaf_bits binary, vocabulary binary, planes array<struct<chunks:binary,more:binary,rank:binary>>, chunk int, row_min bigint, row_max bigint, col_min bigint, col_max bigint"""
PAYLOAD = ("factors", "starts", "t_bits", "t_rank", "leaf_bits", "vocabulary", "planes", "chunk", "n_points")


def to_row(tree: Tree, p_id: int, row0: int, col0: int, rows: np.ndarray, cols: np.ndarray, chunk: int) -> dict:
    planes = None
    if tree.leaf_codes is not None:
        planes = [{"chunks": c.tobytes(), "more": m.words.tobytes(), "rank": m.directory.tobytes()} for c, m in tree.leaf_codes.planes]
    n_l = tree.n_leaves << (2 * sum(tree.leaf_levels)) if tree.leaf_bits is not None else tree.leaf_codes.n_bits(tree.n_leaves) + 64 * len(tree.vocabulary)
    return {
        "p_id": p_id, "row0": row0, "col0": col0, "n_points": tree.n_points, "n_bits": tree.n_bits(), "n_t": int(tree.starts[-1]), "n_l": n_l, "leaf": "plain" if planes is None else "vocab8",
        "factors": list(tree.schedule.factors), "starts": tree.starts.tolist(), "t_bits": tree.t.words.tobytes(), "t_rank": tree.t.directory.tobytes(),
        "leaf_bits": None if tree.leaf_bits is None else tree.leaf_bits.tobytes(), "vocabulary": None if tree.vocabulary is None else tree.vocabulary.astype("<u8").tobytes(), "planes": planes, "chunk": chunk,
        "row_min": row0 + int(rows.min()), "row_max": row0 + int(rows.max()), "col_min": col0 + int(cols.min()), "col_max": col0 + int(cols.max()),
    }


def from_row(x: dict) -> Tree:
    bits = lambda words, rank: Bits(np.frombuffer(words, "<u8"), np.frombuffer(rank, "<u4"))
    schedule = Schedule(tuple(x["factors"]))
    starts = np.array(x["starts"], np.int64)
    codes = None if x["planes"] is None else Codes(x["chunk"], [(np.frombuffer(p["chunks"], np.uint8), bits(p["more"], p["rank"])) for p in x["planes"]])
    return Tree(
        schedule, schedule.bits[: len(starts) - 1], starts, bits(x["t_bits"], x["t_rank"]), x["n_points"],
        leaf_bits=None if x["leaf_bits"] is None else np.frombuffer(x["leaf_bits"], "<u8"), vocabulary=None if x["vocabulary"] is None else np.frombuffer(x["vocabulary"], "<u8"), leaf_codes=codes,
    )


def _packer(by_side: dict[int, list[Schedule]], leaf: str, chunk: int):
    """Batches of (p_id, row0, col0, bits, r, c), tiles one after the other, to tile rows."""
    def pack(key: tuple[int, int, int, int], r: np.ndarray, c: np.ndarray) -> dict:
        p, row0, col0, bits = key
        best = None
        for s in by_side[bits]:
            tree = Tree.build(distinct(codes_of(r, c, s)), s, leaf, chunk)
            best = tree if best is None or tree.n_bits() < best.n_bits() else best
        return to_row(best, p, row0, col0, r, c, chunk)

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_key, rows, cols, done = None, [], [], []

        def close():
            if open_key is not None:
                done.append(pack(open_key, np.concatenate(rows), np.concatenate(cols)))

        for batch in it:
            keys = np.stack([batch.column(i).to_numpy() for i in range(4)], axis=1)
            r, c = batch.column(4).to_numpy(), batch.column(5).to_numpy()
            cuts = np.flatnonzero(np.any(keys[1:] != keys[:-1], axis=1)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(keys)], strict=True):
                key = tuple(map(int, keys[a]))
                if key != open_key:
                    close()
                    open_key, rows, cols = key, [], []
                rows.append(r[a:b])
                cols.append(c[a:b])
            if sum(x["n_bits"] for x in done) > 1 << 26 or len(done) > 2000:
                yield pa.RecordBatch.from_pylist(done, SCHEMA)
                done = []
        close()
        if done:
            yield pa.RecordBatch.from_pylist(done, SCHEMA)

    return batches


def _ending(schedules: list[Schedule], most: int) -> tuple[int, list[Schedule]]:
    """The longest ends of the schedules that divide a side of at most 2 ** ``most``, as (bits, schedules); 0 if there are none.

    A tile that is cut by the end of its schedule has the lower levels of the tree that it is cut from.
    """
    ends = [Schedule(s.factors[i:]) for s in schedules for i in range(len(s.factors))]
    bits = max((sum(e.bits) for e in ends if sum(e.bits) <= most), default=0)
    return bits, [e for e in ends if sum(e.bits) == bits]


def _cut(placed: DataFrame, over: DataFrame, on: str, small: int) -> DataFrame:
    """``placed`` with the points that ``over`` names dealt to tiles of ``small`` bits."""
    joined = placed.join(F.broadcast(over.withColumn("cut", F.lit(True))), F.expr(on), "left")
    narrow = lambda c: F.when(F.col("cut"), F.shiftleft(F.shiftright(c, small), small)).otherwise(F.col(f"{c}0"))
    return joined.select("p_id", "row", "col", narrow("row").alias("row0"), narrow("col").alias("col0"), F.when(F.col("cut"), F.lit(small)).otherwise(F.col("bits")).alias("bits"))


def _points(ids: DataFrame) -> DataFrame:
    return ids.select("p_id", (F.col("s_id") - 1).alias("row"), (F.col("o_id") - 1).alias("col"))


def _placed(points: DataFrame, bits: int) -> DataFrame:
    return points.withColumns({"row0": F.shiftleft(F.shiftright("row", bits), bits), "col0": F.shiftleft(F.shiftright("col", bits), bits), "bits": F.lit(bits)})


def directory_of(ids: DataFrame, tile_bits: int) -> DataFrame:
    """What ``TreeIndex.directory`` tells of tiles of one side, from the facts: no tree is built."""
    ends = [f(c).alias(f"{c}_{n}") for c in ("row", "col") for n, f in (("min", F.min), ("max", F.max))]
    return _placed(_points(ids), tile_bits).groupBy("p_id", "row0", "col0").agg(F.count("*").alias("n_points"), *ends)


@dataclass
class TreeIndex:
    """``tiles`` with a tree a row; ``bits`` is log2 of the largest tile's side, ``n_so`` the shared IDs.

    ``whole`` is the schedule of whole matrices where all tiles have its levels or the ends of them.
    """

    tiles: DataFrame
    bits: int
    dim: int
    n_so: int
    name: str = "tree"
    whole: Schedule | None = None

    @classmethod
    def build(cls, ids: DataFrame, dim: int, n_so: int, scratch: Scratch, schedule: str = "hybrid", leaf: str = "auto", tile_bits: int | None = None, max_points: int = MAX_POINTS, chunk: int = 8) -> TreeIndex:
        """From distinct (s_id, p_id, o_id). ``schedule``: k2, k4, hybrid, or auto for the smaller of k2 and hybrid in each tile.

        Without ``tile_bits`` a predicate is one tile up to ``WHOLE`` points, and cut to tiles of ``TILE_BITS`` beyond.
        """
        names = ["k2", "hybrid"] if schedule == "auto" else [schedule]
        cut = dim if tile_bits is None else min([dim, 1 << tile_bits])
        whole = [Schedule.named(n, cut) for n in names]
        bits = max(sum(s.bits) for s in whole)
        whole = [s for s in whole if sum(s.bits) == bits]
        by_side = {bits: whole}
        placed, now = _placed(_points(ids), bits), bits
        if tile_bits is None and bits > TILE_BITS:
            small, ends = _ending(whole, TILE_BITS)
            large = ids.groupBy(F.col("p_id").alias("op")).agg(F.count("*").alias("n")).where(F.col("n") > min(WHOLE, max_points)).drop("n")  # one row for that many points
            placed, now, by_side[small] = _cut(placed, large, "p_id = op", small), small, ends
        while now > 4 and (over := placed.where(F.col("bits") == now).groupBy("p_id", "row0", "col0").agg(F.count("*").alias("n")).where(F.col("n") > max_points)).limit(1).count():
            small, ends = _ending(whole, now - 2)
            if not small:
                break
            over = over.select(F.col("p_id").alias("op"), F.col("row0").alias("r0"), F.col("col0").alias("c0"), F.lit(now).alias("ob"))  # one row for max_points points
            placed, now, by_side[small] = _cut(placed, over, "p_id = op AND row0 = r0 AND col0 = c0 AND bits = ob", small), small, ends
        dealt = placed.repartition("p_id", "row0", "col0").sortWithinPartitions("p_id", "row0", "col0")
        local = dealt.select("p_id", "row0", "col0", F.col("bits").cast("bigint"), (F.col("row") - F.col("row0")).alias("r"), (F.col("col") - F.col("col0")).alias("c"))
        tiles = local.mapInArrow(_packer(by_side, leaf, chunk), SPARK_SCHEMA)
        return cls(scratch.keep(tiles), bits, dim, n_so, whole=whole[0] if cut == dim and len(names) == 1 else None)

    def level_bits(self) -> DataFrame:
        """(level, n_bits) of the trees of whole matrices, the last level's bits from plain leaves.

        Levels of a tile that was cut off are the lower ones of its matrix; the nodes above it are counted from its place.
        """
        if self.whole is None:
            raise ValueError("the tiles are not those of whole matrices of one schedule")
        s = self.whole
        above = F.lit(len(s.factors)) - F.size("factors")
        ends = F.zip_with(F.slice("starts", 2, F.size("starts") - 1), F.slice("starts", 1, F.size("starts") - 1), lambda b, a: b - a)
        own = self.tiles.select(above.alias("above"), F.posexplode(F.concat(ends, F.array("n_l"))).alias("at", "n_bits")).select((F.col("above") + F.col("at")).alias("level"), "n_bits")
        side = F.array(*[F.lit(sum(s.bits[i:])) for i in range(len(s.bits))])  # log2 of a node's side
        cells = F.array(*[F.lit(k * k).cast("bigint") for k in s.factors])
        nodes = self.tiles.select("p_id", "row0", "col0", F.explode(F.expr(f"slice(sequence(0, {len(s.factors)}), 1, {len(s.factors)} - size(factors))")).alias("level"))
        nodes = nodes.select("p_id", "level", F.call_function("shiftright", "row0", F.get(side, "level")).alias("r"), F.call_function("shiftright", "col0", F.get(side, "level")).alias("c")).distinct()
        return own.union(nodes.select("level", F.get(cells, "level").alias("n_bits"))).groupBy(F.col("level").cast("bigint").alias("level")).agg(F.sum("n_bits").alias("n_bits"))

    def write(self, path: str) -> None:
        """Tiles in Z-order of their place within a predicate, so that rows and columns of tiles both lie close together."""
        b = min(self.bits, TILE_BITS)
        z = cell_code(F.shiftright("row0", b), F.shiftright("col0", b), Schedule.uniform(2, max(2, -(-self.dim >> b) + 1)))
        self.tiles.repartitionByRange("p_id", z).sortWithinPartitions("p_id", z).write.mode("overwrite").parquet(f"{path}/tiles")
        self._write_header(path)

    def bundles(self, target: int) -> DataFrame:
        """(p_id, n_points, bundle): neighbouring predicates that share a bundle of some ``target`` points.

        The running sum is over one row a predicate, so the one task of its window holds no facts.
        """
        sums = self.tiles.groupBy("p_id").agg(F.sum("n_points").alias("n_points"))
        before = F.sum("n_points").over(Window.orderBy("p_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("n_points")
        return sums.withColumn("bundle", F.floor(before / F.lit(target)).cast("bigint"))

    def write_bundled(self, path: str, target: int = MAX_POINTS) -> None:
        """Like ``write``, with the tiles of a bundle of predicates in the same files; large predicates are dealt by their rows of tiles."""
        size = self.bundles(target).select("p_id", "bundle", (F.col("n_points") > target).alias("large"))
        row = F.when(F.col("large"), F.col("row0")).otherwise(F.lit(0))
        dealt = self.tiles.join(size, "p_id").repartition("bundle", row).sortWithinPartitions("bundle", "p_id", "row0", "col0")
        dealt.drop("bundle", "large").write.mode("overwrite").parquet(f"{path}/tiles")
        self._write_header(path)

    def _write_header(self, path: str) -> None:
        self.tiles.sparkSession.createDataFrame([(self.bits, self.dim, self.n_so)], "bits int, dim bigint, n_so bigint").coalesce(1).write.mode("overwrite").parquet(f"{path}/header")

    @classmethod
    def open(cls, spark, path: str) -> TreeIndex:
        h = spark.read.parquet(f"{path}/header").first()
        return cls(spark.read.parquet(f"{path}/tiles"), h["bits"], h["dim"], h["n_so"])

    def directory(self) -> DataFrame:
        return self.tiles.select("p_id", "row0", "col0", "n_points", "n_bits", "n_t", "n_l", "leaf", "row_min", "row_max", "col_min", "col_max")

    def size_bits(self) -> int:
        return self.tiles.agg(F.coalesce(F.sum("n_bits"), F.lit(0))).first()[0]

    # Patterns ------------------------------------------------------------------------------------------------------------

    def _select(self, s=None, p=None, o=None) -> DataFrame:
        """Tiles that a pattern can touch: filters on plain columns, which Parquet statistics prune."""
        t = self.tiles
        for value, low, high in ((p, "p_id", "p_id"), (s and s - 1, "row_min", "row_max"), (o and o - 1, "col_min", "col_max")):
            if value is not None:
                t = t.where((F.col(low) <= value) & (F.col(high) >= value))
        return t

    def match(self, s: int | None = None, p: int | None = None, o: int | None = None) -> DataFrame:
        """(s_id, p_id, o_id) of one pattern; None is free. An ID out of the matrix matches nothing."""
        return self.range(s, s, p, o, o)

    def range(self, s1=None, s2=None, p=None, o1=None, o2=None) -> DataFrame:
        """Points with subjects in [s1, s2] and objects in [o1, o2]."""
        t = self._select(None, p)
        for low, high, a, b in (("row_min", "row_max", s1, s2), ("col_min", "col_max", o1, o2)):
            t = t.where(F.col(high) >= a - 1) if a is not None else t
            t = t.where(F.col(low) <= b - 1) if b is not None else t
        top = 1 << 62
        box = np.array([[(s1 or 1) - 1], [top if s2 is None else s2 - 1], [(o1 or 1) - 1], [top if o2 is None else o2 - 1]], np.int64)

        def walk(tree: Tree, x: dict) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            side, low = tree.schedule.side - 1, np.array([[x["row0"]], [x["row0"]], [x["col0"]], [x["col0"]]])
            for _, r, c, _ in tree.pieces(*np.clip(box - low, [[0], [-1], [0], [-1]], [[side + 1], [side], [side + 1], [side]])):
                yield r, c

        return self._run(t, walk)

    def diagonal(self, p: int | None = None) -> DataFrame:
        """Facts (x, p, x); x is a shared ID, which numbers the same term in both roles."""
        n_so = self.n_so

        def walk(tree: Tree, x: dict) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            d = tree.diagonal(max(0, n_so - x["row0"]))
            yield d, d

        return self._run(self._select(None, p).where((F.col("row0") == F.col("col0")) & (F.col("row_min") < n_so)), walk)

    @staticmethod
    def _run(tiles: DataFrame, walk) -> DataFrame:
        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            return _given_out((x, walk(from_row(x), x)) for x in _tile_rows(it))

        return tiles.select("p_id", "row0", "col0", *PAYLOAD).mapInArrow(batches, "s_id bigint, p_id bigint, o_id bigint")

    def match_batch(self, bindings: DataFrame, most_sent: int = MOST_SENT) -> DataFrame:
        """Distinct facts that agree with a row of ``bindings`` on its columns, some of s_id, p_id and o_id.

        Up to ``most_sent`` bindings go to all tasks; more are joined to the tiles that they can touch, in chunks.
        """
        bound = [c for c in ("s_id", "p_id", "o_id") if c in bindings.columns]
        bindings = bindings.select(*bound).dropDuplicates()
        if not bound:
            return self.match() if bindings.limit(1).count() else self.match().limit(0)
        few = bindings.limit(most_sent + 1).toArrow()
        if few.num_rows <= most_sent:
            return self._match_few(few, bound)
        return self._match_many(bindings, bound)

    def _match_few(self, few: pa.Table, bound: list[str]) -> DataFrame:
        sent = {c: few.column(c).to_numpy() for c in bound}
        t = self.tiles
        if "p_id" in bound:
            order = np.argsort(sent["p_id"], kind="stable")
            sent = {c: v[order] for c, v in sent.items()}
            if len(preds := np.unique(sent["p_id"])) <= 1000:
                t = t.where(F.col("p_id").isin(preds.tolist()))
        for c, low, high in (("s_id", "row_min", "row_max"), ("o_id", "col_min", "col_max")):
            if c in bound and len(sent[c]):
                t = t.where((F.col(high) >= int(sent[c].min()) - 1) & (F.col(low) <= int(sent[c].max()) - 1))
        shared = t.sparkSession.sparkContext.broadcast(sent)

        def walk(tree: Tree, x: dict) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            v = shared.value
            if "p_id" in v:
                a, b = np.searchsorted(v["p_id"], [x["p_id"], x["p_id"] + 1])
                v = {c: y[a:b] for c, y in v.items()}
                if a == b:
                    return
            yield from _walk_pieces(tree, x, v.get("s_id"), v.get("o_id"))

        return self._run(t, walk)

    def _match_many(self, bindings: DataFrame, bound: list[str]) -> DataFrame:
        base = {c: axis for c, axis in {"s_id": "row", "o_id": "col"}.items() if c in bound}
        routed, log_side = None, F.aggregate("factors", F.lit(0), lambda a, k: a + F.log2(k.cast("double")).cast("int"))
        # Tiles of each side by their own band of rows or columns; there are few sides.
        for side in [r[0] for r in self.tiles.select(log_side).distinct().collect()] if base else [self.bits]:
            tiles = self.tiles.where(log_side == side) if base else self.tiles
            keyed, on = bindings, [c for c in bound if c == "p_id"]
            for c, axis in base.items():
                keyed = keyed.withColumn(f"b_{axis}", F.shiftright(F.col(c) - 1, side))
                tiles = tiles.withColumn(f"b_{axis}", F.shiftright(f"{axis}0", side))
                on.append(f"b_{axis}")
            places = tiles.select("p_id", "row0", "col0", "row_min", "row_max", "col_min", "col_max", *[c for c in on if c != "p_id"])
            if places.limit(MOST_SENT + 1).count() <= MOST_SENT:
                places = F.broadcast(places)
            hit = F.lit(True)
            for c, axis in base.items():
                hit &= (F.col(c) - 1).between(F.col(f"{axis}_min"), F.col(f"{axis}_max"))
            here = keyed.join(places, on).where(hit).select("p_id", "row0", "col0", *[c for c in bound if c != "p_id"])
            routed = here if routed is None else routed.union(here)
        # A chunk number by hash bounds a group on average; a tile's points bound what its walks return.
        n = F.greatest(F.lit(1), F.ceil(F.count("*").over(_by("p_id", "row0", "col0")) / CHUNK))
        routed = routed.withColumn("part", F.pmod(F.xxhash64(*bound), n) if bound != ["p_id"] else F.lit(0))
        lists = routed.groupBy("p_id", "row0", "col0", "part").agg(F.count("*").alias("n_bindings"), *[F.collect_list(c).alias(f"{c}s") for c in bound if c != "p_id"])

        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            return _given_out((x, _walk_pieces(from_row(x), x, *[np.array(x[f"{c}s"], np.int64) if f"{c}s" in x else None for c in ("s_id", "o_id")])) for x in _tile_rows(it))

        return lists.join(self.tiles.select("p_id", "row0", "col0", *PAYLOAD), ["p_id", "row0", "col0"]).mapInArrow(batches, "s_id bigint, p_id bigint, o_id bigint")

    def work(self, s=None, p=None, o=None) -> DataFrame:
        """(tiles, bits_looked_at, points) of a pattern: what explains its time."""
        box = np.array([[(s or 1) - 1], [1 << 62 if s is None else s - 1], [(o or 1) - 1], [1 << 62 if o is None else o - 1]], np.int64)

        def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in it:
                for x in batch.to_pylist():
                    tree = from_row(x)
                    side, low = tree.schedule.side - 1, np.array([[x["row0"]], [x["row0"]], [x["col0"]], [x["col0"]]])
                    r, _, _, looked = tree.ranges(*np.clip(box - low, [[0], [-1], [0], [-1]], [[side + 1], [side], [side + 1], [side]]))
                    yield pa.RecordBatch.from_arrays([pa.array([1]), pa.array([looked]), pa.array([len(r)])], names=["tiles", "bits_looked_at", "points"])

        rows = self._select(s, p, o).select("p_id", "row0", "col0", *PAYLOAD).mapInArrow(batches, "tiles bigint, bits_looked_at bigint, points bigint")
        return rows.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in rows.columns])


def _by(*cols: str):
    from pyspark.sql import Window

    return Window.partitionBy(*cols)


def _tile_rows(it: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for batch in it:
        for k in range(0, batch.num_rows, HELD):
            yield from batch.slice(k, HELD).to_pylist()


def _given_out(found: Iterator[tuple[dict, Iterator[tuple[np.ndarray, np.ndarray]]]]) -> Iterator[pa.RecordBatch]:
    """Facts of (tile, pieces of its points) in batches of some ``OUT`` rows, whatever a tile gives."""
    parts, n = [], 0

    def batch() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*parts, strict=True)], names=["s_id", "p_id", "o_id"])

    for x, pieces in found:
        for r, c in pieces:
            if len(r):
                parts.append((r + x["row0"] + 1, np.full(len(r), x["p_id"]), c + x["col0"] + 1))
                n += len(r)
            if n >= OUT:
                yield batch()
                parts, n = [], 0
    if parts:
        yield batch()


def _walk_pieces(tree: Tree, x: dict, s: np.ndarray | None, o: np.ndarray | None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Points of a tile that have one of the subjects, one of the objects, or one of the pairs."""
    side = tree.schedule.side
    inside = np.ones(len(s if s is not None else o if o is not None else [0]), bool)
    ends = []
    for ids, low in ((s, x["row0"]), (o, x["col0"])):
        if ids is None:
            ends.append(None)
            continue
        at = ids - 1 - low
        inside &= (at >= 0) & (at < side)
        ends.append(at)
    at = np.flatnonzero(inside)
    if len(at) > tree.n_points:  # reading the tile once and looking its points up is cheaper than a walk for each binding
        wanted = np.unique(sum(e[at] * k for e, k in zip(ends, (side, 1), strict=True) if e is not None))
        for _, r, c, _ in tree.pieces(*np.array([[0], [side - 1], [0], [side - 1]], np.int64)):
            key = sum(y * k for e, y, k in zip(ends, (r, c), (side, 1), strict=True) if e is not None)
            found = wanted[np.minimum(np.searchsorted(wanted, key), len(wanted) - 1)] == key
            yield r[found], c[found]
        return
    for k in range(0, len(at), CHUNK):
        part = at[k : k + CHUNK]
        free = np.zeros(len(part), np.int64)
        box = [y for e in ends for y in ((free, free + side - 1) if e is None else (e[part], e[part]))]
        for _, r, c, _ in tree.pieces(*box):
            yield r, c


def _walk_bindings(tree: Tree, x: dict, s: np.ndarray | None, o: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """``_walk_pieces`` at once."""
    none = np.zeros(0, np.int64)
    r, c = zip((none, none), *_walk_pieces(tree, x, s, o), strict=True)
    return np.concatenate(r), np.concatenate(c)
