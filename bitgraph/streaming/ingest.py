"""Events as a stream: facts into a delta, windows of counts, joins with the index and with themselves, degrees."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitgraph.store import Scratch

LATE = "2 days"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, ts as an instant."""
    path = f"{sf_dir}/events.parquet"
    stream = spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{sf_dir}/events.parque[t]")  # a pattern, as a stream takes a plain path for a folder
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, scratch: Scratch, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None, progress: list | None = None) -> DataFrame:
    """What a stream gives until its input is used up.

    Each micro-batch overwrites a folder named by its id, so that a batch that runs twice counts once. In complete mode
    the last folder is the answer, else all are. ``progress`` takes the reports of the micro-batches.
    """
    scratch.n += 1
    root = f"{scratch.root}/stream{scratch.n}"
    last = _run(stream, root, mode, each, progress)
    path = f"{root}/out/batch={last}" if mode == "complete" else f"{root}/out"
    return stream.sparkSession.read.parquet(path).drop("batch")


def _run(stream: DataFrame, root: str, mode: str, each: Callable[[DataFrame], DataFrame] | None, progress: list | None) -> int:
    """Runs a stream until its input is used up; the id of the last micro-batch."""
    last = [-1]

    def write(df: DataFrame, batch: int) -> None:
        (each(df) if each else df).write.mode("overwrite").parquet(f"{root}/out/batch={batch}")
        last.append(batch)

    run = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{root}/checkpoint").foreachBatch(write).start()
    run.awaitTermination()
    if progress is not None:
        progress.extend(run.recentProgress)
    return max(last)


def facts(stream: DataFrame) -> DataFrame:
    """The activity graph's facts of events, each once within the watermark."""
    item = F.concat(F.lit("item/"), F.get_json_object("props", "$.k"))
    event, user = F.concat(F.lit("event/"), "event_id"), F.concat(F.lit("user/"), "user_id")
    hour = F.concat(F.lit('"'), F.date_format("ts", "yyyy-MM-dd'T'HH"), F.lit('"'))
    one = lambda s, p, o: F.struct(s.alias("s"), p.alias("p"), o.alias("o"))
    rows = F.array(one(user, F.col("event_type"), item), one(event, F.lit("by"), user), one(event, F.lit("about"), item), one(event, F.lit("kind"), F.concat(F.lit('"'), "event_type", F.lit('"'))), one(event, F.lit("hour"), hour))
    return stream.withWatermark("ts", LATE).select("ts", F.explode(rows).alias("t")).select("ts", "t.*").dropDuplicatesWithinWatermark(["s", "p", "o"]).select("s", "p", "o")


def counts(stream: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", LATE).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    w = F.session_window("ts", gap)
    return stream.withWatermark("ts", LATE).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def pairs(stream: DataFrame, minutes: int) -> DataFrame:
    """Pairs of a user's events, a click after a view within so many minutes: a stream-stream interval join."""
    side = lambda kind, name: stream.where(F.col("event_type") == kind).select(F.col("event_id").alias(name), F.col("user_id").alias(f"{name}_user"), F.col("ts").alias(f"{name}_ts")).withWatermark(f"{name}_ts", LATE)
    a, b = side("view", "a"), side("click", "b")
    near = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {minutes} MINUTES"))
    return a.join(b, near).select("a", "b")


def degrees(stream: DataFrame) -> DataFrame:
    """Events of each user so far, by state kept in Python."""
    import pandas as pd

    def add(key, batches, state):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    return stream.groupBy("user_id").applyInPandasWithState(add, "user_id bigint, n bigint", "n bigint", "update", "NoTimeout")


def replay(spark: SparkSession, sf_dir: str, of: Callable[[DataFrame], DataFrame], scratch: Scratch, progress: list | None = None) -> DataFrame:
    """What ``of`` gives in append mode for events that arrive in three parts: the later half, its last instant, then the
    earlier half, which is late. Each part is one run of the stream, however many files it has; the next run goes on from
    the checkpoint, as after a restart."""
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    at = F.col("ts").cast("timestamp").cast("double")
    low, high = table.agg(F.min(at), F.max(at)).first()
    if low is None:
        low = high = 0.0
    scratch.n += 1
    root = f"{scratch.root}/replay{scratch.n}"
    later = at >= (low + high) / 2
    for i, part in enumerate((later & (at < high), later & (at == high), ~later)):
        table.where(part).write.parquet(f"{root}/in/part={i}")
        stream = spark.readStream.schema(table.schema).option("recursiveFileLookup", "true").parquet(f"{root}/in")
        _run(of(stream.withColumn("ts", F.col("ts").cast("timestamp"))), root, "append", None, progress)
    return spark.read.parquet(f"{root}/out").drop("batch")


def dropped(progress: list) -> int:
    """Rows that the watermark shut out, over all micro-batches; rows folded before the state count as one."""
    return sum(op.numRowsDroppedByWatermark for p in progress for op in p.stateOperators)
