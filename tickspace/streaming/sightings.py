"""Sightings as streams: windows, late rows, joins, and epochs driven by batches.

Every windowed function takes a static or a streaming DataFrame: the streaming
queries have batch twins of the same plan.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import runtime
from ..plans.agents import AgentClass
from ..sources.adapters import read, read_stream

LATE = "1 hour"
_BATCH = "batch"  #: folders of a drained stream's rows


def sightings(spark: SparkSession, sf_dir: str, stream: bool = False, files: int = 1) -> DataFrame:
    """events; the time of day becomes a TIMESTAMP, as watermarks need it."""
    raw = read_stream(spark, sf_dir, "events", files) if stream else read(spark, sf_dir, "events")
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


def _start(window: str):
    return F.col(f"{window}.start").cast("timestamp_ntz").alias("start")


def tumbling(rows: DataFrame, width: str = "1 hour", late: str = LATE) -> DataFrame:
    """(start, n) of windows that hold rows.  On a stream, a row later than the
    watermark is dropped (and counted in the query's progress)."""
    return rows.withWatermark("ts", late).groupBy(F.window("ts", width)).agg(F.count("*").alias("n")).select(_start("window"), "n")


def sliding(rows: DataFrame, width: str = "6 hours", slide: str = "1 hour", late: str = LATE) -> DataFrame:
    return rows.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n")).select(_start("window"), "n")


def sessions(rows: DataFrame, gap: str = "30 minutes", late: str = LATE) -> DataFrame:
    """(user_id, start, n): a user's rows less than ``gap`` apart."""
    return rows.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", _start("session_window"), "n")


def inflow(rows: DataFrame, late: str = LATE) -> DataFrame:
    """Arrivals by day and kind."""
    return rows.withWatermark("ts", late).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")).select(_start("window"), "event_type", "n")


def first_seen(rows: DataFrame, within: str = LATE) -> DataFrame:
    """Rows without those repeated under one event_id within the watermark."""
    return rows.withWatermark("ts", within).dropDuplicatesWithinWatermark(["event_id"])


def meetings(left: DataFrame, right: DataFrame, apart: str = "5 minutes", late: str = LATE) -> DataFrame:
    """(a_id, b_id) of sightings of one kind and different users, b up to
    ``apart`` after a: a join whose state both watermarks bound."""
    a = left.select(F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"), F.col("user_id").alias("a_user"), F.col("event_type").alias("kind")).withWatermark("a_ts", late)
    b = right.select(F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"), F.col("user_id").alias("b_user"), F.col("event_type").alias("b_kind")).withWatermark("b_ts", late)
    # both meet in slots of time as long as ``apart``: a's own one and the next
    slot = lambda c: F.floor(F.unix_micros(c) / F.expr(f"unix_micros(timestamp_seconds(0) + INTERVAL {apart})")).cast("bigint")
    a = a.withColumn("slot", F.explode(F.sequence(slot(F.col("a_ts")), slot(F.col("a_ts")) + 1)))
    b = b.withColumn("b_slot", slot(F.col("b_ts")))
    return a.join(b, (F.col("slot") == F.col("b_slot")) & (F.col("kind") == F.col("b_kind")) & (F.col("a_user") != F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {apart}"))).select("a_id", "b_id")


def drain(stream: DataFrame, mode: str = "complete", path: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Run a stream over all that is there now; its result as a table.

    ``complete``: the last batch's table; ``append``: all batches' rows;
    ``update``: of each of ``keys`` the row of the last batch that changed it.  Each
    batch is written under its id, so a batch repeated after a failure replaces
    itself; ``path`` with an earlier run's state continues that run."""
    spark = stream.sparkSession
    if mode == "update" and (not keys or _BATCH in stream.columns):
        raise ValueError(f"updates need the keys that they replace, and no column {_BATCH}")
    path = path or f"{runtime.checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/rows/{_BATCH}={batch}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").foreachBatch(put).trigger(availableNow=True).start().awaitTermination()
    jvm = spark._jvm
    root = jvm.org.apache.hadoop.fs.Path(f"{path}/rows")
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    batches = sorted(int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(root)) if fs.exists(root) else []
    if not batches:
        return spark.createDataFrame([], stream.schema)
    if mode == "update":
        rest = [c for c in stream.columns if c not in keys]
        every = spark.read.schema(T.StructType([*stream.schema.fields, T.StructField(_BATCH, T.LongType())])).parquet(f"{path}/rows")
        last = every.groupBy(*keys).agg(F.max_by(F.struct(F.lit(0).alias(_BATCH), *rest), _BATCH).alias("_last"))
        return last.select(*[F.col(c) if c in keys else F.col(f"_last.`{c}`") for c in stream.columns])
    wanted = batches[-1:] if mode == "complete" else batches
    return spark.read.schema(stream.schema).parquet(*[f"{path}/rows/{_BATCH}={b}" for b in wanted])


def stream_epochs(observed: DataFrame, name: str, classes: dict[str, AgentClass], path: str, epoch_len: int = 1) -> tuple[runtime.World, int] | None:
    """Each batch of ``observed`` (rows of agents of class ``name``) enters the
    world at a tick boundary, then an epoch of ticks runs and is written as the
    checkpoint of that batch's number: a batch that comes again is skipped, and a
    restart on the same ``path`` goes on after the last one.  Classes other than
    ``name`` start empty.  Returns the last (world, tick), None before any."""
    spark = observed.sparkSession

    def epoch(rows: DataFrame, batch: int) -> None:
        here = rows.sparkSession
        last = runtime.resume(here, f"{path}/epochs")
        if last is not None and last[2] > batch:
            return
        if last is None:
            world, tick = {name: rows}, 0
            for other, c in classes.items():
                if other != name:
                    world[other] = here.createDataFrame([], ", ".join(f"{x} bigint" for x in c.columns()))
        else:
            world, tick = dict(last[0]), last[1]
            world[name] = world[name].unionByName(rows.select(*world[name].columns))
        runtime.run(world, classes, tick + epoch_len, epoch_len, path=f"{path}/epochs", start_tick=tick, start_epoch=batch)

    observed.writeStream.option("checkpointLocation", f"{path}/state").foreachBatch(epoch).trigger(availableNow=True).start().awaitTermination()
    last = runtime.resume(spark, f"{path}/epochs")
    return None if last is None else (last[0], last[1])
