"""Sketches of streams. Slots are maxima: replays, late rows and any order give the same ones."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from distinct_bounds.operators import estimate, hashing
from distinct_bounds.operators.sketch import SlotFrame, merge
from distinct_bounds.sources.shipping import ship
from distinct_bounds.sources.storage import load_slots, save_slots, scratch
from distinct_bounds.spec import SketchSpec


def slots_of(stream: DataFrame, cols, spec: SketchSpec = SketchSpec(), by=()) -> DataFrame:
    """Slots of an unbounded stream; state is one number a slot and group, so no watermark is needed."""
    names = [cols] if isinstance(cols, str) else list(cols)
    words = hashing.lanes(stream, hashing.object_key(stream, *names), spec, list(by))
    return words.groupBy(*by, "lane", "row").agg(F.max(hashing.slot_key(F.col("x"), F.col("z"), spec)).alias("key"))


def windowed_slots(stream: DataFrame, cols, time: str, size: str, slide: str | None = None, delay: str = "1 hour", spec: SketchSpec = SketchSpec()) -> DataFrame:
    """(start, lane, row, key) by tumbling or sliding windows; rows later than delay behind the newest are dropped."""
    names = [cols] if isinstance(cols, str) else list(cols)
    timed = stream.withColumn("_time", F.col(time).cast("timestamp")).withWatermark("_time", delay)
    words = hashing.lanes(timed.withColumn("_key", hashing.object_key(stream, *names)), F.col("_key"), spec, ["_time"])
    grouped = words.groupBy(F.window("_time", size, slide) if slide else F.window("_time", size), "lane", "row")
    return grouped.agg(F.max(hashing.slot_key(F.col("x"), F.col("z"), spec)).alias("key")).select(F.col("window.start").alias("start"), "lane", "row", "key")


def sessions(stream: DataFrame, user: str, time: str, gap: str, delay: str = "1 hour") -> DataFrame:
    """(start, session): each user's finished sessions, as user and start, by the day they began in."""
    timed = stream.withColumn("_time", F.col(time).cast("timestamp")).withWatermark("_time", delay)
    found = timed.groupBy(F.session_window("_time", gap), user).agg(F.count("*").alias("rows"))
    began = F.col("session_window.start")
    return found.select(F.date_trunc("day", began).alias("start"), F.concat_ws("|", F.col(user), F.date_format(began, "yyyy-MM-dd HH:mm:ss")).alias("session"))


def session_slots(stream: DataFrame, user: str, time: str, gap: str, delay: str = "1 hour", spec: SketchSpec = SketchSpec()) -> DataFrame:
    """(start, lane, row, key) of the distinct sessions that ended before the watermark, run on all that is there.

    Users are cut into sessions first and sessions are sketched after that: sessions of slots
    would be meaningless, as a slot's rows come from many users. A batch writes the slots of
    the sessions it has finished, and maxima over batches are the whole.
    """
    from distinct_bounds.operators.sketch import build

    made = run_available(sessions(stream, user, time, gap, delay), "append", each=lambda batch: build(batch, "session", spec, ["start"]).df)
    return made.groupBy("start", "lane", "row").agg(F.max("key").alias("key"))


def late_rows(query) -> int:
    """Rows that a finished query's operators have dropped as later than the watermark.

    Aggregates see words after their partial maxima; an operator on plain rows, as in
    deduplicated(), counts the rows themselves.
    """
    return sum(o.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for o in p["stateOperators"])


def deduplicated(stream: DataFrame, cols, time: str, delay: str = "1 day") -> DataFrame:
    """The exact way: first rows of each object within the watermark; state grows with the objects."""
    names = [cols] if isinstance(cols, str) else list(cols)
    return stream.withColumn("_time", F.col(time).cast("timestamp")).withWatermark("_time", delay).dropDuplicatesWithinWatermark(names)


def packed_state(stream: DataFrame, group: str, cols, spec: SketchSpec = SketchSpec()) -> DataFrame:
    """(group, lane, row, key): one matrix a group in custom state; a batch that raises no slot writes nothing."""
    names = [cols] if isinstance(cols, str) else list(cols)
    ship(stream.sparkSession)
    words = hashing.lanes(stream, hashing.object_key(stream, *names), spec, [group])
    keyed = words.select(F.col(group).cast("string").alias("g"), (F.col("lane") * spec.rows + F.col("row")).cast("int").alias("slot"), hashing.slot_key(F.col("x"), F.col("z"), spec).alias("key"))
    slots, rows = spec.slots, spec.rows

    def work(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = np.frombuffer(state.get[0], np.int64).copy() if state.exists else np.full(slots, -1, np.int64)
        before = held.copy()
        for f in frames:
            np.maximum.at(held, f["slot"].to_numpy(), f["key"].to_numpy())
        better = np.flatnonzero(held > before)
        if len(better):
            state.update((held.tobytes(),))
        yield pd.DataFrame({"g": [key[0]] * len(better), "lane": (better // rows).astype(np.int32), "row": (better % rows).astype(np.int32), "key": held[better]})

    return keyed.groupBy("g").applyInPandasWithState(work, "g string, lane int, row int, key bigint", "held binary", "update", GroupStateTimeout.NoTimeout)


def run_available(df: DataFrame, mode: str, checkpoint: str | None = None, each=None, done=None) -> DataFrame:
    """All that is there now, through the stream, as a table: each batch is a file of its number, so replays overwrite.

    each(batch) is what is written of a batch, all of it by default; done(query) is called at the end.
    """
    spark = df.sparkSession
    out = scratch(spark, "stream")
    at = checkpoint or scratch(spark, "stream-checkpoint")
    shape = []

    def put(batch: DataFrame, number: int) -> None:
        made = each(batch) if each else batch
        shape.append(made.schema)
        made.write.mode("overwrite").parquet(f"{out}/batch={number}")

    query = df.writeStream.outputMode(mode).option("checkpointLocation", at).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    if done:
        done(query)
    if not shape:
        return spark.createDataFrame([], df.schema) if each is None else each(spark.createDataFrame([], df.schema))
    return spark.read.schema(shape[0]).option("basePath", out).parquet(f"{out}/batch=*").select(*shape[0].names)


def keep_store(stream: DataFrame, cols, store: str, intervals: str, checkpoint: str, spec: SketchSpec = SketchSpec(), alpha: float = 0.9):
    """A query that merges each batch's slots into a store and writes an interval row for each batch.

    A batch that is run again writes the same version and the same row once more.
    """

    def put(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        names = [cols] if isinstance(cols, str) else list(cols)
        words = hashing.lanes(batch, hashing.object_key(batch, *names), spec)
        fresh = SlotFrame(words.groupBy("lane", "row").agg(F.max(hashing.slot_key(F.col("x"), F.col("z"), spec)).alias("key")), spec)
        frame = merge(load_slots(spark, f"{store}/version={number - 1}", spec), fresh) if number else fresh
        save_slots(frame, f"{store}/version={number}")
        held = load_slots(spark, f"{store}/version={number}", spec)
        estimate.interval(held, alpha).write.mode("overwrite").parquet(f"{intervals}/batch={number}")

    return stream.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(put).start()


def joined(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream rows with columns of a static table, to be sketched by them."""
    return stream.join(static, on)


