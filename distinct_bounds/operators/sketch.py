"""Sketches as rows of slots: building, merging, rolling up, folding, packing."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from distinct_bounds.operators import hashing
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec


@dataclass(frozen=True)
class SlotFrame:
    """Non-empty slots (by..., lane, row, key) with what they were made by."""

    df: DataFrame
    spec: SketchSpec
    by: tuple[str, ...] = ()

    def keys(self) -> list[str]:
        return [*self.by, "lane", "row"]


def build(df: DataFrame, cols: str | list[str], spec: SketchSpec = SketchSpec(), by: list[str] | tuple[str, ...] = ()) -> SlotFrame:
    """Slots of the distinct objects of each group: one scan, one aggregate with map-side maxima.

    A task sends at most one row for each group and slot, whatever it reads. Repeats, order
    and partitioning make no difference, so nothing is deduplicated before.
    """
    names = [cols] if isinstance(cols, str) else list(cols)
    words = hashing.lanes(df, hashing.object_key(df, *names), spec, list(by))
    slots = words.groupBy(*by, "lane", "row").agg(F.max(hashing.slot_key(F.col("x"), F.col("z"), spec)).alias("key"))
    return SlotFrame(slots, spec, tuple(by))


def build_two_step(df: DataFrame, cols: str | list[str], spec: SketchSpec = SketchSpec(), by: list[str] | tuple[str, ...] = ()) -> SlotFrame:
    """The same slots as the deepest position and then the least refinement among those that reach it."""
    names = [cols] if isinstance(cols, str) else list(cols)
    words = hashing.lanes(df, hashing.object_key(df, *names), spec, list(by))
    at = [*by, "lane", "row"]
    deepest = words.groupBy(*at).agg(F.max("x").alias("x"))
    least = words.join(deepest, [*at, "x"]).groupBy(*at, "x").agg(F.min("z").alias("z"))
    return SlotFrame(least.select(*at, hashing.slot_key(F.col("x"), F.col("z"), spec).alias("key")), spec, tuple(by))


def build_arrow(df: DataFrame, cols: str | list[str], spec: SketchSpec = SketchSpec()) -> SlotFrame:
    """The same slots by a dense matrix in each task, merged by one aggregate; without groups."""
    names = [cols] if isinstance(cols, str) else list(cols)
    words = hashing.lanes(df, hashing.object_key(df, *names), spec).select("lane", "row", hashing.slot_key(F.col("x"), F.col("z"), spec).alias("key"))
    c0, rows = spec.c0, spec.rows
    ship(df.sparkSession)

    def work(batches):
        held = np.full(c0 * rows, -1, np.int64)
        for b in batches:
            lane, row, key = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            np.maximum.at(held, lane.astype(np.int64) * rows + row, key)
        at = np.flatnonzero(held >= 0)
        yield pa.RecordBatch.from_arrays([pa.array((at // rows).astype(np.int32)), pa.array((at % rows).astype(np.int32)), pa.array(held[at])], ["lane", "row", "key"])

    parts = words.mapInArrow(work, "lane int, row int, key bigint")
    return SlotFrame(parts.groupBy("lane", "row").agg(F.max("key").alias("key")), spec)


def merge(*frames: SlotFrame) -> SlotFrame:
    """Slots of the union of what the frames have seen; they must be of one spec and grouping."""
    first = frames[0]
    if any(f.spec != first.spec or f.by != first.by for f in frames):
        raise ValueError("only sketches of one spec and grouping can be merged")
    df = first.df
    for f in frames[1:]:
        df = df.unionByName(f.df)
    return SlotFrame(df.groupBy(*first.keys()).agg(F.max("key").alias("key")), first.spec, first.by)


def rollup(frame: SlotFrame, by: list[str] | tuple[str, ...] = ()) -> SlotFrame:
    """Slots of coarser groups: the maxima of the finer ones' slots, never their sum."""
    return SlotFrame(frame.df.groupBy(*by, "lane", "row").agg(F.max("key").alias("key")), frame.spec, tuple(by))


def decode(key: Column, spec: SketchSpec) -> tuple[Column, Column]:
    return F.floor(key / spec.steps).cast("int"), (F.lit(spec.steps - 1) - F.pmod(key, F.lit(spec.steps))).cast("int")


def fold(frame: SlotFrame, z0: int | None = None, r0: int | None = None) -> SlotFrame:
    """A coarser sketch without reading objects again: low refinement bits dropped, rows of one prefix joined.

    Dropping bits keeps the order of slots, so maxima stay maxima. The spec returned cuts
    words as the finer one does: building by it gives the same slots, so both may be merged,
    and neither with those of a spec that takes the same number of bits from other places.
    """
    spec = frame.spec
    coarse = replace(spec, z0=spec.z0 if z0 is None else z0, r0=spec.r0 if r0 is None else r0)
    if coarse.z0 > spec.z0 or coarse.r0 > spec.r0:
        raise ValueError("a sketch can only be folded to fewer bits")
    x, z = decode(F.col("key"), spec)
    df = frame.df.select(*frame.by, "lane", F.shiftright("row", spec.r0 - coarse.r0).alias("row"), x.alias("x"), F.shiftright(z, spec.z0 - coarse.z0).alias("z"))
    return SlotFrame(df.groupBy(*frame.by, "lane", "row").agg(F.max(hashing.slot_key(F.col("x"), F.col("z"), coarse)).alias("key")), coarse, frame.by)


def pack(frame: SlotFrame) -> DataFrame:
    """(by..., slots): one array of keys for each group, 0 where a slot is empty; bounded by the spec."""
    spec = frame.spec
    entries = F.map_from_entries(F.collect_list(F.struct((F.col("lane") * spec.rows + F.col("row")).alias("k"), F.col("key").alias("v"))))
    grouped = frame.df.groupBy(*frame.by).agg(entries.alias("m"))
    return grouped.select(*frame.by, F.transform(F.sequence(F.lit(0), F.lit(spec.slots - 1)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0).cast("bigint"))).alias("slots"))


def merge_packed(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def unpack(df: DataFrame, spec: SketchSpec, by: list[str] | tuple[str, ...] = ()) -> SlotFrame:
    spread = df.select(*by, F.posexplode("slots").alias("k", "key")).filter("key > 0")
    return SlotFrame(spread.select(*by, F.floor(F.col("k") / spec.rows).cast("int").alias("lane"), F.pmod("k", F.lit(spec.rows)).cast("int").alias("row"), "key"), spec, tuple(by))


SLOT_SCHEMA = T.StructType([T.StructField("lane", T.IntegerType()), T.StructField("row", T.IntegerType()), T.StructField("key", T.LongType())])
