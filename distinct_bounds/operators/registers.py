"""What slots say: the transform of a slot, its mean, occupancies and health."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.operators import hashing
from distinct_bounds.operators.sketch import SlotFrame, decode
from distinct_bounds.spec import SketchSpec

#: What an empty slot counts for: 0, the maximum of nothing, or the start value -log2(2 - 2**-z0).
EMPTY = ("zero", "printed")


def empty_value(spec: SketchSpec, empty: str = "zero") -> float:
    import math

    if empty not in EMPTY:
        raise ValueError(f"empty is one of {EMPTY}")
    return 0.0 if empty == "zero" else -math.log2(1 + (spec.steps - 1) / spec.steps)


def y_column(key: Column, spec: SketchSpec) -> Column:
    """The slot's value on the exponential scale, rising with the key."""
    x, z = decode(key, spec)
    return x - F.log2(1 + z / float(spec.steps))


def dense(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(by..., lane, row, x, z, y) of every slot of every group, empty ones too (x, z null)."""
    spark, spec = frame.df.sparkSession, frame.spec
    grid = spark.range(spec.slots, numPartitions=1).select(F.floor(F.col("id") / spec.rows).cast("int").alias("lane"), F.pmod("id", F.lit(spec.rows)).cast("int").alias("row"))
    every = frame.df.select(*frame.by).distinct().crossJoin(F.broadcast(grid)) if frame.by else grid
    held = frame.df.select(*[F.col(k).alias(f"_{k}") for k in frame.keys()], "key")
    on = [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in frame.keys()]
    x, z = decode(F.col("key"), spec)
    y = F.coalesce(y_column(F.col("key"), spec), F.lit(empty_value(spec, empty)))
    return every.join(held, on, "left").select(*frame.by, "lane", "row", x.alias("x"), z.alias("z"), y.alias("y"))


def mean_y(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(by..., mean_y, filled, saturated) without making empty slots rows. Without groups one row, even of no slots."""
    spec, none = frame.spec, empty_value(frame.spec, empty)
    x, _ = decode(F.col("key"), spec)
    total = F.coalesce(F.sum(y_column(F.col("key"), spec)), F.lit(0.0))
    filled = F.count("key")
    return frame.df.groupBy(*frame.by).agg(
        ((total + (spec.slots - filled) * F.lit(none)) / spec.slots).alias("mean_y"),
        filled.alias("filled"),
        F.coalesce(F.sum((x >= spec.saturated).cast("bigint")), F.lit(0)).cast("bigint").alias("saturated"),
    )


def occupancy(df: DataFrame, cols: str | list[str], spec: SketchSpec = SketchSpec()) -> DataFrame:
    """(lane, row, objects): how many distinct objects each slot has seen; the rows of a lane add up to the truth."""
    names = [cols] if isinstance(cols, str) else list(cols)
    objects = df.select(hashing.object_key(df, *names).alias("k")).distinct()
    return hashing.lanes(objects, F.col("k"), spec).groupBy("lane", "row").agg(F.count("*").alias("objects"))


def health(frame: SlotFrame) -> DataFrame:
    """(by..., saturated, empty_slots, max_x)."""
    x, _ = decode(F.col("key"), frame.spec)
    return frame.df.groupBy(*frame.by).agg(F.sum((x >= frame.spec.saturated).cast("bigint")).alias("saturated"), (frame.spec.slots - F.count("key")).alias("empty_slots"), F.max(x).alias("max_x"))
