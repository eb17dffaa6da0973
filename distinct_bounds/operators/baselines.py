"""What the intervals are compared with: exact counts, other sketches, other intervals."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds
from distinct_bounds.functions.special import EULER, LN2, normal_quantile
from distinct_bounds.operators import estimate, hashing, registers
from distinct_bounds.operators.sketch import SlotFrame, build, decode
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec


def exact(df: DataFrame, cols, by=()) -> DataFrame:
    """(by..., truth). Two-phase distinct: shuffles every object once."""
    names = [cols] if isinstance(cols, str) else list(cols)
    return df.select(*by, hashing.object_key(df, *names).alias("_o")).groupBy(*by).agg(F.countDistinct("_o").alias("truth"))


def _hash_parts(df: DataFrame, cols, bits: int) -> DataFrame:
    """(bucket, rank, unit) of every object: `bits` bucket bits, the position of the first one in 40 further bits,
    and a number in (0, 1] of 52 bits."""
    names = [cols] if isinstance(cols, str) else list(cols)
    digest = df.select(F.sha2(hashing.object_key(df, *names).cast("binary"), 256).alias("d")).filter("d is not null")
    head = F.conv(F.substring("d", 1, 8), 16, 10).cast("bigint")
    field = F.conv(F.substring("d", 9, 10), 16, 10).cast("bigint")
    unit = (F.conv(F.substring("d", 19, 13), 16, 10).cast("bigint") + 1) / float(1 << 52)
    rank = F.when(field == 0, F.lit(41)).otherwise(F.lit(41) - F.length(F.bin(field))).cast("int")
    return digest.select(F.pmod(head, F.lit(1 << bits)).alias("bucket"), rank.alias("rank"), unit.alias("unit"))


def pcsa(df: DataFrame, cols, bits: int = 6) -> DataFrame:
    """Bitmaps of ranks a bucket, of which the lowest missing rank is averaged."""
    m = 1 << bits
    maps = _hash_parts(df, cols, bits).groupBy("bucket").agg(F.bit_or(F.expr("shiftleft(1L, rank - 1)")).alias("b"))
    lowest = F.length(F.bin(F.expr("~b & (b + 1)"))) - 1
    return maps.agg((F.lit(m / 0.77351) * F.pow(F.lit(2.0), F.sum(lowest) / m)).alias("estimate"))


def linear_counting(df: DataFrame, cols, bits: int = 17) -> DataFrame:
    """Minus m times the log of the share of cells that stayed empty; infinite once none is."""
    m = 1 << bits
    hit = _hash_parts(df, cols, bits).select("bucket").distinct().agg(F.count("*").alias("n"))
    return hit.select(F.when(F.col("n") < m, -m * F.log1p(-F.col("n") / float(m))).otherwise(F.lit(math.inf)).alias("estimate"))


def multires_bitmap(df: DataFrame, cols, bits: int = 10, levels: int = 16) -> DataFrame:
    """Linear counting by rank: the finest levels that are not too full are counted and scaled up."""
    m = 1 << bits
    parts = _hash_parts(df, cols, bits).select(F.least("rank", F.lit(levels)).alias("level"), "bucket").distinct()
    full = parts.groupBy("level").agg(F.count("*").alias("n"))
    grid = df.sparkSession.range(1, levels + 1, numPartitions=1).select(F.col("id").cast("int").alias("level"))
    counts = grid.join(full, "level", "left").select("level", F.coalesce("n", F.lit(0)).alias("n"))
    base = counts.agg((F.coalesce(F.max(F.when(F.col("n") > 0.7 * m, F.col("level"))), F.lit(0)) + 1).alias("base"))
    each = F.when(F.col("n") < m, -m * F.log1p(-F.col("n") / float(m))).otherwise(F.lit(m * math.log(m)))
    used = counts.crossJoin(base).filter(F.col("level") >= F.least("base", F.lit(levels)))
    return used.agg((F.sum(each) * F.pow(F.lit(2.0), F.max(F.least("base", F.lit(levels))) - 1)).alias("estimate"))


def min_count(df: DataFrame, cols, k: int = 256) -> DataFrame:
    """(k-1) over the k-th least hash; the number of hashes itself if there are fewer.

    A task keeps its own k least hashes and sends no others, so the shuffle has at most k rows a task.
    """
    ship(df.sparkSession)

    def least_of(batches):
        held = np.empty(0)
        for b in batches:
            fresh = b.column(0).to_numpy(zero_copy_only=False)
            if len(held) == k:
                fresh = fresh[fresh < held[-1]]
            if len(fresh):
                held = np.unique(np.concatenate([held, fresh]))[:k]
        yield pa.RecordBatch.from_arrays([pa.array(held, pa.float64())], ["unit"])

    own = _hash_parts(df, cols, 0).select("unit").mapInArrow(least_of, "unit double")
    least = own.distinct().orderBy("unit").limit(k)
    return least.agg(F.when(F.count("*") < k, F.count("*").cast("double")).otherwise((k - 1) / F.max("unit")).alias("estimate"))


def _ranks(df: DataFrame, cols, bits: int) -> DataFrame:
    return _hash_parts(df, cols, bits).groupBy("bucket").agg(F.max("rank").alias("r"))


def loglog(df: DataFrame, cols, bits: int = 10) -> DataFrame:
    """Geometric mean of 2**rank over the buckets, by the limit of the bias."""
    m = 1 << bits
    return _ranks(df, cols, bits).agg((F.lit(0.39701 * m) * F.pow(F.lit(2.0), F.sum("r") / m)).alias("estimate"))


def hll(df: DataFrame, cols, bits: int = 10) -> DataFrame:
    """Harmonic mean of 2**rank, with linear counting where buckets are empty and the estimate is small."""
    m = 1 << bits
    ranks = _ranks(df, cols, bits).agg(F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("s"), F.count("*").alias("n"))
    raw = F.lit(0.7213 / (1 + 1.079 / m) * m * m) / (F.coalesce("s", F.lit(0.0)) + (m - F.col("n")))
    return ranks.select(F.when((raw <= 2.5 * m) & (F.col("n") < m), m * F.log(m / (m - F.col("n")))).otherwise(raw).alias("estimate"))


def hll_interval(df: DataFrame, cols, bits: int = 10, alpha: float = 0.9) -> DataFrame:
    """The estimate and its standard error times a normal quantile."""
    half = normal_quantile((1 + alpha) / 2) * 1.04 / math.sqrt(1 << bits)
    return hll(df, cols, bits).select("estimate", (F.col("estimate") * (1 - half)).alias("lower"), (F.col("estimate") * (1 + half)).alias("upper"))


def single_slot(df: DataFrame, cols, lanes: int = 4) -> DataFrame:
    """2 to the mean of the lanes' deepest positions, less what that mean exceeds log2 of the truth by, G / ln 2 + 1/2."""
    frame = build(df, cols, SketchSpec.single_slot(lanes))
    x, _ = decode(F.col("key"), frame.spec)
    return frame.df.agg(F.pow(F.lit(2.0), F.avg(x)).alias("raw")).select((F.col("raw") / (math.exp(EULER) * math.sqrt(2))).alias("estimate"))


BUILTIN = ("hllpp", "hll_sketch", "theta_sketch")


def builtin(df: DataFrame, cols, kind: str = "hllpp") -> DataFrame:
    """The engine's own sketches."""
    names = [cols] if isinstance(cols, str) else list(cols)
    key = df.select(hashing.object_key(df, *names).alias("o"))
    made: dict[str, Column] = {"hllpp": F.approx_count_distinct("o", 0.02), "hll_sketch": F.hll_sketch_estimate(F.hll_sketch_agg("o", 12)), "theta_sketch": F.expr("theta_sketch_estimate(theta_sketch_agg(o, 12))")}
    return key.agg(made[kind].cast("double").alias("estimate"))


def _other_interval(frame: SlotFrame, half: float, alpha: float, empty: str) -> DataFrame:
    aimed = estimate.targets(registers.mean_y(frame, empty), frame.spec, half, half, "sound")
    return estimate.inverted(aimed, frame, half, half, alpha)


def clt_interval(frame: SlotFrame, alpha: float = 0.9, empty: str = "zero") -> DataFrame:
    """Asymptotic interval: the mean of the slots as if it were normal."""
    return _other_interval(frame, bounds.clt_half(alpha, frame.spec.slots), alpha, empty)


def chebyshev_interval(frame: SlotFrame, alpha: float = 0.9, empty: str = "zero") -> DataFrame:
    """Interval from the variance alone."""
    return _other_interval(frame, bounds.chebyshev_half(alpha, frame.spec.slots), alpha, empty)


def markov_lower(frame: SlotFrame, alpha: float = 0.9, empty: str = "zero") -> DataFrame:
    """(by..., lower) from the mean alone: the level is at least 1 - alpha of what was seen."""
    means = registers.mean_y(frame, empty)
    return means.select(*frame.by, estimate.inverse(F.col("mean_y") * LN2 * (1 - alpha), frame.spec.p).alias("lower"))


def elephants(df: DataFrame, cols, least: int) -> DataFrame:
    """Objects with at least `least` rows, with their counts; sketch them like any table."""
    names = [cols] if isinstance(cols, str) else list(cols)
    return df.groupBy(*names).agg(F.count("*").alias("n")).filter(F.col("n") >= least)
