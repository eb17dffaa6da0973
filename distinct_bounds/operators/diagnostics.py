"""Measures: accuracy, coverage, fit of the hash statistics, frequency shape, evolution."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from distinct_bounds.functions.special import chi_square_tail, f_tail
from distinct_bounds.operators import estimate, hashing, registers
from distinct_bounds.operators.sketch import SlotFrame
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec


def relative_accuracy(intervals: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """intervals with truth, accuracy = estimate / truth and covered."""
    met = intervals.join(truth, on) if on else intervals.crossJoin(F.broadcast(truth))
    return met.withColumn("accuracy", F.col("estimate") / F.col("truth")).withColumn("covered", (F.col("lower") <= F.col("truth")) & (F.col("truth") <= F.col("upper")))


def coverage(accuracies: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., slices, rate): how many intervals there are and what share covers the truth."""
    return accuracies.groupBy(*by).agg(F.count("*").alias("slices"), F.avg(F.col("covered").cast("double")).alias("rate"))


def log_length(intervals: DataFrame) -> DataFrame:
    return intervals.withColumn("log_length", F.log(F.col("upper") / F.col("lower")))


def accuracy_histogram(accuracies: DataFrame, low: float = 0.5, high: float = 1.5, bins: int = 20) -> DataFrame:
    """(bin, n): accuracies in equal bins, 0 and bins + 1 for those outside."""
    return accuracies.select(F.width_bucket("accuracy", F.lit(low), F.lit(high), F.lit(bins)).cast("int").alias("bin")).groupBy("bin").agg(F.count("*").alias("n"))


def truth_histogram(accuracies: DataFrame, bins: int = 20) -> DataFrame:
    """(bin, low, n): true counts of the slices in equal bins from 0 to the largest."""
    width = accuracies.agg(F.greatest(F.lit(1), F.ceil((F.max("truth") + 1) / bins)).cast("bigint").alias("_width"))
    placed = accuracies.crossJoin(F.broadcast(width)).select(F.floor(F.col("truth") / F.col("_width")).cast("int").alias("bin"), "_width")
    return placed.groupBy("bin").agg((F.max("_width") * F.col("bin")).alias("low"), F.count("*").alias("n"))


def association(df: DataFrame, x: str, y: str) -> DataFrame:
    """(n, slope, intercept, r2, f, p) of y against x; p is the chance of such an r2 without association."""
    fit = df.agg(F.count("*").alias("n"), F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))
    made = fit.withColumn("f", F.when((F.col("n") > 2) & (F.col("r2") < 1), F.col("r2") * (F.col("n") - 2) / (1 - F.col("r2"))))
    return made.withColumn("p", tail_chance(f_tail, F.col("f"), F.lit(1), F.col("n") - 2))


def tail_chance(tail: Callable[..., float], *of: Column) -> Column:
    """tail(*of), null where a number is: an Arrow function over the few rows of a finished statistic."""

    def run(batches: Iterator[tuple[pa.Array, ...]]) -> Iterator[pa.Array]:
        for batch in batches:
            rows = zip(*(c.to_pylist() for c in batch), strict=True)
            yield pa.array([None if None in r else tail(*r) for r in rows], pa.float64())

    ship(SparkSession.active())
    run.__annotations__ = {"batches": Iterator[tuple[pa.Array, ...]], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, "double")(*[c.cast("double") for c in of])


def object_words(df: DataFrame, cols, spec: SketchSpec) -> DataFrame:
    """Hash fields of each distinct object once a lane."""
    names = [cols] if isinstance(cols, str) else list(cols)
    return hashing.lanes(df.select(hashing.object_key(df, *names).alias("k")).distinct(), F.col("k"), spec)


def _chi_square(words: DataFrame, cell, cells: int, expected_share) -> DataFrame:
    """(statistic, df, n) over cells 0..cells-1 with given shares; empty cells count."""
    spark = words.sparkSession
    counted = words.select(cell.alias("cell")).groupBy("cell").agg(F.count("*").alias("o"))
    grid = spark.range(cells, numPartitions=1).select(F.col("id").cast("int").alias("cell"), expected_share(F.col("id")).alias("share"))
    total = counted.agg(F.sum("o").alias("total"))
    met = grid.join(counted, "cell", "left").crossJoin(F.broadcast(total)).withColumn("e", F.col("total") * F.col("share"))
    return met.agg(F.sum(F.pow(F.coalesce("o", F.lit(0)) - F.col("e"), F.lit(2.0)) / F.col("e")).alias("statistic"), F.lit(cells - 1).alias("df"), F.first("total").alias("n"))


def fit_rows(df: DataFrame, cols, spec: SketchSpec = SketchSpec()) -> DataFrame:
    """Chi-square of the row of distinct objects against equal shares."""
    return _tested(_chi_square(object_words(df, cols, spec), F.col("row"), spec.rows, lambda i: F.lit(1.0 / spec.rows)))


def fit_refinement(df: DataFrame, cols, spec: SketchSpec = SketchSpec()) -> DataFrame:
    """Chi-square of the refinement against equal shares."""
    return _tested(_chi_square(object_words(df, cols, spec), F.col("z"), spec.steps, lambda i: F.lit(1.0 / spec.steps)))


def fit_first_one(df: DataFrame, cols, spec: SketchSpec = SketchSpec(), cells: int = 13) -> DataFrame:
    """Chi-square of the first-one position against halving shares; the last cell holds the rest."""
    cell = F.least(F.col("x"), F.lit(cells)) - 1
    return _tested(_chi_square(object_words(df, cols, spec), cell, cells, lambda i: F.pow(F.lit(2.0), -F.least(i + 1, F.lit(cells - 1)))))


def _tested(fit: DataFrame) -> DataFrame:
    return fit.withColumn("p", tail_chance(chi_square_tail, F.col("statistic"), F.col("df")))


def anova_parts(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(f, df1, df2): one-way analysis of variance of the slots' values by lane."""
    lanes = registers.dense(frame, empty).groupBy("lane").agg(F.count("*").alias("n"), F.avg("y").alias("m"), F.var_pop("y").alias("v"))
    grand = lanes.agg((F.sum(F.col("n") * F.col("m")) / F.sum("n")).alias("g"))
    sums = lanes.crossJoin(F.broadcast(grand)).agg(F.sum(F.col("n") * F.pow(F.col("m") - F.col("g"), F.lit(2.0))).alias("between"), F.sum(F.col("n") * F.col("v")).alias("within"))
    c0, slots = frame.spec.c0, frame.spec.slots
    return sums.select((F.col("between") / (c0 - 1) / (F.col("within") / (slots - c0))).alias("f"), F.lit(c0 - 1).alias("df1"), F.lit(slots - c0).alias("df2"))


def anova_lanes(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    return anova_parts(frame, empty).withColumn("p", tail_chance(f_tail, F.col("f"), F.col("df1"), F.col("df2")))


def lane_quartiles(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(lane, low, q1, median, q3, high) of the slots' values."""
    q = [F.percentile("y", F.lit(s)).alias(n) for s, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3"))]
    return registers.dense(frame, empty).groupBy("lane").agg(F.min("y").alias("low"), *q, F.max("y").alias("high"))


def frequency_rank(df: DataFrame, cols) -> DataFrame:
    """(frequency, objects, first_rank): how many objects have a frequency and the rank of the first of them.

    Objects are counted by frequency before anything is ordered, so that only the distinct
    frequencies meet in one task.
    """
    names = [cols] if isinstance(cols, str) else list(cols)
    counts = df.groupBy(*names).agg(F.count("*").alias("frequency")).groupBy("frequency").agg(F.count("*").alias("objects"))
    before = W.orderBy(F.desc("frequency")).rowsBetween(W.unboundedPreceding, -1)
    return counts.select("frequency", "objects", (F.coalesce(F.sum("objects").over(before), F.lit(0)) + 1).cast("bigint").alias("first_rank"))


def frequency_rank_fit(df: DataFrame, cols) -> DataFrame:
    """(frequencies, slope, intercept, r2) of log frequency against log first rank."""
    y, x = F.log("frequency"), F.log("first_rank")
    return frequency_rank(df, cols).agg(F.count("*").alias("frequencies"), F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def running_slots(frame: SlotFrame, batch: str) -> SlotFrame:
    """Slots of all batches up to each one, from slots by batch; objects are not read again.

    The grid of batches and slots is filled and a running maximum taken for each slot.
    """
    spec = frame.spec
    spark = frame.df.sparkSession
    batches = frame.df.select(batch).distinct()
    grid = spark.range(spec.slots, numPartitions=1).select(F.floor(F.col("id") / spec.rows).cast("int").alias("lane"), F.pmod("id", F.lit(spec.rows)).cast("int").alias("row"))
    full = batches.crossJoin(F.broadcast(grid)).join(frame.df, [batch, "lane", "row"], "left")
    upto = W.partitionBy("lane", "row").orderBy(batch).rowsBetween(W.unboundedPreceding, 0)
    run = full.select(batch, "lane", "row", F.max("key").over(upto).alias("key")).filter("key is not null")
    return SlotFrame(run, spec, (batch,))


def running_truth(df: DataFrame, cols, batch: str) -> DataFrame:
    """(batch, truth): distinct objects of all batches up to each one."""
    names = [cols] if isinstance(cols, str) else list(cols)
    first = df.select(batch, hashing.object_key(df, *names).alias("_o")).filter("_o is not null").groupBy("_o").agg(F.min(batch).alias(batch))
    fresh = first.groupBy(batch).agg(F.count("*").alias("fresh"))
    every = df.select(batch).distinct().join(fresh, batch, "left")
    return every.select(batch, F.sum(F.coalesce("fresh", F.lit(0))).over(W.orderBy(batch).rowsBetween(W.unboundedPreceding, 0)).cast("bigint").alias("truth"))


def evolution(df: DataFrame, cols, batch: str, spec: SketchSpec = SketchSpec(), alpha: float = 0.9, **options) -> DataFrame:
    """(batch, interval..., truth, accuracy, covered) after each batch of a stream."""
    from distinct_bounds.operators.sketch import build

    run = running_slots(build(df, cols, spec, [batch]), batch)
    return relative_accuracy(estimate.interval(run, alpha, **options), running_truth(df, cols, batch), [batch])
