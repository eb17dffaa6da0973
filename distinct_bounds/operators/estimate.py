"""Point estimates and intervals from slots."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds
from distinct_bounds.functions.solvers import hp_inverse_vec
from distinct_bounds.functions.special import EULER, LN2
from distinct_bounds.operators import registers
from distinct_bounds.operators.sketch import SlotFrame
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec

#: Where the truncation of the refinement is paid for: "sound" lowers the lower bound by its
#: largest effect, "theorem" and "procedure" raise the upper one, by 2**-z0 / ln 2 or 2**-z0.
SLACK = ("sound", "theorem", "procedure")


def slack_of(spec: SketchSpec, slack: str) -> tuple[float, float]:
    """(below, above) to be added to the half-widths."""
    step = 2.0**-spec.z0
    return {"sound": (step, 0.0), "theorem": (0.0, step / LN2), "procedure": (0.0, step)}[slack]


def inverse(target: Column, p: float) -> Column:
    """The number of objects whose expected level is target; the only Python of a query, over one row a group."""

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for x in batches:
            y = np.array([np.nan if v is None else v for v in x.to_pylist()], float)
            yield pa.array(hp_inverse_vec(y, p), pa.float64(), from_pandas=True)

    ship(target_session())
    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, "double")(target)


def target_session():
    from pyspark.sql import SparkSession

    return SparkSession.active()


def point(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(by..., mean_y, estimate)."""
    means = registers.mean_y(frame, empty)
    return means.select(*frame.by, "mean_y", inverse(F.col("mean_y") * LN2, frame.spec.p).alias("estimate"))


def point_fast(frame: SlotFrame, empty: str = "zero") -> DataFrame:
    """(by..., mean_y, estimate) in closed form: the upper end of the inverse's bracket."""
    means = registers.mean_y(frame, empty)
    return means.select(*frame.by, "mean_y", (F.exp(F.col("mean_y") * LN2 - EULER) / frame.spec.p - 0.5).alias("estimate"))


def targets(means: DataFrame, spec: SketchSpec, h_down: float, h_up: float, slack: str = "sound", level: Column | None = None) -> DataFrame:
    """means with middle, low and high on the scale that is to be inverted; an absent side is null."""
    below, above = slack_of(spec, slack)
    middle = F.col("mean_y") * LN2 if level is None else level
    low = F.greatest(F.lit(0.0), middle - h_down - below) if math.isfinite(h_down) else F.lit(None).cast("double")
    high = middle + h_up + above if math.isfinite(h_up) else F.lit(None).cast("double")
    return means.withColumns({"middle": middle, "low": low, "high": high})


def transformed_interval(frame: SlotFrame, alpha: float, side: str = "two", split="equal", slack: str = "sound", empty: str = "zero") -> DataFrame:
    """(by..., low, high): the interval before inversion, for the expected level of the truth."""
    h = bounds.budget(alpha, frame.spec.slots, side, split)
    return targets(registers.mean_y(frame, empty), frame.spec, *h, slack).select(*frame.by, "low", "high")


def interval(frame: SlotFrame, alpha: float = 0.9, side: str = "two", split="equal", slack: str = "sound", empty: str = "zero", halves: tuple[float, float] | None = None) -> DataFrame:
    """One row a group: estimate, lower, upper and what they rest on.

    halves overrides the half-widths that alpha, side and split would give. The lower bound
    of a one-sided upper interval is 0, the upper of a lower one infinite. level is what
    holds for ideal hash bits; saturated slots break it and are counted.
    """
    spec = frame.spec
    h_down, h_up = halves or bounds.budget(alpha, spec.slots, side, split)
    return inverted(targets(registers.mean_y(frame, empty), spec, h_down, h_up, slack), frame, h_down, h_up, alpha)


def inverted(aimed: DataFrame, frame: SlotFrame, h_down: float, h_up: float, level: float) -> DataFrame:
    p, finite = frame.spec.p, math.isfinite(h_up)
    lower = inverse(F.col("low"), p) if math.isfinite(h_down) else F.lit(0.0)
    upper = inverse(F.col("high"), p) if finite else F.lit(math.inf)
    out = aimed.select(*frame.by, inverse(F.col("middle"), p).alias("estimate"), lower.alias("lower"), upper.alias("upper"), "filled", "saturated")
    return out.select(
        *frame.by, "estimate", "lower", "upper",
        F.ceil("lower").cast("bigint").alias("lower_int"), (F.floor("upper").cast("bigint") if finite else F.lit(None).cast("bigint")).alias("upper_int"),
        F.when(F.col("lower") > 0, F.log(F.col("upper") / F.col("lower"))).alias("log_width"),
        F.lit(h_down).alias("h_down"), F.lit(h_up).alias("h_up"), F.lit(level).alias("level"), "saturated", (frame.spec.slots - F.col("filled")).alias("empty_slots"),
    )


def count_distinct_interval(df: DataFrame, cols, by=(), alpha: float = 0.9, spec: SketchSpec = SketchSpec(), **options) -> DataFrame:
    """Interval of the number of distinct objects of each group, in one pass over df."""
    from distinct_bounds.operators.sketch import build

    return interval(build(df, cols, spec, by), alpha, **options)


def hp_table(spark, n: int, p: float) -> DataFrame:
    """(n, hp) for 1..n: the expected level of whole numbers of objects, by a running sum in SQL alone.

    For small n: the running sum is one ordered window.
    """
    from pyspark.sql import Window

    terms = spark.range(1, n + 1).select(F.col("id").alias("n"), ((1 - F.pow(F.lit(1 - p), F.col("id"))) / F.col("id")).alias("term"))
    return terms.select("n", F.sum("term").over(Window.orderBy("n").rowsBetween(Window.unboundedPreceding, 0)).alias("hp"))


def inverse_by_table(aimed: DataFrame, table: DataFrame, column: str, name: str, p: float, cuts: int = 8) -> DataFrame:
    """aimed with the largest n whose level is no more than column: an as-of join, and the inverse above the table's end.

    A row n of the table holds from its level up to the next one. It is entered under each
    of the cells of 1/cuts that this stretch meets, so that the join is on equal cells and
    no row of aimed is ordered or moved. The table, whose length the caller chose, is broadcast. p is that of the table.
    """
    from pyspark.sql import Window

    upto = F.lead("hp").over(Window.orderBy("n"))
    stretches = table.select("n", "hp", upto.alias("_upto"))
    start = F.lit(0).cast("bigint"), F.lit(0.0)
    first = table.agg(F.min("hp").alias("_upto")).select(start[0].alias("n"), start[1].alias("hp"), "_upto")
    stretches = first.unionByName(stretches).filter("_upto is not null")
    cell = F.explode(F.sequence(F.floor(F.col("hp") * cuts), F.floor(F.col("_upto") * cuts)))
    side = F.broadcast(stretches.select(F.col("n").alias("_n"), F.col("hp").alias("_from"), "_upto", cell.alias("_cell")))
    end = F.broadcast(table.agg(F.max("n").alias("_end")))
    at = F.greatest(F.col(column), F.lit(0.0))
    found = aimed.withColumn("_at", at).crossJoin(end).join(side, (F.floor(F.col("_at") * cuts) == F.col("_cell")) & (F.col("_at") >= F.col("_from")) & (F.col("_at") < F.col("_upto")), "left")
    beyond = F.greatest(F.coalesce("_end", F.lit(0)), F.floor(inverse(F.col("_at"), p)))
    return found.select(*[F.col(c) for c in aimed.columns], F.coalesce("_n", beyond).cast("bigint").alias(name))
