"""Monte Carlo: tightness of the bounds, coverage of every interval, effects of truncation and empty slots."""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds
from distinct_bounds.functions.solvers import hp_inverse_vec
from distinct_bounds.functions.special import LN2, hp
from distinct_bounds.operators import estimate
from distinct_bounds.operators.registers import decode, empty_value
from distinct_bounds.operators.sketch import SlotFrame
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec

TRUTHS = (50, 100, 500, 1000, 5000, 10_000, 50_000, 100_000)
ALPHAS = (0.9, 0.95, 0.975, 0.99)


def generator(*seed: int) -> np.random.Generator:
    """The same draws for the same numbers, whatever task makes them."""
    return np.random.Generator(np.random.PCG64(list(seed)))


def occupancies(rng: np.random.Generator, truth: int, spec: SketchSpec) -> np.ndarray:
    """Objects of each row in each lane."""
    return rng.multinomial(truth, np.full(spec.rows, spec.p), size=spec.c0)


def slot_maxima(rng: np.random.Generator, m: np.ndarray) -> np.ndarray:
    """Maxima of m exponentials of rate ln 2 by the inverse of their law, so any m costs the same; 0 for none."""
    u = rng.random(m.shape)
    with np.errstate(divide="ignore"):
        log_root = np.log(u) / np.maximum(m, 1)
    return np.where(m > 0, -np.log2(-np.expm1(log_root)), 0.0)


def truncated(y: np.ndarray, m: np.ndarray, spec: SketchSpec, empty: str = "zero") -> np.ndarray:
    """What slots of the spec keep of the exact maxima: the value at the next coarser refinement."""
    x = np.floor(y) + 1
    z = np.floor((2.0 ** (x - y) - 1) * spec.steps)
    return np.where(m > 0, x - np.log2(1 + z / spec.steps), empty_value(spec, empty))


def _spread(spark: SparkSession, n: int, parts: int) -> DataFrame:
    ship(spark)
    return spark.range(n, numPartitions=max(1, min(parts, n)))


def tail_grid(spark: SparkSession, trials: int = 400, seed: int = 7, r0=(0, 1, 2, 3, 4), c0=(1, 2, 3, 4), alphas=ALPHAS, truths=TRUTHS, parts: int = 64) -> DataFrame:
    """(r0, c0, alpha, truth, side, tail, mean, sd, low, high, span, imprecision, above) of the finite bound.

    Half-widths are those at which the limit form is 1 - alpha. Occupancies are drawn trials
    times and the finite form is minimised for each; span is the width of three standard
    deviations either way, imprecision the distance of tail from its lower end, above counts
    trials in which the finite form exceeded the limit.
    """
    grid = list(itertools.product(r0, c0, truths))

    def work(batches):
        for batch in batches:
            rows = []
            for i in batch.column(0).to_pylist():
                a, c, truth = grid[i]
                spec = SketchSpec(c0=c, r0=a, z0=0, layout="prefix", family="md5")
                rng = generator(seed, i)
                drawn = np.stack([occupancies(rng, truth, spec).ravel() for _ in range(trials)])
                for alpha in alphas:
                    for side in ("lower", "upper"):
                        h = bounds._half(1 - alpha, spec.slots, side)
                        tails = bounds.finite_tails(drawn, h, side)
                        mean, sd = float(tails.mean()), float(tails.std(ddof=1)) if trials > 1 else 0.0
                        rows.append((a, c, alpha, truth, side, 1 - alpha, mean, sd, mean - 3 * sd, mean + 3 * sd, 6 * sd, 1 - alpha - (mean - 3 * sd), int((tails > (1 - alpha) * (1 + 1e-9)).sum())))
            if rows:
                yield pa.RecordBatch.from_pylist([dict(zip(TAIL.names, r, strict=True)) for r in rows], schema=TAIL)

    return _spread(spark, len(grid), parts).mapInArrow(work, "r0 int, c0 int, alpha double, truth long, side string, tail double, mean double, sd double, low double, high double, span double, imprecision double, above int")


TAIL = pa.schema([("r0", pa.int32()), ("c0", pa.int32()), ("alpha", pa.float64()), ("truth", pa.int64()), ("side", pa.string()), *[(n, pa.float64()) for n in ("tail", "mean", "sd", "low", "high", "span", "imprecision")], ("above", pa.int32())])


def scattered(grid: DataFrame) -> DataFrame:
    """grid where occupancies vary at all: several rows a lane, and a spread above what rounding leaves of none."""
    return grid.filter("r0 >= 1 AND sd > 1e-13 * tail AND imprecision > 0")


def tail_fit(grid: DataFrame) -> DataFrame:
    """(direction, n, slope, intercept, r2) of the straight line between the logs of span and imprecision, fitted both ways."""
    span, imprecision = F.log("span"), F.log("imprecision")
    fits = [(name, F.regr_slope(y, x), F.regr_intercept(y, x)) for name, y, x in (("span on imprecision", span, imprecision), ("imprecision on span", imprecision, span))]
    both = F.array(*[F.struct(F.lit(name).alias("direction"), slope.alias("slope"), intercept.alias("intercept")) for name, slope, intercept in fits])
    one = scattered(grid).agg(F.count("*").alias("n"), F.regr_r2(span, imprecision).alias("r2"), both.alias("fits"))
    return one.select("n", "r2", F.inline("fits")).select("direction", "n", "slope", "intercept", "r2")


def tail_constant(grid: DataFrame) -> DataFrame:
    """(side, alpha, n, low, middle, high) of the log of span over the square of imprecision, the constant of the line of slope 2."""
    c = F.log("span") - 2 * F.log("imprecision")
    return scattered(grid).groupBy("side", "alpha").agg(F.count("*").alias("n"), F.min(c).alias("low"), F.avg(c).alias("middle"), F.max(c).alias("high"))


def tail_claims(grid: DataFrame) -> DataFrame:
    """(claim, holds): what is said of the tightness of the bound, on a grid of all of its parameters."""
    rows = grid.filter("truth >= 500").groupBy().agg(
        F.max_by(F.struct("r0", "c0", "tail", "truth", "imprecision"), "imprecision").alias("m"),
        F.max_by(F.struct("r0", "c0", "tail", "truth", "imprecision"), F.when(F.col("truth") >= 50_000, F.col("imprecision"))).alias("l"),
    )

    def least(c: str, truth: int, printed: float) -> Column:
        place = (F.col(f"{c}.r0") == 4) & (F.col(f"{c}.c0") == 1) & (F.abs(F.col(f"{c}.tail") - 0.1) < 1e-9) & (F.col(f"{c}.truth") == truth)
        return place & (F.abs(F.col(f"{c}.imprecision") / printed - 1) < 0.1)

    fit = tail_fit(grid).filter("direction = 'span on imprecision'").select("slope", "r2")
    parts = tail_constant(grid).groupBy("side").agg(F.avg("middle").alias("of_side"), F.count("*").alias("levels"), F.corr("alpha", "middle").alias("by_level"))
    sides = parts.agg(F.min(F.when(F.col("side") == "lower", F.col("of_side"))).alias("lower"), F.max(F.when(F.col("side") == "upper", F.col("of_side"))).alias("upper"), F.min("by_level").alias("by_level"))
    never = grid.agg(F.sum("above").alias("above"))
    met = rows.crossJoin(fit).crossJoin(sides).crossJoin(never)
    holds = (
        F.col("above") == 0,
        F.abs(F.col("slope") - 1.88) < 0.05,
        F.col("r2") > 0.95,
        least("m", 500, 0.00683),
        least("l", 50_000, 6.7e-5),
        F.col("lower") > F.col("upper") + 0.5,
        F.col("by_level") > 0.9,
    )
    return told(met, TAIL_CLAIMS, holds)


def told(df: DataFrame, claims: tuple[str, ...], holds: tuple[Column, ...]) -> DataFrame:
    return df.select(F.inline(F.array(*[F.struct(F.lit(c).alias("claim"), h.alias("holds")) for c, h in zip(claims, holds, strict=True)])))


TAIL_CLAIMS = (
    "the finite form is never above the limit form",
    "the line of the logs has slope 1.88 within 0.05",
    "the line explains more than 0.95 of the variance",
    "from 500 objects on the largest imprecision is 0.00683 within a tenth",
    "from 50000 objects on it is 0.000067 within a tenth",
    "the constant differs between the sides",
    "the constant rises with the level",
)

METHODS = ("equal", "shortest", "lower", "upper", "clt", "chebyshev", "markov")


def halves_of(method: str, alpha: float, slots: int) -> tuple[float, float]:
    if method in ("equal", "shortest"):
        return bounds.budget(alpha, slots, "two", method)
    if method in ("lower", "upper"):
        return bounds.budget(alpha, slots, method)
    half = bounds.clt_half(alpha, slots) if method == "clt" else bounds.chebyshev_half(alpha, slots)
    return half, half


COVER = pa.schema([("method", pa.string()), ("slack", pa.string()), ("empty", pa.string()), ("alpha", pa.float64()), ("truth", pa.int64()), ("trials", pa.int64()), ("covered", pa.int64()), ("bias", pa.float64())])


def coverage(spark: SparkSession, spec: SketchSpec = SketchSpec(), truths=(10, 50, 500, 5000, 100_000), alpha: float = 0.9, trials: int = 2000, seed: int = 11, methods=METHODS, chunk: int = 500) -> DataFrame:
    """(method, slack, empty, alpha, truth, trials, covered, rate, bias): how often each interval holds the truth.

    Targets are compared with the level of the truth, which is the same as comparing after
    inversion. bias is the mean of the slots' mean less its expectation, in units of 1 / ln 2.
    """
    jobs = [(t, k) for t in truths for k in range(-(-trials // chunk))]
    p, slots = spec.p, spec.slots

    def work(batches):
        for batch in batches:
            rows = []
            for i in batch.column(0).to_pylist():
                truth, k = jobs[i]
                n = min(chunk, trials - k * chunk)
                rng = generator(seed, truth, k)
                m = np.stack([occupancies(rng, truth, spec) for _ in range(n)])
                ideal = slot_maxima(rng, m)
                level = float(hp(truth, p)[0])
                for empty in ("zero", "printed"):
                    mean = truncated(ideal, m, spec, empty).reshape(n, -1).mean(axis=1)
                    for slack in estimate.SLACK:
                        below, above = estimate.slack_of(spec, slack)
                        for method in methods:
                            if method == "markov":
                                ok = mean * LN2 * (1 - alpha) <= level
                            else:
                                down, up = halves_of(method, alpha, slots)
                                ok = (mean * LN2 - down - below <= level) & (level <= mean * LN2 + up + above)
                            rows.append((method, slack, empty, alpha, truth, n, int(ok.sum()), float((mean - level / LN2).sum())))
            if rows:
                yield pa.RecordBatch.from_pylist([dict(zip(COVER.names, r, strict=True)) for r in rows], schema=COVER)

    made = _spread(spark, len(jobs), 64).mapInArrow(work, "method string, slack string, empty string, alpha double, truth long, trials long, covered long, bias double")
    return made.groupBy("method", "slack", "empty", "alpha", "truth").agg(F.sum("trials").alias("trials"), F.sum("covered").alias("covered"), (F.sum("covered") / F.sum("trials")).alias("rate"), (F.sum("bias") / F.sum("trials")).alias("bias"))


COVER_CLAIMS = (
    "every Chernoff interval holds at least its level",
    "the shortest interval holds at least its level",
    "the variance alone holds at least its level",
    "the central limit holds less than the Chernoff interval",
    "the printed start value loses coverage at 10 objects or fewer",
    "the mean has no bias above a hundredth over all sizes",
)


def coverage_claims(rates: DataFrame) -> DataFrame:
    """(claim, holds) of simulated coverage at nominal alpha."""
    plain = (F.col("slack") == "sound") & (F.col("empty") == "zero")

    def least(*methods: str) -> Column:
        return F.min(F.when(plain & F.col("method").isin(*methods), F.col("rate") - F.col("alpha"))) >= 0

    met = rates.agg(
        least("equal", "lower", "upper").alias("a"),
        least("shortest").alias("b"),
        least("chebyshev").alias("c"),
        (F.sum(F.when(plain & (F.col("method") == "clt"), F.col("covered"))) < F.sum(F.when(plain & (F.col("method") == "equal"), F.col("covered")))).alias("d"),
        (F.min(F.when((F.col("slack") == "sound") & (F.col("empty") == "printed") & (F.col("method") == "equal") & (F.col("truth") <= 10), F.col("rate") - F.col("alpha"))) < -0.1).alias("e"),
        (F.abs(F.avg(F.when(plain, F.col("bias")))) < 0.01).alias("f"),
    )
    return told(met, COVER_CLAIMS, tuple(F.col(c) for c in "abcdef"))


def truncation_gap(spark: SparkSession, spec: SketchSpec = SketchSpec(), truth: int = 1000, trials: int = 1000, seed: int = 13) -> DataFrame:
    """(trials, least, most, bound): what truncation adds to a slot, and 2**-z0 / ln 2 that it must stay below."""

    def work(batches):
        for batch in batches:
            ids = batch.column(0).to_pylist()
            low, high = [], []
            for i in ids:
                rng = generator(seed, i)
                m = occupancies(rng, truth, spec)
                ideal = slot_maxima(rng, m)
                gap = (truncated(ideal, m, spec) - ideal)[m > 0]
                low.append(float(gap.min(initial=np.inf)))
                high.append(float(gap.max(initial=-np.inf)))
            yield pa.RecordBatch.from_arrays([pa.array(low), pa.array(high)], ["low", "high"])

    made = _spread(spark, trials, 32).mapInArrow(work, "low double, high double")
    return made.agg(F.count("*").alias("trials"), F.min("low").alias("least"), F.max("high").alias("most"), F.lit(2.0**-spec.z0 / LN2).alias("bound"))


def truncation_of(frame: SlotFrame, z0: int) -> DataFrame:
    """(trials, least, most, bound) of truncation_gap from the slots of a table: what is added to a slot of each group if
    only z0 bits of its refinement are kept."""
    _, z = decode(F.col("key"), frame.spec)
    coarse = F.floor(z / 2 ** (frame.spec.z0 - z0)) / 2.0**z0
    gap = F.log2(1 + z / float(frame.spec.steps)) - F.log2(1 + coarse)
    made = frame.df.select(*frame.by, gap.alias("gap")).groupBy(*frame.by).agg(F.min("gap").alias("low"), F.max("gap").alias("high"))
    return made.agg(F.count("*").alias("trials"), F.min("low").alias("least"), F.max("high").alias("most"), F.lit(2.0**-z0 / LN2).alias("bound"))


def estimate_spread(spec: SketchSpec, truth: int, trials: int, seed: int = 17) -> np.ndarray:
    """Point estimates of many simulated sketches."""
    rng = generator(seed, truth)
    m = np.stack([occupancies(rng, truth, spec) for _ in range(trials)])
    mean = truncated(slot_maxima(rng, m), m, spec).reshape(trials, -1).mean(axis=1)
    return hp_inverse_vec(mean * LN2, spec.p)
