"""Mixing sources to target weights by entropy balancing: tilted rates from the convex dual, rounded to copies."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from distinct_bounds.llm.common import col, map_arrow, materialize, quoted, table, without
from distinct_bounds.sources.shipping import ship

OUTPUTS = ("size", "source_size", "target", "copies", "taken")
CYCLE = (1, 2, 3)
CAP = 3
#: Sources whose parameters the driver and a broadcast may hold; those of more stay in a table.
MOST_SOURCES = 200_000
BINS = 4096


def words_in(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("bigint")


def shares(sizes: list[int], weights: list[float], cap: float = CAP) -> list[float]:
    """Targets that share sum(sizes) by weight, none above cap times its size.

    Sources that would be above stop there and leave the rest to the others, until none is
    above. Sources without words have target 0.
    """
    target, left, open_ = [0.0] * len(sizes), float(sum(sizes)), {i for i, s in enumerate(sizes) if s > 0}
    while open_:
        total = sum(weights[i] for i in open_)
        over = {i for i in open_ if left * weights[i] / total > cap * sizes[i]}
        if not over:
            for i in open_:
                target[i] = left * weights[i] / total
            break
        for i in over:
            target[i] = float(cap * sizes[i])
            left -= target[i]
        open_ -= over
    return target


@dataclass
class Source:
    """One source: its total and target, the dual variable with its bracket, and a rounding threshold for each size class."""

    name: str | None
    size: int
    docs: int
    target: float
    dual: float = 0.0
    low: float = -math.inf
    high: float = math.inf
    settled: bool = False
    thresholds: tuple[float, ...] = (0.0, 0.0, 0.0)
    width: float = 2.0
    below: float = -1.0

    @property
    def mean(self) -> float:
        return self.size / max(1, self.docs)

    @property
    def fixed(self) -> float | None:
        """The common rate where no tilt is to be found: nothing to take, or all of the cap."""
        if self.size == 0 or self.target <= 0:
            return 0.0
        return float(CAP) if self.target >= CAP * self.size * (1 - 1e-12) else None


def parameters(spark: SparkSession, sources: list[Source]) -> DataFrame:
    rows = [(i, x.name, x.size, x.target, x.dual / x.mean if x.size else 0.0, x.fixed, list(x.thresholds), x.mean, x.below, x.width) for i, x in enumerate(sources)]
    return F.broadcast(spark.createDataFrame(rows, "k int, _source string, source_size long, target double, tilt double, fixed double, thresholds array<double>, mean double, below double, width double"))


def rate() -> Column:
    """Copies a document should have on average: exp(tilt * size), the cap at most."""
    return F.coalesce(F.col("fixed"), F.least(F.lit(float(CAP)), F.exp(F.least(F.lit(60.0), F.col("tilt") * F.col("size")))))


def margin(id_col: str) -> Column:
    """A fixed uniform number of the document minus the fraction of its rate: small where another copy is due."""
    uniform = F.pmod(F.xxhash64(col(id_col), F.col("size"), F.lit("copies")), F.lit(1 << 52)) / float(1 << 52)
    return uniform - (F.col("rate") - F.floor("rate"))


def solve(spark: SparkSession, histogram: DataFrame, sources: list[Source], tolerance: float = 1e-9, most: int = 60) -> int:
    """Newton iterations on every source's dual at once; returns how many were run.

    histogram is (k, size, n): a source's rates depend on sizes alone, so these counts are
    all that the sums of an iteration need, and they are computed where they lie. The step is
    taken on the logarithm of the words taken, kept within a bracket of the root.
    """
    for i in range(most):
        if all(x.fixed is not None or x.settled for x in sources):
            break
        met = histogram.join(parameters(spark, sources).select("k", "tilt", "fixed"), "k").withColumn("rate", rate())
        words = F.col("n") * F.col("size") * F.col("rate")
        slope = F.when(F.col("rate") < CAP, words * F.col("size")).otherwise(0.0)
        for r in met.groupBy("k").agg(F.sum(words).alias("f"), F.sum(slope).alias("g")).collect():
            x = sources[r["k"]]
            if x.fixed is not None or x.settled:
                continue
            off, g = math.log(x.target) - math.log(max(r["f"], 1e-300)), r["g"] / x.mean
            if abs(off) <= tolerance:
                x.settled = True
                continue
            x.low, x.high = (max(x.low, x.dual), x.high) if off > 0 else (x.low, min(x.high, x.dual))
            step = x.dual + off * r["f"] / g if g > 0 else math.inf
            if not x.low < step < x.high:
                step = (x.low + x.high) / 2 if math.isfinite(x.low + x.high) else (2 * x.dual + 1 if off > 0 else 2 * x.dual - 1)
            x.settled, x.dual = abs(step - x.dual) <= 1e-13 * max(1.0, abs(step)), step
    for x in sources:  # sums of doubles differ in their last digits from run to run; the rates must not
        x.dual = float(f"{x.dual:.9g}")
    return i


def size_class() -> Column:
    """0: above the source's mean size; 2: no more than an eighth of it; 1: between."""
    return F.when(F.col("size") > F.col("mean"), 0).when(8 * F.col("size") > F.col("mean"), 1).otherwise(2)


def copies() -> Column:
    """The whole part of the rate, and one more where the margin is below the threshold of the size class."""
    one_more = (F.col("rate") < CAP) & (F.col("margin") < F.element_at("thresholds", size_class() + 1))
    return F.when(F.col("size") == 0, 0).otherwise(F.floor("rate") + F.when(one_more, 1).otherwise(0)).cast("bigint")


def edges(met: DataFrame, c: int) -> DataFrame:
    """(k, e): the bin of the margin in which the words wanted of size class c are met, with the sums around it."""
    from pyspark.sql import Window

    met = met.withColumn("rate", rate()).withColumn("margin", margin("_id"))
    words, kind = F.col("rate") * F.col("size"), size_class()
    due = (F.col("rate") < CAP) & (kind == c)
    place = F.floor((F.col("margin") - F.col("below")) / F.col("width") * BINS)
    place = F.when(~due, F.lit(-2)).otherwise(F.greatest(F.lit(-1), F.least(F.lit(BINS), place))).cast("int")
    owed = F.when(kind < c, words - copies() * F.col("size")).when(kind == c, words - F.floor("rate") * F.col("size")).otherwise(0.0)
    sums = met.groupBy("k", place.alias("bin")).agg(F.sum(owed).alias("owed"), F.sum(F.when(due, F.col("size")).otherwise(0)).alias("extra"))
    by = Window.partitionBy("k")
    run = sums.withColumn("want", F.sum("owed").over(by)).withColumn("upto", F.sum("extra").over(by.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)))
    return run.filter((F.col("bin") >= -1) & (F.col("upto") > F.col("want"))).groupBy("k").agg(F.min(F.struct("bin", "upto", "extra", "want")).alias("e"))


def settle_rounding(spark: SparkSession, sized: DataFrame, sources: list[Source], levels: int = 2) -> None:
    """Thresholds on the margin, such that the copies take each source's target as nearly as small documents allow.

    Size classes go from large to small; each takes its expected words and what the classes
    before it left over or took too much. Words are summed by bins of the margin, and the bin
    in which the wanted words are met is cut into bins again. One row of each source reaches
    the driver.
    """
    for c in range(3):
        for x in sources:
            x.below, x.width = -1.0, 2.0
        for _ in range(levels):
            edge = edges(sized.join(parameters(spark, sources), "k"), c)
            found = {r["k"]: r["e"] for r in edge.collect()}
            for k, x in enumerate(sources):
                e, held = found.get(k), list(x.thresholds)
                if e is None:  # every extra copy of the class is due
                    held[c] = x.below + x.width
                else:
                    cut = x.width / BINS
                    start = x.below + e["bin"] * cut
                    short, over = e["want"] - (e["upto"] - e["extra"]), e["upto"] - e["want"]
                    held[c] = start if short <= over else start + cut
                    x.below, x.width = start, cut
                x.thresholds = tuple(held)


def changes(sized: DataFrame, found: DataFrame) -> DataFrame:
    """(k, _id, size, step): documents that are rounded the other way, so that a source's words come nearer its target.

    Of each source, and of each doubling of the size in it, a few documents that could be
    rounded up and a few that could be rounded down are looked at, chosen by a hash; from
    large to small, each is rounded the other way if that brings the words nearer. What
    stays off is no more than about the smallest of them. Rows of one id and size change together.
    """
    made = sized.join(found, "k").withColumn("rate", rate()).withColumn("margin", margin("_id")).withColumn("copies", copies())
    mark = F.xxhash64("_id", "size", F.lit("change"))
    one = F.struct(mark.alias("mark"), F.col("_id").alias("id"), F.col("size").alias("size"))
    up = (F.col("rate") > F.floor("rate")) & (F.col("rate") < CAP) & (F.col("copies") == F.floor("rate"))
    down = (F.col("rate") > F.floor("rate")) & (F.col("copies") > F.floor("rate"))
    near = made.groupBy("k", F.floor(F.log2("size")).alias("_class"), F.pmod(mark, F.lit(4)).alias("_part")).agg(
        F.first("target").alias("target"), F.sum(F.col("copies") * F.col("size")).alias("taken"), F.min(F.when(up, one)).alias("up"), F.min(F.when(down, one)).alias("down")
    )
    near = materialize(near, "near")
    off = near.groupBy("k").agg((F.first("target") - F.sum("taken")).alias("off"))
    picked = near.select("k", F.inline(F.array(F.struct(F.col("up").alias("x"), F.lit(1).alias("step")), F.struct(F.col("down").alias("x"), F.lit(-1).alias("step"))))).filter("x is not null")
    picked = materialize(picked.select("k", F.col("x.id").alias("_id"), F.col("x.size").alias("size"), "step"), "picked")
    same = [F.col("a.k") == F.col("b.k"), F.col("a.size") == F.col("b.size"), F.col("a._id").eqNullSafe(F.col("b._id"))]
    rows = sized.alias("a").join(picked.alias("b"), same).groupBy("b.k", "b._id", "b.size", "b.step").agg(F.count("*").alias("n"))
    rows = rows.select("k", "_id", "size", "step", (F.col("n") * F.col("size")).alias("weight")).join(off, "k")
    kind = sized.schema["_id"].dataType.simpleString()

    def work(group):
        return turned(group)

    work.__annotations__ = {"group": pa.Table, "return": pa.Table}
    ship(sized.sparkSession)
    return materialize(rows.groupBy("k").applyInArrow(work, f"k long, _id {kind}, size long, step int"), "changes")


def turned(group: pa.Table) -> pa.Table:
    """The rows of one source's candidates that are rounded the other way."""
    off, weight, step = group["off"][0].as_py(), group["weight"].to_pylist(), group["step"].to_pylist()
    taken = []
    for i in sorted(range(len(weight)), key=lambda i: (-weight[i], step[i], str(group["_id"][i].as_py()))):
        moved = off - step[i] * weight[i]
        if abs(moved) < abs(off):
            taken.append(i)
            off = moved
    out = group.take(pa.array(taken, pa.int64())).select(["k", "_id", "size", "step"])
    return out.set_column(0, "k", out["k"].cast(pa.int64())).set_column(3, "step", out["step"].cast(pa.int32()))


def mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", slim: bool = False) -> DataFrame:
    """docs with size, source_size, target, copies and taken = copies * size.

    Sources in code-point order, null last, weigh 1, 2, 3, repeating; targets are those of
    shares(). Within a source the rates minimise relative entropy against one copy each,
    subject to the words taken being the target and to the cap of 3 copies; they are
    rounded by a fixed hash of the id and size, so reruns agree, and a few documents the other way (changes()). Rows with equal id and size
    in a source get equal copies. Null and blank texts have size 0 and take nothing. An
    empty table gives an empty one. The parameters of more than MOST_SOURCES sources stay in a
    table (wide_parameters), so that the number of sources is not limited. Columns of docs named as the new ones
    are replaced. With slim only the id and the new columns are returned, and texts are read once.
    """
    spark = docs.sparkSession
    plain = docs.select(col(id_col)) if slim else without(docs, OUTPUTS)
    sized = docs.select(F.struct(*[col(c) for c in plain.columns]).alias("_doc"), col(id_col).alias("_id"), col(source_col).cast("string").alias("_named"), words_in(col(text_col)).alias("size"))
    slim_rows = materialize(sized.select("_id", F.col("_named").alias("_source"), "size"), "sizes")
    sources = find_sources(slim_rows)
    if sources is None:
        keyed, found = wide_parameters(slim_rows)
    else:
        keyed = materialize(attach(slim_rows, sources, "_source").select("_id", "size", "k"), "keyed")
        histogram = materialize(keyed.filter("size > 0").groupBy("k", "size").agg(F.count("*").alias("n")), "histogram")
        solve(spark, histogram, sources)
        settle_rounding(spark, keyed.filter("size > 0"), sources)
        found = parameters(spark, sources)
    turns = changes(keyed.filter("size > 0"), found).select(F.col("k").alias("_k"), F.col("_id").alias("_turned"), F.col("size").alias("_size"), "step")
    if slim:
        sized = slim_rows.select(F.struct(F.col("_id").alias(id_col)).alias("_doc"), "_id", F.col("_source").alias("_named"), "size")
    made = sized.join(found, F.col("_named").eqNullSafe(F.col("_source"))).withColumn("rate", rate()).withColumn("margin", margin("_id"))
    made = made.join(turns, (F.col("k") == F.col("_k")) & F.col("_id").eqNullSafe(F.col("_turned")) & (F.col("size") == F.col("_size")), "left")
    made = made.withColumn("copies", (copies() + F.coalesce("step", F.lit(0))).cast("bigint"))
    return made.select(*[F.col(f"_doc.{quoted(c)}").alias(c) for c in plain.columns], "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def find_sources(slim: DataFrame) -> list[Source] | None:
    """The sources with their targets; None where there are more than MOST_SOURCES."""
    rows = slim.groupBy("_source").agg(F.sum("size").alias("size"), F.count("*").alias("n")).limit(MOST_SOURCES + 1).collect()
    if len(rows) > MOST_SOURCES:
        return None
    rows.sort(key=lambda r: (r["_source"] is None, r["_source"] or ""))
    targets = shares([r["size"] for r in rows], [CYCLE[i % len(CYCLE)] for i in range(len(rows))])
    found = [Source(r["_source"], r["size"], r["n"], t) for r, t in zip(rows, targets, strict=True)]
    for x in found:
        if x.fixed is None:
            x.dual = math.log(x.target / x.size)
    return found


def attach(df: DataFrame, sources: list[Source], name: str) -> DataFrame:
    side = parameters(df.sparkSession, sources).select("k", F.col("_source").alias("_named"))
    return df.join(F.broadcast(side), F.col(name).eqNullSafe(F.col("_named"))).drop("_named")


def wide_parameters(slim: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The documents with their sources' numbers, and what parameters() gives after solve() and settle_rounding(), with one row a source that never leaves the executors."""
    sources = wide_sources(slim)
    names = sources.select("k", F.col("_source").alias("_named"))
    keyed = materialize(slim.join(names, F.col("_source").eqNullSafe(F.col("_named"))).select("_id", "size", "k"), "keyed")
    duals = wide_duals(keyed.filter("size > 0").groupBy("k", "size").agg(F.count("*").alias("n")).join(sources.filter("fixed is null").select("k", "target", "mean", "start"), "k"))
    tilt = F.coalesce(F.col("dual") / F.col("mean"), F.lit(0.0))
    found = sources.join(duals, "k", "left").select("k", "_source", "source_size", "target", tilt.alias("tilt"), "fixed", F.array(*[F.lit(0.0)] * 3).alias("thresholds"), "mean", F.lit(-1.0).alias("below"), F.lit(2.0).alias("width"))
    return keyed, wide_rounding(keyed.filter("size > 0"), materialize(found, "parameters"))


def wide_sources(slim: DataFrame) -> DataFrame:
    """(k, _source, source_size, target, fixed, mean, start): sources in code-point order, null last, with the targets of shares()."""
    from pyspark.sql import Window

    sums = slim.groupBy("_source").agg(F.sum("size").alias("source_size"), F.count("*").alias("docs"))
    dealt = materialize(sums.repartitionByRange(F.col("_source").asc_nulls_last()).withColumn("_part", F.spark_partition_id()), "sources")
    before, starts = 0, []
    for r in sorted(dealt.groupBy("_part").agg(F.count("*").alias("n")).collect()):
        starts.append((r["_part"], before))
        before += r["n"]
    offset = F.broadcast(slim.sparkSession.createDataFrame(starts, "_part int, _before long"))
    place = F.row_number().over(Window.partitionBy("_part").orderBy(F.col("_source").asc_nulls_last()))
    k = F.col("_before") + place - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in CYCLE]), (k % len(CYCLE) + 1).cast("int"))
    ranked = materialize(dealt.join(offset, "_part").select(k.alias("k"), "_source", "source_size", "docs", weight.alias("weight")), "ranked")
    most, over, count = CAP * F.col("source_size"), F.lit(False), 0
    while True:
        r = ranked.filter("source_size > 0").agg(
            F.sum("source_size").alias("all"), F.sum(F.when(over, most)).alias("gone"), F.sum(F.when(~over, F.col("weight"))).alias("open"), F.count(F.when(over, 1)).alias("n")
        ).first()
        closed, count = over, r["n"]
        if not r["open"]:
            share = F.lit(0.0)
            break
        share = F.lit(float(r["all"] - (r["gone"] or 0))) * F.col("weight") / F.lit(r["open"])
        over = share > most
        if ranked.filter("source_size > 0").filter(over).count() <= count:
            break
    size = F.col("source_size")
    target = F.when(size <= 0, 0.0).when(closed, most.cast("double")).otherwise(share)
    out = ranked.withColumns({"target": target, "mean": size / F.greatest(F.lit(1), F.col("docs"))})
    fixed = F.when((size == 0) | (F.col("target") <= 0), 0.0).when(F.col("target") >= CAP * size * F.lit(1 - 1e-12), float(CAP))
    return materialize(out.select("k", "_source", "source_size", "target", fixed.alias("fixed"), "mean", F.when(fixed.isNull(), F.log(F.col("target") / size)).alias("start")), "targets")


def wide_duals(rows: DataFrame) -> DataFrame:
    """(k, dual) from (k, size, n, target, mean, start): the iterations of solve(), where the counts of a source lie.

    A task goes through its sources in order and holds a batch and what is left of the last source.
    """

    def work(batches):
        left = None
        for batch in batches:
            got = pa.Table.from_batches([batch])
            got = got if left is None else pa.concat_tables([left, got])
            k = got["k"].to_numpy()
            cut = int(np.searchsorted(k, k[-1])) if len(k) else 0
            left = got.slice(cut).combine_chunks()
            if cut:
                yield newton(got.slice(0, cut))
        if left is not None and left.num_rows:
            yield newton(left)

    return map_arrow(rows.select("k", "size", "n", "target", "mean", "start").repartition("k").sortWithinPartitions("k"), work, "k long, dual double")


def newton(rows: pa.Table, tolerance: float = 1e-9, most: int = 60) -> pa.RecordBatch:
    """The duals of all sources of rows in order of k."""
    k, size, n = (rows[c].to_numpy() for c in ("k", "size", "n"))
    at = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
    target, mean, dual = (rows[c].to_numpy()[at].astype(float) for c in ("target", "mean", "start"))
    of = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(k))))
    low, high, settled = np.full(len(at), -np.inf), np.full(len(at), np.inf), np.zeros(len(at), bool)
    with np.errstate(all="ignore"):
        for _ in range(most):
            if settled.all():
                break
            rates = np.minimum(CAP, np.exp(np.minimum(60.0, (dual / mean)[of] * size)))
            words = n * size * rates
            f, g = np.add.reduceat(words, at), np.add.reduceat(np.where(rates < CAP, words * size, 0.0), at) / mean
            off = np.log(target) - np.log(np.maximum(f, 1e-300))
            settled |= np.abs(off) <= tolerance
            go = ~settled
            low = np.where(go & (off > 0), np.maximum(low, dual), low)
            high = np.where(go & (off <= 0), np.minimum(high, dual), high)
            step = np.where(g > 0, dual + off * f / g, np.inf)
            bent = np.where(np.isfinite(low + high), (low + high) / 2, np.where(off > 0, 2 * dual + 1, 2 * dual - 1))
            step = np.where((low < step) & (step < high), step, bent)
            near = np.abs(step - dual) <= 1e-13 * np.maximum(1.0, np.abs(step))
            dual = np.where(go, step, dual)
            settled |= go & near
    return pa.RecordBatch.from_arrays([pa.array(k[at], pa.int64()), pa.array([float(f"{x:.9g}") for x in dual], pa.float64())], ["k", "dual"])


def wide_rounding(sized: DataFrame, found: DataFrame, levels: int = 2) -> DataFrame:
    """found with the thresholds of settle_rounding()."""
    for c in range(3):
        found = found.withColumns({"below": F.lit(-1.0), "width": F.lit(2.0)})
        for _ in range(levels):
            cut = F.col("width") / BINS
            start = F.col("below") + F.col("e.bin") * cut
            short, over = F.col("e.want") - (F.col("e.upto") - F.col("e.extra")), F.col("e.upto") - F.col("e.want")
            held = F.when(F.col("e").isNull(), F.col("below") + F.col("width")).when(short <= over, start).otherwise(start + cut)
            changed = {"thresholds": F.array(*[held if i == c else F.col("thresholds")[i] for i in range(3)]), "below": F.coalesce(start, "below"), "width": F.when(F.col("e").isNull(), F.col("width")).otherwise(cut)}
            found = materialize(found.join(edges(sized.join(found, "k"), c), "k", "left").withColumns(changed).drop("e"), "parameters")
    return found


def op10_mixing(spark, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken (and copies) for every document."""
    return mix(table(spark, sf_dir, "documents").select("doc_id", "source", "text"), slim=True).select("doc_id", "size", "source_size", "target", "taken", "copies")


def take_mix(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: each document as often as the mix takes it, with the documents' own columns. Null and blank
    texts have no words and are not taken; null sources are one source; an empty table stays empty."""
    mixed = mix(docs)
    return mixed.filter("copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*[col(c) for c in docs.columns])
