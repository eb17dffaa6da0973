"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import CHUNK, col, id_remainder, labelled_sample, map_arrow, materialize, table, text_udf, with_outputs

OUTPUTS = ("score",)
MULTIPLIERS = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))


@dataclass(frozen=True)
class ToxicitySpec:
    """sample bounds the labelled documents; a bucket is a feature where its ratio is at least `ratio`
    and z standard errors away from zero, and no more than `most` are, those of the largest z."""

    bits: int = 20
    orders: tuple[int, ...] = (4, 5, 6, 8)
    sample: int = 20_000
    smoothing: float = 1.0
    z: float = 3.5
    ratio: float = 1.0
    most: int = 30_000
    l2: float = 2e-4
    steps: int = 400
    rate: float = 0.3


def buckets(text: str | None, spec: ToxicitySpec):
    """Arrays of the buckets of all character n-grams of the lower-cased text with a space at either end."""
    if not text:
        return
    codes = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    h, done = codes, 1
    for n in spec.orders:
        while done < n and len(h) > 1:
            h = (h[:-1] * MULTIPLIERS[0]) ^ (codes[done:] * MULTIPLIERS[1])
            done += 1
        if done < n:
            return
        yield ((h + np.uint64(n)) * MULTIPLIERS[2]) >> np.uint64(64 - spec.bits)


@dataclass(frozen=True)
class ToxicityModel:
    """scale: the log-count ratio of each kept bucket, 0 elsewhere; weights: the classifier's weight on it."""

    scale: np.ndarray
    weights: np.ndarray
    bias: float
    spec: ToxicitySpec

    def scorer(self):
        product = (self.scale * self.weights).astype(np.float32)

        def score(texts):
            margins = np.empty(len(texts))
            for i, text in enumerate(texts):
                margin = self.bias
                for found in buckets(text, self.spec):
                    hit = found[product[found] != 0]
                    if len(hit):
                        margin += float(product[np.unique(hit)].sum(dtype=np.float64))
                margins[i] = margin
            return (1 / (1 + np.exp(-np.clip(margins, -40, 40))),)

        return score


def presence_counts(sample: DataFrame, spec: ToxicitySpec) -> DataFrame:
    """How many documents of either label hold each bucket: (bucket, pos, neg).

    A task adds up its own documents in two fixed arrays and emits the buckets it met.
    """

    def work(batches):
        counts = np.zeros((2, 1 << spec.bits), np.int32)
        for batch in batches:
            for at in range(0, batch.num_rows, CHUNK):
                part = batch.slice(at, CHUNK)
                for text, y in zip(part.column("text").to_pylist(), part.column("y").to_pylist(), strict=True):
                    if got := list(buckets(text, spec)):
                        counts[1 if y else 0][np.unique(np.concatenate(got))] += 1
        met = np.flatnonzero(counts.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(met.astype(np.int32)), pa.array(counts[1][met]), pa.array(counts[0][met])], ["bucket", "pos", "neg"])

    parts = map_arrow(sample.select("text", "y").coalesce(8), work, "bucket int, pos int, neg int")
    return parts.groupBy("bucket").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))


def train(docs: DataFrame, labels: DataFrame, spec: ToxicitySpec = ToxicitySpec(), label: str = "toxic", learn=None, id_col: str = "doc_id", text_col: str = "text") -> ToxicityModel:
    """Learn from at most spec.sample labelled documents for which `learn` holds.

    The ratio of a bucket is log of its smoothed rate among label 1 over that among label
    0; buckets whose ratio is small or within z standard errors of zero carry no weight. Without
    documents of both labels the score is the smoothed base rate.
    """
    sample = materialize(labelled_sample(docs, labels, label, F.lit(True) if learn is None else learn, spec.sample, id_col, text_col), "labelled")
    totals = {bool(r["y"]): r["n"] for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    pos, neg = totals.get(True, 0), totals.get(False, 0)
    size = 1 << spec.bits
    scale, weights = np.zeros(size, np.float32), np.zeros(size, np.float32)
    base = float(np.log((pos + 1) / (neg + 1)))
    if not pos or not neg:
        return ToxicityModel(scale, weights, base, spec)
    a, b = F.col("pos") + spec.smoothing, F.col("neg") + spec.smoothing
    ratio = F.log(a / (pos + 2 * spec.smoothing)) - F.log(b / (neg + 2 * spec.smoothing))
    told = presence_counts(sample, spec).select("bucket", ratio.alias("ratio"), (F.abs(ratio) / F.sqrt(1 / a + 1 / b)).alias("z")).filter((F.col("z") >= spec.z) & (F.abs("ratio") >= spec.ratio)).orderBy(F.desc("z"), "bucket").limit(spec.most)
    got = told.select("bucket", "ratio").toArrow()
    scale[got["bucket"].to_numpy()] = got["ratio"].to_numpy()

    held = docs.sparkSession.sparkContext.broadcast(scale)

    def make():
        def work(texts):
            out = []
            for text in texts:
                hits = [x[held.value[x] != 0] for x in buckets(text, spec)]
                out.append(np.unique(np.concatenate(hits)).astype(np.int32) if hits else np.zeros(0, np.int32))
            return (out,)

        return work

    rows = with_outputs(sample, text_udf("f array<int>", ("f",), make), "text", ("f",)).select("id", "y", "f").toArrow().sort_by("id")
    lists = rows["f"].combine_chunks()
    flat, ends = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()
    of = np.repeat(np.arange(len(lists)), np.diff(ends))
    used, column = np.unique(flat, return_inverse=True)
    w, bias = descend(of, column, scale[used].astype(np.float64), np.asarray(rows["y"].to_numpy(), float), base, spec)
    weights[used] = w
    return ToxicityModel(scale, weights, bias, spec)


def descend(of: np.ndarray, column: np.ndarray, scale: np.ndarray, y: np.ndarray, base: float, spec: ToxicitySpec) -> tuple[np.ndarray, float]:
    """Regularised logistic regression on presence times ratio, by adaptive full gradients."""
    w, bias = np.zeros(len(scale)), base
    first, second = np.zeros(len(scale) + 1), np.zeros(len(scale) + 1)
    for step in range(1, spec.steps + 1):
        margin = np.bincount(of, (w * scale)[column], len(y)) + bias
        error = (1 / (1 + np.exp(-np.clip(margin, -40, 40))) - y) / len(y)
        grad = np.append(np.bincount(column, error[of], len(scale)) * scale + spec.l2 * w, error.sum())
        first = 0.9 * first + 0.1 * grad
        second = 0.99 * second + 0.01 * grad * grad
        move = spec.rate / np.sqrt(step) * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-8)
        w -= move[:-1]
        bias -= move[-1]
    return w, float(bias)


def score(docs: DataFrame, model: ToxicityModel, text_col: str = "text") -> DataFrame:
    """docs with `score`, the chance of label 1 from the whole text.

    A null or empty text gets the model's base rate. Every row is returned, repeated ones
    too; an empty table gives an empty one.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)
    return with_outputs(docs, text_udf("score double", OUTPUTS, lambda: held.value.scorer()), text_col, OUTPUTS)


def op4_toxicity(spark, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"), learn=id_remainder("doc_id", 3) != 1)
    return score(docs, model).select("doc_id", (id_remainder("doc_id", 3) == 1).alias("held_out"), "score", F.when(col("score") >= 0.7, 1).otherwise(0).alias("predicted"))
