"""Quality: logistic regression on hashed word n-grams, trained by follow-the-regularised-leader."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import col, id_remainder, labelled_sample, table, text_udf, with_outputs

#: Runs of letters and digits are words; so are runs of other visible characters.
TOKENS = re.compile(r"\w+|[^\w\s]+").findall
MIX = np.uint64(0x9E3779B97F4A7C15)
OUTPUTS = ("score",)


class WordHashes(dict):
    """64-bit hash of a word, remembered; emptied when it is large, so memory stays bounded."""

    def __init__(self, most: int = 150_000):
        self.most = most

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        self[word] = found = xxhash.xxh3_64_intdigest(word)
        return found


@dataclass(frozen=True)
class QualitySpec:
    """sample bounds the labelled documents that are learnt from; they are gone through `epochs` times, and
    more often where that makes fewer than `updates` updates; alpha, beta, l1, l2 are the update's constants."""

    bits: int = 18
    orders: int = 2
    sample: int = 4000
    epochs: int = 4
    updates: int = 24_000
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.5


def features(text: str | None, hashes: WordHashes, spec: QualitySpec) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the text's word n-grams and their weights: damped counts of unit length."""
    words = TOKENS(text.lower()) if text else []
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.float32)
    one = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    grams, last = [one], one
    for n in range(1, spec.orders):
        same = last[:-1] == one[n:] if n == 1 else None
        last = (last[:-1] * MIX) ^ (one[n:] + MIX)
        if same is not None:
            last[same] = MIX  # a word twice in a row is one and the same bigram for all words
        grams.append(last)
    buckets = ((np.concatenate(grams) * MIX) >> np.uint64(64 - spec.bits)).astype(np.int64)
    found, counts = np.unique(buckets, return_counts=True)
    value = 1 + np.log(counts)
    return found, (value / np.sqrt(value @ value)).astype(np.float32)


@dataclass(frozen=True)
class QualityModel:
    weights: np.ndarray
    bias: float
    spec: QualitySpec

    def scorer(self):
        hashes = WordHashes()

        def score(texts: list) -> tuple:
            margins = np.empty(len(texts))
            for i, text in enumerate(texts):
                found, value = features(text, hashes, self.spec)
                margins[i] = self.bias + float(self.weights[found] @ value)
            return (1 / (1 + np.exp(-np.clip(margins, -40, 40))),)

        return score


def follow_the_leader(rows: list[tuple[np.ndarray, np.ndarray, int]], spec: QualitySpec) -> QualityModel:
    """Per-coordinate proximal updates; the bias is one more coordinate that is not shrunk to zero."""
    dim = 1 << spec.bits
    lead, squares = np.zeros(dim + 1), np.zeros(dim + 1)
    shrink = np.full(dim + 1, spec.l1)
    shrink[dim] = 0.0

    def weights(at):
        z = lead[at]
        over = np.abs(z) - shrink[at]
        return np.where(over > 0, -np.sign(z) * over / ((spec.beta + np.sqrt(squares[at])) / spec.alpha + spec.l2), 0.0)

    for _ in range(max(spec.epochs, -(-spec.updates // max(1, len(rows))))):
        for found, value, y in rows:
            at, x = np.append(found, dim), np.append(value, 1.0)
            w = weights(at)
            g = (1 / (1 + np.exp(-np.clip(w @ x, -40, 40))) - y) * x
            grown = squares[at] + g * g
            lead[at] += g - (np.sqrt(grown) - np.sqrt(squares[at])) / spec.alpha * w
            squares[at] = grown
    w = weights(np.arange(dim + 1))
    return QualityModel(w[:dim].astype(np.float32), float(w[dim]), spec)


def train(docs: DataFrame, labels: DataFrame, spec: QualitySpec = QualitySpec(), label: str = "quality", learn=None, id_col: str = "doc_id", text_col: str = "text") -> QualityModel:
    """Learn from at most spec.sample labelled documents for which `learn` holds.

    Executors make the features; the driver gets no more than sample sparse rows. Without
    a labelled document every score is one half.
    """
    sample = labelled_sample(docs, labels, label, F.lit(True) if learn is None else learn, spec.sample, id_col, text_col)

    def make():
        hashes = WordHashes()

        def work(texts):
            got = [features(t, hashes, spec) for t in texts]
            return [g[0].astype(np.int32) for g in got], [g[1] for g in got]

        return work

    made = with_outputs(sample, text_udf("f array<int>, v array<float>", ("f", "v"), make), "text", ("f", "v"))
    got = made.select("id", "y", "f", "v").toArrow().sort_by("id")
    order = np.random.default_rng(7).permutation(got.num_rows)
    cols = [got.column(c).combine_chunks() for c in ("f", "v", "y")]
    rows = [(cols[0][i].values.to_numpy(zero_copy_only=False).astype(np.int64), cols[1][i].values.to_numpy(zero_copy_only=False), cols[2][i].as_py()) for i in order.tolist()]
    return follow_the_leader(rows, spec)


def score(docs: DataFrame, model: QualityModel, text_col: str = "text") -> DataFrame:
    """docs with `score`, the chance of label 1 from the whole text.

    A null or empty text has no features and gets the model's base rate. Repeated rows get
    equal scores, every row is returned, an empty table gives an empty one.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)
    return with_outputs(docs, text_udf("score double", OUTPUTS, lambda: held.value.scorer()), text_col, OUTPUTS)


def op1_quality(spark, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"), learn=id_remainder("doc_id", 5) != 0)
    scored = score(docs, model)
    return scored.select("doc_id", (id_remainder("doc_id", 5) == 0).alias("held_out"), "score", F.when(col("score") >= 0.3, 1).otherwise(0).alias("predicted"))


def keep_good(spark, docs: DataFrame, sf_dir: str, threshold: float = 0.3) -> DataFrame:
    """Pipeline stage: the documents whose score reaches the threshold, with their own columns. A null text is scored
    as an empty one; repeated rows stay or go together; an empty table stays empty."""
    model = train(docs, table(spark, sf_dir, "labels"), learn=id_remainder("doc_id", 5) != 0)
    return score(docs, model).filter(col("score") >= threshold).select(*[col(c) for c in docs.columns])
