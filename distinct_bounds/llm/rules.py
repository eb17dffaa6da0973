"""Quality rules: document statistics, fixed base rules and gradient-boosted trees with monotonic constraints."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import id_remainder, labelled_sample, table, text_udf, with_outputs

SPACES = " \t\n\r\x0b\x0c"
SYMBOLS = "#*$%&|<>"
WINDOW = 5
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
OUTPUTS = (*STATS, "base_failed", "score", "kept")
UPPER = bytes(range(65, 91))
DIGITS = bytes(range(48, 58))
#: The trees' inputs and the sign of each one's effect on quality: -1 may only lower it, 0 is free.
FEATURES = (("log_words", 0), ("mean_word", 0), ("symbol_share", -1), ("dup_line_share", -1), ("repeat_share", -1), ("upper_share", 0), ("digit_share", 0), ("words_a_line", 0))


def repeated_words(ids: np.ndarray) -> int:
    """Words that lie in a window of WINDOW words found at least twice; ids number the distinct words."""
    n = len(ids) - WINDOW + 1
    if n < 2:
        return 0
    distinct = int(ids.max()) + 1
    if distinct**WINDOW < 1 << 62:
        key = ids[:n].copy()
        for k in range(1, WINDOW):
            key *= distinct
            key += ids[k : n + k]
    else:  # number the distinct prefixes again after each word, so that keys never overflow
        key = ids[:n]
        for k in range(1, WINDOW):
            key = np.unique(key * distinct + ids[k : n + k], return_inverse=True)[1]
    order = np.argsort(key, kind="stable")
    same = np.diff(key[order]) == 0
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(len(ids) + 1, np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edge, at, 1)
    np.subtract.at(edge, at + WINDOW, 1)
    return int((np.cumsum(edge)[:-1] > 0).sum())


def statistics(text: str | None) -> tuple[int, int, int, int, int, float, float, int]:
    """STATS, then the shares of capitals and digits among the bytes, and the lines with a word."""
    if not text:
        return 0, 0, 0, 0, 0, 0.0, 0.0, 0
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    if not words:
        return 0, 0, sum(map(text.count, SYMBOLS)), 0, 0, 0.0, 0.0, 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
    return (
        len(words),
        len(text) - sum(map(text.count, SPACES)),
        sum(map(text.count, SYMBOLS)),
        len(lines) - len(set(lines)),
        repeated_words(ids),
        1 - len(raw.translate(None, UPPER)) / len(raw),
        1 - len(raw.translate(None, DIGITS)) / len(raw),
        len(lines),
    )


def inputs(rows: np.ndarray) -> np.ndarray:
    """FEATURES of statistics() rows."""
    n, chars, symbols, dups, repeats, upper, digits, lines = np.asarray(rows, float).reshape(-1, 8).T
    some = np.maximum(n, 1)
    return np.column_stack([np.log1p(n), chars / some, symbols / np.maximum(chars, 1), dups / np.maximum(lines, 1), repeats / some, upper, digits, n / np.maximum(lines, 1)])


def base_failed(rows: np.ndarray) -> np.ndarray:
    rows = np.asarray(rows, float).reshape(-1, 8)
    return (rows[:, 0] < 10) | (100 * rows[:, 4] > 20 * rows[:, 0])


@dataclass(frozen=True)
class RuleSpec:
    """sample bounds the labelled documents; the rest are the usual settings of boosted trees."""

    sample: int = 8000
    trees: int = 60
    depth: int = 3
    bins: int = 64
    rate: float = 0.15
    l2: float = 1.0
    least: float = 5.0
    threshold: float = 0.5


@dataclass(frozen=True)
class TreeArrays:
    """All trees' nodes in one array each, a complete binary tree after the other; a leaf's children are itself."""

    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    depth: int
    base: float

    def margin(self, x: np.ndarray) -> np.ndarray:
        at = np.broadcast_to(self.roots, (len(x), len(self.roots))).copy()
        row = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            at = np.where(x[row, self.feature[at]] <= self.cut[at], self.left[at], self.right[at])
        return self.base + self.value[at].sum(axis=1)


def boost(x: np.ndarray, y: np.ndarray, signs: np.ndarray, spec: RuleSpec) -> TreeArrays:
    """Second-order boosting of the logistic loss on histograms of quantile bins.

    A split on a constrained feature must order its children's values by the sign, and the
    midpoint bounds what the subtrees may take, so the sum is monotone in the feature.
    """
    rate = (y.sum() + 1) / (len(y) + 2)
    base = float(np.log(rate / (1 - rate)))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, spec.bins + 1)[1:-1])) if len(x) else np.zeros(0) for j in range(x.shape[1])]
    binned = np.column_stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)]) if len(x) else np.zeros((0, x.shape[1]), int)
    feature, cut, left, right, value, roots = [], [], [], [], [], []
    margin = np.full(len(y), base)

    def node() -> int:
        for held, start in ((feature, 0), (cut, 0.0), (left, len(feature)), (right, len(right)), (value, 0.0)):
            held.append(start)
        left[-1] = right[-1] = len(feature) - 1
        return len(feature) - 1

    def best_split(rows, g, h, low, high):
        total_g, total_h = g[rows].sum(), h[rows].sum()
        most, found = 1e-6, None
        for j, c in enumerate(cuts):
            if not len(c):
                continue
            gl = np.cumsum(np.bincount(binned[rows, j], g[rows], len(c) + 1))[:-1]
            hl = np.cumsum(np.bincount(binned[rows, j], h[rows], len(c) + 1))[:-1]
            gr, hr = total_g - gl, total_h - hl
            vl, vr = np.clip(-gl / (hl + spec.l2), low, high), np.clip(-gr / (hr + spec.l2), low, high)
            v = np.clip(-total_g / (total_h + spec.l2), low, high)
            gain = -(gl * vl + (hl + spec.l2) * vl**2 / 2) - (gr * vr + (hr + spec.l2) * vr**2 / 2) + (total_g * v + (total_h + spec.l2) * v**2 / 2)
            gain[(hl < spec.least) | (hr < spec.least) | (signs[j] * (vr - vl) < 0)] = -np.inf
            k = int(gain.argmax())
            if gain[k] > most:
                most, found = gain[k], (j, k, vl[k], vr[k])
        return found

    def grow(at, rows, g, h, depth, low, high):
        value[at] = spec.rate * float(np.clip(-g[rows].sum() / (h[rows].sum() + spec.l2), low, high))
        split = best_split(rows, g, h, low, high) if depth else None
        if split is None:
            margin[rows] += value[at]
            return
        j, k, vl, vr = split
        feature[at], cut[at] = j, float(cuts[j][k])
        left[at], right[at] = node(), node()
        middle = (vl + vr) / 2
        bounds = {0: ((low, high), (low, high)), 1: ((low, middle), (middle, high)), -1: ((middle, high), (low, middle))}[int(signs[j])]
        goes = binned[rows, j] <= k
        grow(left[at], rows[goes], g, h, depth - 1, *bounds[0])
        grow(right[at], rows[~goes], g, h, depth - 1, *bounds[1])

    if len(np.unique(y)) > 1:
        for _ in range(spec.trees):
            p = 1 / (1 + np.exp(-margin))
            root = node()
            roots.append(root)
            grow(root, np.arange(len(y)), p - y, p * (1 - p), spec.depth, -np.inf, np.inf)
    kinds = ((feature, np.int64), (cut, float), (left, np.int64), (right, np.int64), (value, float), (roots, np.int64))
    return TreeArrays(*[np.array(a, k) for a, k in kinds], spec.depth, base)


def train(docs: DataFrame, labels: DataFrame, spec: RuleSpec = RuleSpec(), label: str = "quality", learn=None, id_col: str = "doc_id", text_col: str = "text") -> TreeArrays:
    """Boost on the statistics of at most spec.sample labelled documents for which `learn` holds.

    With fewer than two classes the trees are empty and every score is the base rate.
    """
    sample = labelled_sample(docs, labels, label, F.lit(True) if learn is None else learn, spec.sample, id_col, text_col)
    told = with_outputs(sample, text_udf("s array<double>", ("s",), lambda: lambda texts: ([list(map(float, statistics(t))) for t in texts],)), "text", ("s",))
    got = told.select("id", "y", "s").toArrow().sort_by("id")
    rows = np.array(got["s"].to_pylist(), float).reshape(-1, 8)
    return boost(inputs(rows), np.asarray(got["y"].to_numpy(), float), np.array([s for _, s in FEATURES]), spec)


def judge(docs: DataFrame, trees: TreeArrays, spec: RuleSpec = RuleSpec(), text_col: str = "text") -> DataFrame:
    """docs with the STATS of the whole text, base_failed, score and kept.

    A null or blank text has no words, fails the base rules and is not kept. Every row is
    returned, repeated ones too; an empty table gives an empty one.
    """
    held = docs.sparkSession.sparkContext.broadcast(trees)

    def make():
        def work(texts):
            rows = np.array([statistics(t) for t in texts], float).reshape(-1, 8)
            failed = base_failed(rows)
            score = 1 / (1 + np.exp(-np.clip(held.value.margin(inputs(rows)), -40, 40)))
            return (*[rows[:, k].astype(np.int64) for k in range(5)], failed, score, ~failed & (score >= spec.threshold))

        return work

    return with_outputs(docs, text_udf(", ".join(f"{s} long" for s in STATS) + ", base_failed boolean, score double, kept boolean", OUTPUTS, make), text_col, OUTPUTS)


def op3_rules(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept (and score)."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    trees = train(docs, table(spark, sf_dir, "labels"), learn=id_remainder("doc_id", 5) != 0)
    return judge(docs, trees).select("doc_id", *STATS, "base_failed", "kept", "score")
