"""Language: known words by their frequency in each language, unseen words by ever shorter character n-grams."""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import CHUNK, col, id_remainder, map_arrow, table, text_udf, with_outputs

OUTPUTS = ("lang_pred", "score")
WORDS = re.compile(r"[^\W\d_]+").findall
UNKNOWN = "und"
STEP = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class LanguageSpec:
    """sample: documents of each language that are learnt from, in expectation; vocabulary: words kept of each language."""

    sample: int = 2000
    vocabulary: int = 30_000
    least: int = 2
    orders: tuple[int, ...] = (5, 4, 3, 2, 1)
    grams: int = 30_000
    smoothing: float = 0.5


def words_of(text: str | None) -> list[str]:
    """Lower-cased runs of letters; characters that only look like letters are cut out."""
    if not text:
        return []
    found = WORDS(text.lower())
    if all(map(str.isalpha, found)):
        return found
    return [w for x in found for w in "".join(c if c.isalpha() else " " for c in x).split()]


def gram_keys(codes: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit key of the n characters that begin at each position where n fit."""
    h = codes[: len(codes) - n + 1].astype(np.uint64)
    for k in range(1, n):
        h = (h ^ (h >> np.uint64(29))) * STEP + codes[k : len(codes) - n + 1 + k]
    return (h + np.uint64(n)) * STEP


@dataclass(frozen=True)
class LanguageModel:
    """words: row of each known word in word_logs; keys and logs: for each order, sorted keys and their rows."""

    langs: tuple[str, ...]
    words: dict[str, int]
    word_logs: np.ndarray
    keys: dict[int, np.ndarray]
    logs: dict[int, np.ndarray]
    prior: np.ndarray
    spec: LanguageSpec

    def unseen(self, words: list[str]) -> np.ndarray:
        """Log frequencies of unseen words: at each position of the padded word the longest known
        n-gram counts; positions of which not even one character is known count for nothing."""
        padded = [f"^{w}$" for w in words]
        lengths = np.fromiter(map(len, padded), np.int64, len(padded))
        codes = np.frombuffer("".join(padded).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
        ends = np.repeat(np.cumsum(lengths), lengths)
        at = np.arange(len(codes))
        out, open_ = np.zeros((len(codes), len(self.langs)), np.float32), np.ones(len(codes), bool)
        for n in self.spec.orders:
            known = self.keys.get(n)
            if known is None or not len(known) or len(codes) < n:
                continue
            todo = np.flatnonzero(open_[: len(codes) - n + 1] & (at[: len(codes) - n + 1] + n <= ends[: len(codes) - n + 1]))
            keys = gram_keys(codes, n)[todo]
            place = np.minimum(np.searchsorted(known, keys), len(known) - 1)
            hit = known[place] == keys
            out[todo[hit]] = self.logs[n][place[hit]]
            open_[todo[hit]] = False
        return np.add.reduceat(out, np.cumsum(lengths) - lengths, axis=0)

    def scorer(self):
        """Words met before, known or not, keep their row; the memory is emptied when it is large."""
        fixed = len(self.words)
        memory = dict(self.words)
        rows = np.zeros((1 << 16, len(self.langs)), np.float32)
        if fixed > len(rows):
            rows = np.zeros((2 * fixed, len(self.langs)), np.float32)
        rows[:fixed] = self.word_logs
        most = fixed + 300_000

        def score(texts):
            nonlocal memory, rows
            if len(memory) > most:
                memory = dict(self.words)
            lists = [words_of(t) for t in texts]
            new = list({w for x in lists for w in x if w not in memory}) if self.langs else []
            if new:
                first = len(memory)
                if first + len(new) > len(rows):
                    rows = np.concatenate([rows, np.zeros((max(len(rows), len(new)), len(self.langs)), np.float32)])
                rows[first : first + len(new)] = self.unseen(new)
                memory.update(zip(new, range(first, first + len(new)), strict=True))
            names, scores = [], np.zeros(len(texts))
            for i, found in enumerate(lists):
                if not found or not self.langs:
                    names.append(UNKNOWN)
                    continue
                total = self.prior + rows[np.fromiter(map(memory.__getitem__, found), np.int64, len(found))].sum(axis=0, dtype=np.float64)
                best = int(total.argmax())
                names.append(self.langs[best])
                scores[i] = 1 / np.exp(total - total[best]).sum()
            return names, scores

        return score


def word_counts(sample: DataFrame) -> DataFrame:
    """(lang, word, n) over the sample's texts; a task adds up its own part first."""

    def work(batches):
        for batch in batches:
            counts: dict[str, Counter] = {}
            for at in range(0, batch.num_rows, CHUNK):
                part = batch.slice(at, CHUNK)
                for text, lang in zip(part.column("text").to_pylist(), part.column("lang").to_pylist(), strict=True):
                    counts.setdefault(lang, Counter()).update(words_of(text))
            flat = [(lang, w, n) for lang, c in counts.items() for w, n in c.items()]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in flat], pa.string()), pa.array([x[1] for x in flat], pa.string()), pa.array([x[2] for x in flat], pa.int64())], ["lang", "word", "n"])

    return map_arrow(sample.select("text", "lang"), work, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def train(docs: DataFrame, spec: LanguageSpec = LanguageSpec(), learn=None, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id") -> LanguageModel:
    """Learn from documents with text and language for which `learn` holds.

    Of each language about spec.sample documents are read, chosen by a hash of the id, so
    rare languages are read in full. The driver gets the spec.vocabulary most frequent
    words of each language, ties by the word. Without a labelled document every text is
    'und' with score 0.
    """
    told = docs.filter(col(text_col).isNotNull() & col(lang_col).isNotNull() & (F.lit(True) if learn is None else learn))
    told = told.select(col(id_col).alias("id"), col(text_col).alias("text"), col(lang_col).alias("lang"))
    sizes = {r["lang"]: r["n"] for r in told.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    langs = tuple(sorted(sizes))
    if not langs:
        return LanguageModel((), {}, np.zeros((0, 0), np.float32), {}, {}, np.zeros(0), spec)
    share = F.create_map(*[F.lit(x) for lang in langs for x in (lang, min(1.0, spec.sample / sizes[lang]))])
    chosen = told.filter(F.pmod(F.xxhash64("id", F.lit("language")), F.lit(1 << 30)) < share[F.col("lang")] * (1 << 30))
    from pyspark.sql import Window

    most = Window.partitionBy("lang").orderBy(F.desc("n"), "word")
    top = word_counts(chosen).filter(F.col("n") >= spec.least).withColumn("k", F.row_number().over(most)).filter(F.col("k") <= spec.vocabulary)
    got = top.select("lang", "word", "n").toArrow()
    return fit([(a, b, c) for a, b, c in zip(*(got[x].to_pylist() for x in ("lang", "word", "n")), strict=True)], langs, spec)


def logs_of(counts: dict, langs: tuple[str, ...], smoothing: float) -> tuple[list, np.ndarray]:
    """Entries in order and, for each language, the log of their smoothed share."""
    names = sorted(counts)
    table_ = np.array([counts[x] for x in names], float).reshape(len(names), len(langs)) + smoothing
    return names, np.log(table_ / table_.sum(axis=0)).astype(np.float32)


def fit(counted: list[tuple[str, str, int]], langs: tuple[str, ...], spec: LanguageSpec) -> LanguageModel:
    column = {x: i for i, x in enumerate(langs)}
    words: dict[str, list] = {}
    for lang, word, n in counted:
        words.setdefault(word, [0] * len(langs))[column[lang]] += n
    names, word_logs = logs_of(words, langs, spec.smoothing)
    keys, logs = {}, {}
    for n in spec.orders:
        grams: dict[str, list] = {}
        for word, by in words.items():
            padded = f"^{word}$"
            for i in range(len(padded) - n + 1):
                held = grams.setdefault(padded[i : i + n], [0] * len(langs))
                for k, x in enumerate(by):
                    held[k] += x
        kept = dict(sorted(((g, x) for g, x in grams.items() if sum(x) >= spec.least), key=lambda e: (-sum(e[1]), e[0]))[: spec.grams])
        texts, rows = logs_of(kept, langs, spec.smoothing) if kept else ([], np.zeros((0, len(langs)), np.float32))
        key = np.array([gram_keys(np.frombuffer(g.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64), n)[0] for g in texts], np.uint64)
        order = np.argsort(key)
        keys[n], logs[n] = key[order], rows[order]
    return LanguageModel(langs, {w: i for i, w in enumerate(names)}, word_logs, keys, logs, np.zeros(len(langs)), spec)


def identify(docs: DataFrame, model: LanguageModel, text_col: str = "text") -> DataFrame:
    """docs with lang_pred and score, the share of the likeliest language, 0 to 1.

    A null text or one without a letter is 'und' with score 0. Between equally likely
    languages the first by code point wins. Every row is returned, repeated ones too.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)
    return with_outputs(docs, text_udf("lang_pred string, score double", OUTPUTS, lambda: held.value.scorer()), text_col, OUTPUTS)


def op7_language(spark, sf_dir: str) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document."""
    docs = table(spark, sf_dir, "documents")
    model = train(docs.select("doc_id", "text", "lang"), learn=id_remainder("doc_id", 5) != 0)
    return identify(docs.select("doc_id", "text"), model).select("doc_id", (id_remainder("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")
