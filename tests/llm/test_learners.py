import random
import re

import numpy as np
import pytest

from distinct_bounds.llm import language, quality, rules, toxicity
from distinct_bounds.llm.common import id_remainder


def prose(rng, letters="abcdefghij", n=60):
    return " ".join("".join(rng.choice(letters) for _ in range(rng.randint(2, 6))) for _ in range(n))


@pytest.fixture(scope="module")
def corpus(spark):
    rng = random.Random(3)
    docs, labels = [], []
    for i in range(400):
        text, bad, toxic = prose(rng), i % 4 == 0, i % 5 == 0
        if bad:
            text = " ".join(w + "###" for w in text.split())
        if toxic:
            text = text.replace(" ", " zorgle ", 3)
        docs.append((i, text, "xx", 0.5))
        labels.append((i, 0 if bad else 1, 1 if toxic else 0))
    docs += [(400, None, None, 1.0), (401, "", "xx", 1.0), (None, "some words", None, None), (0, docs[0][1], "xx", 0.5), (402, "word " * 100_000, "xx", 0.1)]
    labels += [(401, None, None), (None, 1, 0), (0, 0, 1), (9999, 1, 1)]
    return spark.createDataFrame(docs, "doc_id long, text string, lang string, SCORE double").coalesce(2), spark.createDataFrame(labels, "doc_id long, quality int, toxic int").coalesce(2)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_quality_learns_and_keeps_every_row(corpus):
    docs, labels = corpus
    scored = quality.score(docs, quality.train(docs, labels, learn=id_remainder("doc_id", 5) != 0))
    assert scored.columns == ["doc_id", "text", "lang", "score"] and scored.count() == docs.count()
    got = by_id(scored)
    held = {r["doc_id"] for r in docs.filter(id_remainder("doc_id", 5) == 0).collect()} & set(range(400))
    assert np.mean([(got[i]["score"] >= 0.5) == (i % 4 != 0) for i in held]) > 0.95
    assert all(0 <= got[i]["score"] <= 1 for i in (400, 401, None, 402)) and got[400]["score"] == got[401]["score"]


def test_quality_without_labels_is_one_half(corpus):
    docs, labels = corpus
    model = quality.train(docs, labels.limit(0))
    assert {r["score"] for r in quality.score(docs, model).collect()} == {0.5}
    assert quality.score(docs.limit(0), model).count() == 0


def test_leader_updates_match_a_plain_loop():
    spec = quality.QualitySpec(bits=4, epochs=2, updates=0, l1=0.1)
    rng = np.random.default_rng(1)
    rows = [(np.sort(rng.choice(16, 3, replace=False)), rng.random(3).astype(np.float32), int(rng.random() < 0.5)) for _ in range(40)]
    z, n, w = [0.0] * 17, [0.0] * 17, [0.0] * 17
    for _ in range(2):
        for at, x, y in rows:
            at, x = [*at.tolist(), 16], [*x.tolist(), 1.0]
            for i in at:
                l1 = 0 if i == 16 else spec.l1
                w[i] = 0.0 if abs(z[i]) <= l1 else -(z[i] - np.sign(z[i]) * l1) / ((spec.beta + n[i] ** 0.5) / spec.alpha + spec.l2)
            p = 1 / (1 + np.exp(-sum(w[i] * v for i, v in zip(at, x))))
            for i, v in zip(at, x):
                g = (p - y) * v
                s = ((n[i] + g * g) ** 0.5 - n[i] ** 0.5) / spec.alpha
                z[i] += g - s * w[i]
                n[i] += g * g
    model = quality.follow_the_leader(rows, spec)
    for i in range(16):
        want = 0.0 if abs(z[i]) <= spec.l1 else -(z[i] - np.sign(z[i]) * spec.l1) / ((spec.beta + n[i] ** 0.5) / spec.alpha + spec.l2)
        assert model.weights[i] == pytest.approx(want, rel=1e-4, abs=1e-6)


def test_toxicity_finds_the_word_and_leaves_others(corpus):
    docs, labels = corpus
    model = toxicity.train(docs, labels, learn=id_remainder("doc_id", 3) != 1)
    got = by_id(toxicity.score(docs, model))
    held = {r["doc_id"] for r in docs.filter(id_remainder("doc_id", 3) == 1).collect()} & set(range(1, 400))
    assert np.mean([(got[i]["score"] >= 0.7) == (i % 5 == 0) for i in held]) > 0.98
    assert got[400]["score"] == got[401]["score"]
    base = toxicity.train(docs, labels.filter("toxic = 0"))
    assert len({r["score"] for r in toxicity.score(docs, base).collect()}) == 1


def test_toxicity_ratio_is_the_naive_bayes_one(spark):
    docs = spark.createDataFrame([(i, "abcd" if i < 30 else "wxyz") for i in range(60)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 30)) for i in range(60)], "doc_id long, toxic int")
    spec = toxicity.ToxicitySpec(orders=(4,), z=1.0)
    model = toxicity.train(docs, labels, spec)
    at = np.unique(np.concatenate(list(toxicity.buckets("abcd", spec))))
    assert np.allclose(model.scale[at], np.log((31 / 32) / (1 / 32)), atol=1e-5)


def test_languages(spark):
    rng = random.Random(4)
    docs = [(i, prose(rng, "abcdef" if i % 2 else "uvwxyz", 30), "aa" if i % 2 else "uu") for i in range(200)]
    docs += [(1000, None, "aa"), (1001, " 12 ²!", "aa"), (1002, "fade", None), (None, "zyx", None), (1003, "qqqq", None)]
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string")
    model = language.train(df, learn=id_remainder("doc_id", 5) != 0)
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.identify(df, model).collect()}
    assert all(got[i][0] == ("aa" if i % 2 else "uu") for i in range(200))
    assert got[1000] == got[1001] == ("und", 0.0)
    assert got[1002][0] == "aa" and got[None][0] == "uu" and got[1003][0] in ("aa", "uu")
    assert all(0 <= s <= 1 for _, s in got.values())
    none = language.train(df.limit(0))
    assert {r["lang_pred"] for r in language.identify(df, none).collect()} == {"und"}


def test_unseen_words_back_off_to_shorter_grams():
    model = language.fit([("aa", "abcab", 5), ("bb", "bcabc", 5)], ("aa", "bb"), language.LanguageSpec(least=1))
    whole, part = model.unseen(["abcab"])[0], model.unseen(["zzabcz"])[0]
    assert whole[0] > whole[1] and part.any() and not model.unseen(["zzz"])[0][:0].size
    key = {n: dict(zip(model.keys[n].tolist(), model.logs[n], strict=True)) for n in model.spec.orders}
    padded = "^abq$"
    codes = np.frombuffer(padded.encode("utf-32-le"), np.uint32).astype(np.uint64)
    want = np.zeros(2)
    for i in range(len(padded)):
        for n in model.spec.orders:
            if i + n <= len(padded):
                k = int(language.gram_keys(codes[i : i + n], n)[0])
                if k in key[n]:
                    want += key[n][k]
                    break
    assert np.allclose(model.unseen(["abq"])[0], want, atol=1e-4)


def plain_statistics(text):
    words = [(m.start(), m.group()) for m in re.finditer(r"[^\x20\x09-\x0D]+", text or "")]
    w = [x for _, x in words]
    windows = {}
    for i in range(len(w) - 4):
        windows.setdefault(tuple(w[i : i + 5]), []).append(i)
    covered = {i + k for at in windows.values() if len(at) > 1 for i in at for k in range(5)}
    seen, dups = set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dups += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), dups, len(covered)


def test_statistics_equal_brute_force():
    rng = random.Random(8)
    pieces = ["a", "b", "c", "é#", "x|y", "\n", " ", "\t", "\x0b", "\x1c", "a b c a b c", "\na b\n"]
    for _ in range(2000):
        text = "".join(rng.choice(pieces) + rng.choice(["", " "]) for _ in range(rng.randint(0, 40)))
        assert rules.statistics(text)[:5] == plain_statistics(text), repr(text)
    assert rules.statistics(None)[:5] == (0, 0, 0, 0, 0)
    long = " ".join(f"w{i % 9001}" for i in range(30_000))
    assert rules.statistics(long)[:5] == plain_statistics(long)


def test_trees_are_monotone_and_flat_arrays_agree():
    rng = np.random.default_rng(2)
    x = rng.random((1500, len(rules.FEATURES)))
    y = (x[:, 0] + 0.5 * np.sin(9 * x[:, 2]) - x[:, 2] + 0.2 * rng.standard_normal(1500) > 0.3).astype(float)
    signs = np.array([s for _, s in rules.FEATURES])
    trees = rules.boost(x, y, signs, rules.RuleSpec(trees=20))
    assert ((trees.margin(x) > 0) == y).mean() > 0.8

    def walk(row):
        total = trees.base
        for at in trees.roots:
            while trees.left[at] != at:
                at = trees.left[at] if row[trees.feature[at]] <= trees.cut[at] else trees.right[at]
            total += trees.value[at]
        return total

    assert np.allclose(trees.margin(x[:50]), [walk(r) for r in x[:50]])
    for j in np.flatnonzero(signs):
        grid = np.repeat(x[:40], 30, axis=0)
        grid[:, j] = np.tile(np.linspace(0, 1, 30), 40)
        steps = np.diff(trees.margin(grid).reshape(40, 30), axis=1)
        assert (signs[j] * steps >= -1e-9).all()


def test_rules_judge_and_edges(corpus):
    docs, labels = corpus
    judged = rules.judge(docs, rules.train(docs, labels))
    got = by_id(judged)
    assert judged.count() == docs.count() and "SCORE" not in judged.columns
    assert all(got[i]["base_failed"] and not got[i]["kept"] and got[i]["n_words"] == 0 for i in (400, 401))
    assert got[402]["base_failed"] and got[402]["n_repeat_words"] == got[402]["n_words"] == 100_000
    assert np.mean([got[i]["kept"] == (i % 4 != 0) for i in range(1, 400)]) > 0.95
    none = rules.train(docs, labels.limit(0))
    assert rules.judge(docs.limit(0), none).count() == 0
