import hashlib
import math
import random
import re

import pytest
from pyspark.sql import functions as F

from distinct_bounds.llm import bpe, exact, mixing


@pytest.fixture(scope="module")
def vocabulary():
    return bpe.default_vocabulary()


@pytest.fixture(scope="module")
def library(vocabulary):
    tiktoken = pytest.importorskip("tiktoken")
    return tiktoken.Encoding("own", pat_str=vocabulary.pattern, mergeable_ranks={t: i for i, t in enumerate(vocabulary.tokens)}, special_tokens={})


def test_perfect_hash_is_minimal(vocabulary):
    assert sorted(vocabulary.whole.owner) == list(range(len(vocabulary.tokens)))
    assert all(vocabulary.whole.find(t) == i for i, t in enumerate(vocabulary.tokens))


def test_encoding_equals_the_library(vocabulary, library):
    encoder = bpe.Encoder(vocabulary, most=50)
    rng = random.Random(1)
    pieces = ["ab", "'s", "'LL", "tion", "E", " ", "  ", "\n", "\t", "é", "ß", "日本", "\U0001f600", "12", "½", "²", ".,", "-#", "_", "\x1c", "\x85", "\xa0", "　", "\x00", "́"]
    for _ in range(4000):
        text = "".join(rng.choice(pieces) for _ in range(rng.randint(0, 30)))
        ids = encoder.encode(text).tolist()
        assert ids == library.encode_ordinary(text), repr(text)
        assert bpe.decode(ids, vocabulary) == text.encode()
    for text in ("a" * 5000, "the" * 3000, "!?" * 2000, " " * 3000, "<|endoftext|>"):
        assert encoder.encode(text).tolist() == library.encode_ordinary(text)


def test_encode_frame(spark, vocabulary, library):
    rows = [(1, "Hello wörld", 5), (2, None, 5), (3, "", 5), (None, "x", 5), (1, "Hello wörld", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, N_TOKENS int")
    made = bpe.encode(docs, vocabulary, ("ids", "n_tokens", "ids_sha256", "decoded", "decoded_sha256"))
    assert made.columns == ["doc_id", "text", "ids", "n_tokens", "ids_sha256", "decoded", "decoded_sha256"]
    for r in made.collect():
        text = r["text"] or ""
        ids = library.encode_ordinary(text)
        assert r["ids"] == ids and r["n_tokens"] == len(ids) and bytes(r["decoded"]) == text.encode()
        assert r["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()
    assert bpe.encode(docs.limit(0), vocabulary).count() == 0
    with pytest.raises(ValueError):
        bpe.encode(docs, vocabulary, ("nothing",))


def plain_copies(rows):
    groups = {}
    for i, (id_, text, _) in enumerate(rows):
        groups.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", text or ""), []).append((id_ is None, id_ or 0, i))
    out = []
    for text, held in groups.items():
        first = min(held)
        for none, id_, i in held:
            out.append((rows[i][0], None if first[0] else first[1], len(held), hashlib.sha256(text.encode()).hexdigest()))
    return sorted(out, key=str)


def test_copies_equal_brute_force(spark):
    rng = random.Random(2)
    texts = ["a b", "a  b", "a\tb", "a\n\nb", " a b", "é", None, "", " ", "   ", "z" * 50_000] + [f"t{i}" for i in range(40)]
    rows = [(rng.choice([None, *range(1000)]), rng.choice(texts), i) for i in range(400)] + [(5, "a b", 0), (5, "a b", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _n int").repartition(5)
    made = exact.mark_copies(docs)
    got = made.collect()
    assert sorted(((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got), key=str) == plain_copies(rows)
    kept = {}
    for r in got:
        kept[r["text_sha256"]] = kept.get(r["text_sha256"], 0) + r["kept"]
        assert not r["kept"] or r["doc_id"] == r["keep_id"]
    assert set(kept.values()) == {1}
    slim = exact.mark_copies(docs.withColumn("KEPT", F.lit(1)), slim=True)
    assert slim.columns == ["doc_id", "keep_id", "group_size", "kept", "text_sha256"] and slim.count() == len(rows)
    assert exact.mark_copies(docs.limit(0)).count() == 0


def test_many_filters_mark_as_one_does(spark, monkeypatch):
    rng = random.Random(3)
    rows = [(rng.choice([None, *range(1000)]), f"t{rng.randrange(700)}", i) for i in range(1500)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, other int")
    monkeypatch.setattr(exact.sieve, "MOST_BITS", 1 << 13)
    monkeypatch.setattr(exact.sieve, "LEAST_BITS", 1 << 10)
    assert exact.sieve.filters_for(1500) == 3
    for slim in (False, True):
        got = exact.mark_copies(docs, slim=slim).collect()
        assert sorted(((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got), key=str) == plain_copies(rows)
        assert sum(r["kept"] for r in got) == len({r[1] for r in rows})


def test_only_possible_copies_shuffle(spark):
    docs = spark.createDataFrame([(i, f"text {i}") for i in range(500)] + [(900, "text 7")], "doc_id long, text string")
    made = exact.mark_copies(docs)
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "Arrow" not in plan
    assert {r["doc_id"] for r in made.filter("group_size > 1").collect()} == {7, 900}


def test_shares_fill_up_to_the_cap():
    assert mixing.shares([100, 100, 100], [1, 2, 3]) == [50.0, 100.0, 150.0]
    got = mixing.shares([1000, 10, 10], [1, 2, 3])
    assert got[1:] == [30.0, 30.0] and got[0] == pytest.approx(960.0)
    assert mixing.shares([0, 0], [1, 2]) == [0.0, 0.0] and mixing.shares([], []) == []


def test_mix_meets_targets_and_bounds(spark):
    rng = random.Random(6)
    rows = [(i, rng.choice(["a", "b", "c", "d", None]) if i % 3 else "a", " ".join(["w"] * rng.choice([1, 5, 20, 60, 300]))) for i in range(3000)]
    rows += [(5000, "only", "one two three"), (5001, "blank", None), (5002, "blank", " \n"), (None, "a", "w w"), (1, rows[1][1], rows[1][2])]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string").withColumn("TARGET", F.lit("x")).withColumn("rate", F.lit("y"))
    made = mixing.mix(docs)
    got = made.collect()
    assert len(got) == len(rows) and made.columns[:4] == ["doc_id", "source", "text", "rate"]
    again = {(r["doc_id"], r["text"]): r["taken"] for r in mixing.mix(docs.repartition(3)).collect()}
    by = {}
    for r in got:
        assert r["size"] == len((r["text"] or "").split()) and r["taken"] == r["copies"] * r["size"] <= 3 * r["size"]
        assert again[r["doc_id"], r["text"]] == r["taken"]
        x = by.setdefault(r["source"], [0, 0, r["target"], r["source_size"]])
        x[0] += r["taken"]
        x[1] += r["size"]
    assert sum(x[1] for x in by.values()) == pytest.approx(sum(x[2] for x in by.values()))
    for source, (taken, size, target, named) in by.items():
        assert size == named and target <= 3 * size + 1e-9
        assert abs(taken - target) <= max(3, 0.002 * target), source
    assert by["only"][0] in (6, 9) and by["blank"][:2] == [0, 0]
    assert mixing.mix(docs.limit(0)).count() == 0


def test_rates_are_tilted_and_meet_the_constraint(spark):
    histogram = spark.createDataFrame([(0, s, 10) for s in (1, 2, 5, 40)] + [(1, s, 4) for s in (3, 9)], "k int, size long, n long")
    sources = [mixing.Source("a", 480, 40, 1200.0), mixing.Source("b", 48, 8, 10.0)]
    assert mixing.solve(spark, histogram, sources) < 60
    import math

    for k, x in enumerate(sources):
        total = sum(r["n"] * r["size"] * min(3, math.exp(x.dual / x.mean * r["size"])) for r in histogram.collect() if r["k"] == k)
        assert total == pytest.approx(x.target, rel=1e-6)


def test_any_number_of_sources_is_mixed_alike(spark, monkeypatch):
    rng = random.Random(8)
    rows = [(i, rng.choice([*"abcdefgh", "é", "\U0001f600", None]), " ".join(["w"] * rng.choice([0, 1, 5, 20, 60, 300]))) for i in range(2000)]
    rows += [(5000, "only", "one two three"), (5001, "blank", None), (5002, "blank", " \n")]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string")
    few = {r["doc_id"]: tuple(r) for r in mixing.mix(docs).collect()}
    monkeypatch.setattr(mixing, "MOST_SOURCES", 2)
    many = {r["doc_id"]: tuple(r) for r in mixing.mix(docs).collect()}
    assert many == few and len(many) == len(rows)
    assert mixing.mix(docs.filter("source is null")).count() == sum(r[1] is None for r in rows)


def plain_rates(sizes, target):
    """Rates exp(tilt * size), 3 at most, whose words are the target, by bisection."""
    if target >= 3 * sum(sizes):
        return [3.0] * len(sizes)
    low, high = -50.0, 50.0
    for _ in range(200):
        tilt = (low + high) / 2
        total = sum(s * min(3.0, math.exp(min(60.0, tilt * s))) for s in sizes)
        low, high = (tilt, high) if total < target else (low, tilt)
    return [min(3.0, math.exp(min(60.0, low * s))) for s in sizes]


def test_query_equals_plain_rates_and_meets_targets(spark, tmp_path):
    rng = random.Random(4)
    rows = [(i, rng.choice(["s3", "s1", "s2", None, "s9"]) if i % 2 else "hot", " ".join(["word"] * int(rng.lognormvariate(4, 1.2)))) for i in range(1500)]
    rows += [(9000, "hot", "long " * 20_000), (9001, "hot", None), (9002, "one", "a b c d e f g"), (7, rows[7][1], rows[7][2])]
    spark.createDataFrame(rows, "doc_id long, source string, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = mixing.op10_mixing(spark, str(tmp_path)).collect()
    assert len(got) == len(rows)
    of = {i: s for i, s, _ in rows}
    names = sorted({s for s in of.values() if s}) + [None]
    sizes = {n: sorted((r["size"], r["doc_id"]) for r in got if of[r["doc_id"]] == n) for n in names}
    totals = [sum(s for s, _ in sizes[n]) for n in names]
    targets = mixing.shares(totals, [(1, 2, 3)[i % 3] for i in range(len(names))])
    copies = {(r["doc_id"], r["size"]): r["copies"] for r in got}
    for n, total, target in zip(names, totals, targets, strict=True):
        held = [r for r in got if of[r["doc_id"]] == n]
        assert {r["source_size"] for r in held} == {total} and all(r["target"] == pytest.approx(target) for r in held)
        for (s, i), rate in zip(sizes[n], plain_rates([s for s, _ in sizes[n]], target), strict=True):
            assert s == 0 or math.floor(rate - 1e-6) <= copies[i, s] <= math.ceil(rate + 1e-6), (n, s, rate)
        assert abs(sum(r["taken"] for r in held) - target) <= max(7, 0.005 * target), n


def test_scratch_space_is_never_local_to_a_machine_of_a_cluster(spark, monkeypatch):
    from types import SimpleNamespace

    from distinct_bounds.llm import common

    unset = SimpleNamespace(isDefined=lambda: False)
    jsc = SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: unset))
    away = SimpleNamespace(conf=SimpleNamespace(get=lambda *_: None), sparkContext=SimpleNamespace(_jsc=jsc, master="spark://far:7077"))
    with pytest.raises(RuntimeError):
        common.scratch_dir(away)


def test_batches_are_bounded_unless_the_session_bounds_them(spark):
    from distinct_bounds.llm.common import BATCH_KEY, bound_batches

    held = spark.conf.get(BATCH_KEY, None)
    try:
        spark.conf.set(BATCH_KEY, "1m")
        bound_batches(spark)
        assert spark.conf.get(BATCH_KEY) == "1m"
        spark.conf.unset(BATCH_KEY)
        bound_batches(spark)
        assert spark.conf.get(BATCH_KEY) == "4m"
    finally:
        if held is not None:
            spark.conf.set(BATCH_KEY, held)
