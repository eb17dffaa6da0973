import hashlib
import math

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds, surface
from distinct_bounds.functions.special import LN2
from distinct_bounds.operators import baselines, diagnostics, estimate, hashing, registers, simulate, sketch
from distinct_bounds.operators.sketch import build
from distinct_bounds.sources import storage
from distinct_bounds.spec import SketchSpec
from distinct_bounds.streaming import streams

SF = "/root/testdata/sf0.001"


def rows(frame):
    return sorted(tuple(r) for r in frame.df.select(*frame.keys(), "key").collect())


@pytest.fixture(scope="module")
def keys(spark):
    return storage.table(spark, SF, "lineitem").select("l_orderkey").cache()


def test_digest_vector(spark):
    one = spark.createDataFrame([("pippo",)], "k string")
    r = hashing.lanes(one, F.col("k"), SketchSpec()).filter("lane = 0").first()
    assert (r["row"], r["v"], r["x"], r["z"]) == (10, 602732848597324, 3, 61)
    assert rows(build(one, "k"))[0] == (0, 10, 962)


def test_all_ways_of_building_agree(keys):
    base = rows(build(keys, "l_orderkey"))
    assert rows(sketch.build_two_step(keys, "l_orderkey")) == base
    assert rows(sketch.build_arrow(keys, "l_orderkey")) == base
    twice = keys.unionByName(keys).repartition(7)
    assert rows(build(twice, "l_orderkey")) == base
    parts = [build(keys.filter(F.pmod("l_orderkey", F.lit(3)) == i), "l_orderkey") for i in range(3)]
    assert rows(sketch.merge(*parts)) == base
    by = build(keys.withColumn("g", F.pmod("l_orderkey", F.lit(4))), "l_orderkey", by=["g"])
    assert rows(sketch.rollup(by)) == base
    assert rows(sketch.unpack(sketch.pack(build(keys, "l_orderkey")), SketchSpec())) == base
    with pytest.raises(ValueError):
        sketch.merge(build(keys, "l_orderkey"), build(keys, "l_orderkey", SketchSpec(z0=4)))


def test_plan_hashes_once_and_shuffles_slots_only(keys):
    plan = build(keys, "l_orderkey").df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("sha2(") == 1 and plan.count("Exchange hashpartitioning") == 1 and "partial_max" in plan


def plain_slots(objects, spec):
    """Slots by hashlib and xxhash, bit by bit."""
    out = {}
    for o in objects:
        text = str(o).encode()
        for lane in range(spec.c0):
            if spec.family == "sha2":
                digest = (hashlib.sha256 if spec.c0 <= 4 else hashlib.sha512)(text).digest()
                word = int.from_bytes(digest[8 * lane : 8 * lane + 8])
            elif spec.family == "md5":
                word = int.from_bytes(hashlib.md5(f"{lane}:".encode() + text).digest()[:8])
            else:
                word = xxhash.xxh64_intdigest(text, xxhash.xxh64_intdigest(lane.to_bytes(4, "little"), 42))
            bits = f"{word:064b}"
            row, rest = bits[: spec.word_r0], bits[spec.word_r0 :]
            z, v = (rest[: spec.word_z0], rest[spec.word_z0 :]) if spec.layout == "prefix" else (rest[len(rest) - spec.word_z0 :], rest[: len(rest) - spec.word_z0])
            row = row[::-1] if spec.layout == "prefix" and spec.row_bits == "lsb" else row
            row, z = int(row[: spec.r0] or "0", 2), int(z[: spec.z0] or "0", 2)
            x = v.find("1") + 1 or len(v) + 1
            out[lane, row] = max(out.get((lane, row), -1), x * spec.steps + spec.steps - 1 - z)
    return sorted((*k, v) for k, v in out.items())


@pytest.mark.parametrize("spec", [SketchSpec(), SketchSpec(c0=8), SketchSpec(family="xxhash64"), SketchSpec(c0=6, r0=5, z0=3, family="xxhash64", layout="prefix"), SketchSpec(family="md5"), SketchSpec.single_slot(4, family="md5"), SketchSpec.hll_shape(8), SketchSpec(c0=2, r0=5, z0=3, layout="prefix", row_bits="lsb"), SketchSpec(r0=2, z0=4, word_r0=4, word_z0=8), SketchSpec(r0=1, z0=0, layout="prefix", row_bits="lsb", word_r0=3, word_z0=2)], ids=str)
def test_slots_equal_brute_force(keys, spec):
    assert rows(build(keys, "l_orderkey", spec)) == plain_slots({r[0] for r in keys.collect()}, spec)


def test_folding_equals_building_coarser(keys):
    fine = build(keys, "l_orderkey")
    for z0, r0 in ((4, 4), (0, 2), (8, 0), (5, 3)):
        folded = sketch.fold(fine, z0=z0, r0=r0)
        native = build(keys, "l_orderkey", folded.spec)
        assert rows(folded) == rows(native) == rows(sketch.merge(folded, native))
        assert folded.spec.saturated == 53 and registers.mean_y(folded).first()["saturated"] == 0
    assert rows(sketch.fold(sketch.fold(fine, z0=6), z0=2, r0=3)) == rows(sketch.fold(fine, z0=2, r0=3))
    same_bits = SketchSpec(z0=4)
    assert sketch.fold(fine, z0=4).spec.fingerprint() != same_bits.fingerprint()
    with pytest.raises(ValueError):
        sketch.merge(sketch.fold(fine, z0=4), build(keys, "l_orderkey", same_bits))
    with pytest.raises(ValueError):
        sketch.fold(fine, z0=9)
    r = estimate.interval(sketch.fold(fine, z0=4, r0=2), 0.99).first()
    assert r["lower"] < 1473 < r["upper"]


def test_empty_and_null_input(spark):
    none = spark.createDataFrame([(None,), (None,)], "k string")
    r = estimate.interval(build(none, "k")).first()
    assert (r["estimate"], r["lower"], r["empty_slots"]) == (0.0, 0.0, 64) and r["upper"] > 0
    assert estimate.interval(build(none.limit(0), "k")).count() == 1
    assert estimate.interval(build(none.withColumn("g", F.lit(1)), "k", by=["g"])).count() == 0
    one = spark.range(100_000).select(F.lit(5).alias("k"))
    assert estimate.interval(build(one, "k")).first()["lower"] <= 1


def test_object_keys(spark):
    df = spark.sql("SELECT * FROM VALUES (0.0D, map('a', 1, 'b', 2), timestamp_ntz'2024-01-01', array(1, null), interval '1' day), (-0.0D, map('b', 2, 'a', 1), timestamp_ntz'2024-01-01', array(1, null), interval '1' day), (double('NaN'), null, null, null, null) t(d, m, t, a, i)")
    for c, n in (("d", 2), ("m", 1), ("t", 1), ("a", 1), ("i", 1)):
        assert df.select(hashing.object_key(df, c).alias("k")).filter("k is not null").distinct().count() == n, c
    pair = spark.createDataFrame([(1, None), (1, 2), (12, None)], "a int, b int")
    assert pair.select(hashing.object_key(pair, "a", "b").alias("k")).distinct().count() == 3


def test_special_layouts(keys):
    for spec in (SketchSpec.hll_shape(8), SketchSpec.single_slot(4), SketchSpec(c0=8), SketchSpec(c0=8, r0=0, family="xxhash64"), SketchSpec(c0=2, r0=5, z0=3, layout="prefix", row_bits="lsb")):
        frame = build(keys, "l_orderkey", spec)
        r = estimate.interval(frame, 0.99).first()
        assert r["lower"] < 1473 < r["upper"] and r["saturated"] == 0


def test_occupancies_add_up(keys):
    per_lane = registers.occupancy(keys, "l_orderkey").groupBy("lane").agg(F.sum("objects").alias("n")).collect()
    assert {r["n"] for r in per_lane} == {1473}


def test_intervals_are_nested(keys):
    frame = build(keys, "l_orderkey")
    wide, narrow = (estimate.interval(frame, a).first() for a in (0.99, 0.9))
    assert wide["lower"] < narrow["lower"] < narrow["estimate"] < narrow["upper"] < wide["upper"]
    assert narrow["lower_int"] == math.ceil(narrow["lower"]) and narrow["upper_int"] == math.floor(narrow["upper"])
    upper = estimate.interval(frame, 0.9, side="upper").first()
    lower = estimate.interval(frame, 0.9, side="lower").first()
    assert upper["lower"] == 0 and lower["upper"] == math.inf and lower["upper_int"] is None
    assert upper["upper"] < narrow["upper"] and lower["lower"] > narrow["lower"]
    fast = estimate.point_fast(frame).first()["estimate"]
    assert fast == pytest.approx(narrow["estimate"], rel=1e-3)


def test_baselines_are_near_the_truth(keys):
    made = {"pcsa": (baselines.pcsa(keys, "l_orderkey"), 0.3), "linear": (baselines.linear_counting(keys, "l_orderkey"), 0.03), "multires": (baselines.multires_bitmap(keys, "l_orderkey"), 0.2), "min": (baselines.min_count(keys, "l_orderkey"), 0.2), "hll": (baselines.hll(keys, "l_orderkey"), 0.12)}
    for name, (df, error) in made.items():
        assert df.first()["estimate"] == pytest.approx(1473, rel=error), name
    for kind in baselines.BUILTIN:
        assert baselines.builtin(keys, "l_orderkey", kind).first()["estimate"] == pytest.approx(1473, rel=0.1)
    frame = build(keys, "l_orderkey")
    clt, cheb, chern = (f.first() for f in (baselines.clt_interval(frame), baselines.chebyshev_interval(frame), estimate.interval(frame)))
    assert clt["upper"] - clt["lower"] < chern["upper"] - chern["lower"] < cheb["upper"] - cheb["lower"]
    assert baselines.markov_lower(frame).first()["lower"] < chern["lower"]


def test_simulated_coverage(spark):
    got = {(r["method"], r["slack"], r["empty"], r["truth"]): r["rate"] for r in simulate.coverage(spark, truths=(10, 500), trials=1000).collect()}
    for method in ("equal", "shortest", "lower", "upper", "chebyshev"):
        assert got[method, "sound", "zero", 10] >= 0.9 and got[method, "sound", "zero", 500] >= 0.9
    assert got["equal", "sound", "printed", 10] < 0.8  # what the start value of an empty slot costs


def test_slack_belongs_below_the_lower_bound(spark):
    spec = SketchSpec(z0=0, layout="prefix")
    got = {(r["method"], r["slack"]): r["rate"] for r in simulate.coverage(spark, spec, truths=(500,), trials=1000).filter("empty = 'zero'").collect()}
    assert got["equal", "sound"] >= 0.9 > got["equal", "theorem"]


def test_tightness_of_the_bound(spark):
    grid = simulate.tail_grid(spark).cache()
    assert {r["claim"]: r["holds"] for r in simulate.tail_claims(grid).collect()} == dict.fromkeys(simulate.TAIL_CLAIMS, True)
    got = {(r["truth"], r["side"]): r for r in grid.filter("r0 = 4 AND c0 = 1 AND alpha = 0.9").collect()}
    assert got[500, "upper"]["imprecision"] == pytest.approx(0.00683, rel=0.1)
    assert got[50_000, "upper"]["imprecision"] == pytest.approx(6.7e-5, rel=0.1)
    fit = {r["direction"]: r for r in simulate.tail_fit(grid).collect()}
    assert fit["span on imprecision"]["slope"] == pytest.approx(1.88, abs=0.05) and fit["span on imprecision"]["n"] == 1024
    grid.unpersist()


def test_finite_tails_are_least_over_the_tilt():
    rng = np.random.default_rng(3)
    for side, grid in (("lower", 1 / (1 + np.exp(-np.linspace(-9, 12, 4000)))), ("upper", np.exp(np.linspace(-6, 7, 4000)))):
        for m in ([4, 0, 7, 11], rng.multinomial(50, [1 / 16] * 16), [50_000], [1, 700]):
            h = bounds.budget(0.99, len(m), side)[0 if side == "lower" else 1]
            sign = -1 if side == "lower" else 1
            plain = min(sum(math.fsum(sign * t / j - math.log1p(sign * t / j) for j in range(1, min(k, 2000) + 1)) for k in m) - len(m) * h * t for t in grid[::40]) if max(m) <= 2000 else None
            fine = min(float(bounds.log_product(np.array(m), t, sign).sum()) - len(m) * h * t for t in grid)
            got = bounds.finite_tail(m, h, side)
            assert got <= math.exp(fine) * (1 + 1e-9) and got == pytest.approx(math.exp(fine), rel=1e-3)
            assert plain is None or got <= math.exp(plain) * (1 + 1e-9)


def test_truncation_stays_in_its_bound(spark):
    r = simulate.truncation_gap(spark, trials=50).first()
    assert -1e-9 <= r["least"] and r["most"] <= r["bound"]


def test_evolution_and_measures(spark):
    e = storage.table(spark, SF, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id")
    run = diagnostics.evolution(e, "user_id", "day").orderBy("day").collect()
    assert [r["truth"] for r in run] == sorted(r["truth"] for r in run) and run[-1]["truth"] == 15
    whole = estimate.interval(build(e, "user_id")).first()
    assert run[-1]["estimate"] == pytest.approx(whole["estimate"])
    fit = diagnostics.fit_rows(storage.table(spark, SF, "lineitem"), "l_orderkey").first()
    assert fit["df"] == 15 and 0 < fit["p"] < 1
    ranks = diagnostics.frequency_rank(e, "user_id").collect()
    assert sum(r["objects"] for r in ranks) == 15 and min(r["first_rank"] for r in ranks) == 1


def test_slot_store(spark, tmp_path, keys):
    frame = build(keys, "l_orderkey")
    storage.save_slots(frame, str(tmp_path / "s"))
    storage.save_slots(frame, str(tmp_path / "s"), "append")
    assert rows(storage.load_slots(spark, str(tmp_path / "s"), SketchSpec())) == rows(frame)
    with pytest.raises(ValueError):
        storage.load_slots(spark, str(tmp_path / "s"), SketchSpec(z0=4))


def test_sources_by_file(spark, tmp_path):
    for i in range(3):
        spark.range(i * 10, i * 10 + 10).coalesce(1).write.mode("append").option("compression", "gzip").csv(str(tmp_path / "c"))
    df = storage.by_file(spark, str(tmp_path / "c"), "csv")
    assert estimate.count_distinct_interval(df, "_c0", ["slice_file"]).count() == 3


def test_streams_equal_batches(spark, tmp_path):
    events = storage.table(spark, SF, "events")
    for i in range(3):
        events.filter(F.pmod("event_id", F.lit(3)) == i).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    want = rows(build(events, "user_id"))
    got = streams.run_available(streams.slots_of(stream, "user_id"), "update").groupBy("lane", "row").agg(F.max("key").alias("key"))
    assert sorted(tuple(r) for r in got.collect()) == want
    states = streams.run_available(streams.packed_state(stream, "event_type", "user_id"), "update").groupBy("lane", "row").agg(F.max("key"))
    assert sorted(tuple(r) for r in states.collect()) == want
    store, out, at = (str(tmp_path / n) for n in ("store", "intervals", "at"))
    streams.keep_store(stream, "user_id", store, out, at).awaitTermination()
    batches = spark.read.parquet(out).count()
    assert batches == 3 and rows(storage.load_slots(spark, f"{store}/version=2", SketchSpec())) == want
    # the same files once more change nothing
    again = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    got = streams.run_available(streams.slots_of(again, "user_id"), "update").groupBy("lane", "row").agg(F.max("key").alias("key"))
    assert sorted(tuple(r) for r in got.collect()) == want
    first = streams.run_available(streams.deduplicated(stream, "user_id", "ts", "60 days"), "append")
    assert first.count() == 15


def test_sql_surface(spark, keys):
    surface.register(spark)
    keys.createOrReplaceTempView("order_keys")
    spark.sql("SELECT sha2(CAST(l_orderkey AS STRING), 256) AS d FROM order_keys").createOrReplaceTempView("digests")
    got = spark.sql("SELECT sketch_row(substr(d, 1, 16)) AS r, max(sketch_key(substr(d, 1, 16))) AS key FROM digests GROUP BY 1").collect()
    want = {r[1]: r[2] for r in rows(build(keys, "l_orderkey")) if r[0] == 0}
    assert {r["r"]: r["key"] for r in got} == want
    frame = build(keys, "l_orderkey")
    frame.df.createOrReplaceTempView("slots")
    one = spark.sql("SELECT * FROM distinct_interval(TABLE(SELECT lane, row, key FROM slots), 0.9)").first()
    r = estimate.interval(frame).first()
    assert (one["estimate"], one["lower"], one["upper"]) == (pytest.approx(r["estimate"]), pytest.approx(r["lower"]), pytest.approx(r["upper"]))
    packed = spark.sql("SELECT sketch_agg(CAST(l_orderkey AS STRING)) AS s FROM order_keys").first()["s"]
    held = np.frombuffer(packed, np.int64)
    assert surface.mean_of(held[held > 0], SketchSpec()) * LN2 == pytest.approx(registers.mean_y(frame).first()["mean_y"] * LN2)
    assert spark.sql("SELECT distinct_hp(CAST(1 AS DOUBLE)) AS x").first()["x"] == pytest.approx(0.0625)


def test_row_sampling_does_not_estimate_distinct_counts(spark):
    df = storage.table(spark, SF, "lineitem").select("l_suppkey")
    scaled = df.filter(F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(10)) == 0).select("l_suppkey").distinct().count() * 10
    assert scaled >= 50  # ten suppliers
