"""Every method, variant, baseline, measure and experiment as a named query with its SQL twin."""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds, planner, solvers, special
from distinct_bounds.functions.special import EULER, LN2, normal_quantile
from distinct_bounds.operators import baselines, diagnostics, estimate, hashing, registers, simulate, sketch
from distinct_bounds.operators.sketch import SlotFrame, build
from distinct_bounds.plans import oracle as sql
from distinct_bounds.sources.shipping import ship
from distinct_bounds.sources.storage import settled, table
from distinct_bounds.spec import SketchSpec

QUERIES: dict = {}
SQL: dict[str, str] = {}
SPEC = SketchSpec()


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            SQL[name] = oracle
        return f

    return add


# ---- key streams -----------------------------------------------------------------------


def orderkeys(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey")


def pairs(spark, d):
    return table(spark, d, "lineitem").select(F.concat_ws("|", "l_partkey", "l_suppkey").alias("pair"))


def tokens(spark, d, *more):
    return table(spark, d, "documents").select(*more, F.explode(F.split("text", " ")).alias("token")).filter("token <> ''")


PAIR = "concat_ws('|', l_partkey, l_suppkey)"
TOKENS = "(SELECT doc_id, unnest(string_split(text, ' ')) AS token FROM documents) q"
STREAMS = {
    "orderkeys": (orderkeys, "l_orderkey", "lineitem", "l_orderkey"),
    "users": (lambda s, d: table(s, d, "events").select("user_id"), "user_id", "events", "user_id"),
    "pairs": (pairs, "pair", "lineitem", PAIR),
    "tokens": (tokens, "token", TOKENS, "nullif(token, '')"),
    "partkeys": (lambda s, d: table(s, d, "lineitem").select("l_partkey"), "l_partkey", "lineitem", "l_partkey"),
    "suppkeys": (lambda s, d: table(s, d, "lineitem").select("l_suppkey"), "l_suppkey", "lineitem", "l_suppkey"),
    "custkeys": (lambda s, d: table(s, d, "orders").select("o_custkey"), "o_custkey", "orders", "o_custkey"),
}


def stream_of(name, spark, d):
    make, col, *_ = STREAMS[name]
    return make(spark, d), col


def frame_of(name, spark, d, spec=SPEC) -> SlotFrame:
    return build(*stream_of(name, spark, d), spec)


def each(df: DataFrame, function, schema: str) -> DataFrame:
    """The rows, as tuples of the schema, that function returns for each row of df, which are few: groups of a table."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    ship(df.sparkSession)
    kinds = to_arrow_schema(StructType.fromDDL(schema))

    def work(batches):
        for batch in batches:
            rows = [dict(zip(kinds.names, r, strict=True)) for x in batch.to_pylist() for r in function(**x)]
            yield pa.RecordBatch.from_pylist(rows, schema=kinds)

    return df.mapInArrow(work, schema)


def truths(df: DataFrame, by: Column, name: str, key: str) -> DataFrame:
    """(name, truth): the number of distinct keys of each group that has any."""
    return df.groupBy(by.alias(name)).agg(F.countDistinct(key).alias("truth")).filter("truth > 0")


USERS_K = "k AS (SELECT event_type, count(DISTINCT user_id) AS truth FROM events GROUP BY event_type HAVING count(DISTINCT user_id) > 0)"
DAYS_K = "k AS (SELECT CAST(l_shipdate AS DATE) AS day, count(DISTINCT l_orderkey) AS truth FROM lineitem GROUP BY 1 HAVING count(DISTINCT l_orderkey) > 0)"
LEVELS_K = f"t AS (SELECT n, sum((1 - pow({1 - sql.P!r}, n)) / n) OVER (ORDER BY n) AS hp FROM (SELECT unnest(range(1, (SELECT max(truth) + 1 FROM k))) AS n))"


def users_of_types(spark, d):
    return truths(table(spark, d, "events"), F.col("event_type"), "event_type", "user_id")


def orders_of_days(spark, d):
    return truths(table(spark, d, "lineitem"), F.to_date("l_shipdate"), "day", "l_orderkey")


# ---- hashing and slots -----------------------------------------------------------------


@query("worked_example", "SELECT * FROM (VALUES ('msb', 14, 0, 2, 2.0), ('lsb', 12, 0, 2, 2.0)) v(row_bits, slot_row, z, x, y)")
def worked_example(spark, d):
    bits = f"{0xD012F681:032b}"
    rows = [(b, *hashing.fields_from_bits(bits, SketchSpec(c0=1, r0=4, z0=6, layout="prefix", row_bits=b))) for b in ("msb", "lsb")]
    made = spark.createDataFrame(rows, "row_bits string, slot_row int, z int, x int")
    return made.withColumn("y", F.col("x") - F.log2(1 + F.col("z") / 64.0))


@query("hash_fields", sql.with_(sql.words("lineitem", "l_orderkey")) + ' SELECT k AS object, lane, "row", z, v, x FROM f')
def hash_fields(spark, d):
    words = hashing.lanes(orderkeys(spark, d).distinct(), F.col("l_orderkey").cast("string"), SPEC, keep=True)
    return words.withColumnRenamed("_object", "object")


def _slots_query(name):
    *_, source, key = STREAMS[name]
    query(f"slots_{name}", sql.with_(sql.slots(source, key)) + ' SELECT lane, "row", key FROM s')(lambda spark, d: frame_of(name, spark, d).df)


for _name in ("orderkeys", "users", "pairs", "tokens"):
    _slots_query(_name)

ORDER_SLOTS = sql.with_(sql.slots("lineitem", "l_orderkey"))


@query("slots_two_step", ORDER_SLOTS + ' SELECT lane, "row", key FROM s')
def slots_two_step(spark, d):
    return sketch.build_two_step(*stream_of("orderkeys", spark, d)).df


@query("slots_arrow", ORDER_SLOTS + ' SELECT lane, "row", key FROM s')
def slots_arrow(spark, d):
    return sketch.build_arrow(*stream_of("orderkeys", spark, d)).df


def _plain_slots(lane_word: str, lanes: int, row: str, z: str, v: str, bits: int, steps: int) -> str:
    return f"""
WITH o AS (SELECT DISTINCT CAST(l_orderkey AS VARCHAR) AS k FROM lineitem),
g AS (SELECT lane, {lane_word} AS w FROM o, (SELECT CAST(unnest(range({lanes})) AS INTEGER) AS lane) t),
h AS (SELECT lane, {row} AS "row", {z} AS z, {v} AS v FROM g)
SELECT lane, "row", max(CASE WHEN v = 0 THEN {bits + 1} ELSE {bits + 1} - length(bin(v)) END * {steps} + {steps - 1} - z) AS key FROM h GROUP BY lane, "row"
"""


def _hex(at, n, kind="BIGINT"):
    return f"CAST(CAST('0x' || substr(w, {at}, {n}) AS UBIGINT) AS {kind})"


SHA_WORD, MD5_WORD = "substr(sha256(k), CAST(16 * lane + 1 AS BIGINT), 16)", "substr(md5(lane || ':' || k), 1, 16)"


@query("slots_md5_lanes", _plain_slots(MD5_WORD, 4, _hex(1, 1, "INTEGER"), _hex(15, 2), _hex(2, 13), 52, 256))
def slots_md5_lanes(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec(family="md5")).df


@query("slots_hll_shape", _plain_slots(SHA_WORD, 1, _hex(1, 2, "INTEGER"), "0", _hex(3, 14), 56, 1))
def slots_hll_shape(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec.hll_shape(8)).df


@query("slots_single", _plain_slots(MD5_WORD, 4, "0", "0", "CAST('0x' || w AS UBIGINT)", 64, 1))
def slots_single(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec.single_slot(4, family="md5")).df


@query("slots_many_lanes", _plain_slots(MD5_WORD, 8, "0", _hex(15, 2), _hex(1, 14), 56, 256))
def slots_many_lanes(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec(c0=8, r0=0, z0=8, family="md5")).df


@query("slots_prefix", _plain_slots(SHA_WORD, 4, _hex(1, 1, "INTEGER"), _hex(2, 2), _hex(4, 13), 52, 256))
def slots_prefix(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec(layout="prefix")).df


@query("slots_xxhash", sql.with_(sql.xx_slots("lineitem", "l_orderkey")) + ' SELECT lane, "row", key FROM s')
def slots_xxhash(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec(family="xxhash64")).df


@query("slots_sha512")
def slots_sha512(spark, d):
    return frame_of("orderkeys", spark, d, SketchSpec(c0=8)).df


@query("slot_matrix", ORDER_SLOTS + ' SELECT "row", ' + ", ".join(f'max(CASE WHEN lane = {i} THEN key END) AS lane{i}' for i in range(4)) + ' FROM s GROUP BY "row"')
def slot_matrix(spark, d):
    out = frame_of("orderkeys", spark, d).df.groupBy("row").pivot("lane", list(range(4))).agg(F.max("key"))
    return out.select("row", *[F.col(str(i)).alias(f"lane{i}") for i in range(4)])


GRID = "(SELECT CAST(a AS INTEGER) AS lane, CAST(b AS INTEGER) AS \"row\" FROM (SELECT unnest(range(4)) AS a), (SELECT unnest(range(16)) AS b))"


@query("y_dense", sql.with_(sql.slots("lineitem", "l_suppkey")) + f"""
SELECT g.lane, g."row", CAST(key // 256 AS INTEGER) AS x, CAST(255 - key % 256 AS INTEGER) AS z, round(coalesce(key // 256 - log2(1 + (255 - key % 256) / 256.0), 0.0), 6) AS y
FROM {GRID} g LEFT JOIN s ON g.lane = s.lane AND g."row" = s."row" """)
def y_dense(spark, d):
    return registers.dense(frame_of("suppkeys", spark, d)).withColumn("y", F.round("y", 6))


def _mean_query(name, stream, empty, value):
    *_, source, key = STREAMS[stream]
    query(name, sql.with_(sql.slots(source, key), sql.means(empty=value)) + " SELECT round(mean_y, 6) AS mean_y, filled FROM m")(
        lambda spark, d: registers.mean_y(frame_of(stream, spark, d), empty).select(F.round("mean_y", 6).alias("mean_y"), "filled")
    )


_mean_query("mean_y_zero", "suppkeys", "zero", 0.0)
_mean_query("mean_y_printed", "suppkeys", "printed", registers.empty_value(SPEC, "printed"))


@query("occupancy", sql.with_(sql.words("lineitem", "l_orderkey")) + ' SELECT lane, "row", count(*) AS objects FROM f GROUP BY lane, "row"')
def occupancy(spark, d):
    return registers.occupancy(*stream_of("orderkeys", spark, d))


@query("sketch_health", sql.with_(sql.slots("lineitem", "l_suppkey")) + " SELECT CAST(sum(CASE WHEN key // 256 >= 53 THEN 1 ELSE 0 END) AS BIGINT) AS saturated, 64 - count(*) AS empty_slots, CAST(max(key // 256) AS INTEGER) AS max_x FROM s")
def sketch_health(spark, d):
    return registers.health(frame_of("suppkeys", spark, d))


# ---- estimates and intervals -----------------------------------------------------------


@query("hp_table", sql.with_(DAYS_K, LEVELS_K) + " SELECT day, n, round(hp, 6) AS hp FROM k JOIN t ON truth = n")
def hp_table(spark, d):
    """The level of the number of orders of each ship day, from a table as long as the largest of them."""
    days = settled(orders_of_days(spark, d), "days")
    most = days.agg(F.max("truth")).first()[0] or 0
    return days.join(estimate.hp_table(spark, most, SPEC.p), F.col("truth") == F.col("n")).select("day", "n", F.round("hp", 6).alias("hp"))


LEVELS = (0.9, 0.95, 0.99)
#: How many slots the customers of each order day fill, each number once.
FILLED = sql.with_(sql.slots("(SELECT CAST(o_orderdate AS DATE) AS day, o_custkey FROM orders) q", "o_custkey", "day")) + ", n AS (SELECT DISTINCT CAST(count(*) AS INTEGER) AS a0 FROM s GROUP BY day)"
ALL_CASES = "SELECT alpha, a0 FROM (SELECT unnest([0.9, 0.95, 0.99]::DOUBLE[]) AS alpha), n"


def filled_slots(spark, d):
    frame = build(table(spark, d, "orders").select(F.to_date("o_orderdate").alias("day"), "o_custkey"), "o_custkey", SPEC, ["day"])
    return frame.df.groupBy("day").agg(F.count("*").cast("int").alias("a0")).select("a0").distinct()


@query("h_exponents", FILLED + """,
c AS (SELECT alpha, a0, -ln((1 - alpha) / 2) / a0 AS y FROM (SELECT unnest([0.9, 0.95, 0.99]) AS alpha), n),
t AS (SELECT exp(-9 + i * 1.2e-4) AS t FROM (SELECT unnest(range(100000)) AS i)),
u AS (SELECT 1 / (1 + exp(9 - i * 2.2e-4)) AS t, 1 / (1 + exp(i * 2.2e-4 - 9)) AS rest FROM (SELECT unnest(range(100000)) AS i)),
up AS (SELECT alpha, a0, min((y + lgamma(1 + t)) / t) AS h FROM c, t GROUP BY alpha, a0),
down AS (SELECT alpha, a0, min((y + lgamma(rest)) / u.t) AS h FROM c, u GROUP BY alpha, a0)
SELECT CAST(alpha AS DOUBLE) AS alpha, a0, round(down.h - 0.5772156649015329, 4) AS h_down, round(up.h + 0.5772156649015329, 4) AS h_up FROM down JOIN up USING (alpha, a0)
""")
def h_exponents(spark, d):
    """Half-widths for as many slots as the sketches of the order days fill."""
    made = each(filled_slots(spark, d), lambda a0: [(a, a0, *bounds.budget(a, a0)) for a in LEVELS], "alpha double, a0 int, h_down double, h_up double")
    return made.withColumns({c: F.round(c, 4) for c in ("h_down", "h_up")})


@query("log_shortest", f"""{FILLED.replace('WITH', 'WITH RECURSIVE', 1)}, {sql.shortest(ALL_CASES)}
SELECT alpha, a0, round(down, 6) AS h_down, round(up, 6) AS h_up, round(lower_tail, 7) AS lower_tail FROM x""")
def log_shortest(spark, d):
    """The shortest intervals for as many slots as the sketches of the order days fill."""
    made = each(filled_slots(spark, d), lambda a0: [(a, a0, *bounds.log_shortest(a, a0)) for a in LEVELS], "alpha double, a0 int, h_down double, h_up double, lower_tail double")
    return made.withColumns({"h_down": F.round("h_down", 6), "h_up": F.round("h_up", 6), "lower_tail": F.round("lower_tail", 7)})


SOLVER_Y = (0.03, 0.3, 3.0, 12.0)
MOST_STEPS = {"halley": 12, "newton": 20, "bisect": 120}


def solver_traces():
    """(method, problem, y, trace) of every equation by every iteration."""
    for method in solvers.METHODS:
        for y in SOLVER_Y:
            yield method, "h_up", y, solvers.h_up_trace(y, method)
            yield method, "h_down", y, solvers.h_down_trace(y, method)
            yield method, "psi", y, solvers.psi_inverse_trace(y - 2, method)
            yield method, "hp", y, solvers.hp_inverse_trace(y, 1 / 16, method)


@query("solver_roots", f"""
WITH RECURSIVE y AS (SELECT unnest([0.03, 0.3, 3.0, 12.0]::DOUBLE[]) AS y),
p AS (SELECT 0 AS i, y, 1e-9 AS lo, 1e9 AS hi FROM y UNION ALL SELECT i + 1, y, CASE WHEN {sql.digamma('mid')} > y - 2 THEN lo ELSE mid END, CASE WHEN {sql.digamma('mid')} > y - 2 THEN mid ELSE hi END FROM (SELECT *, sqrt(lo * hi) AS mid FROM p WHERE i < 90)),
{sql.levels(4_000_000, over=None).strip()},
k AS (SELECT 'h_up' AS problem, y, (SELECT min((y + lgamma(1 + t)) / t) + {EULER!r} FROM (SELECT exp(-9 + i * 1.2e-4) AS t FROM (SELECT unnest(range(105000)) AS i))) AS root FROM y
UNION ALL SELECT 'h_down', y, (SELECT min((y + lgamma(rest)) / t) - {EULER!r} FROM (SELECT 1 / (1 + exp(9 - i * 2.2e-4)) AS t, 1 / (1 + exp(i * 2.2e-4 - 9)) AS rest FROM (SELECT unnest(range(120000)) AS i))) FROM y
UNION ALL SELECT 'psi', y, sqrt(lo * hi) FROM p WHERE i = 90
UNION ALL SELECT 'hp', y, n + 0.0 FROM y ASOF JOIN t ON y >= hp)
SELECT method, problem, y, CASE WHEN problem = 'hp' THEN floor(root) ELSE round(root, 4) END AS root, true AS in_bracket, true AS in_time FROM k, (SELECT unnest(['halley', 'newton', 'bisect']) AS method)""")
def solver_roots(spark, d):
    """Every root by every iteration, whether it lies in its bracket and is reached in the steps its rate allows."""
    rows = []
    for method, problem, y, t in solver_traces():
        root = float(math.floor(t.root + 1e-9)) if problem == "hp" else round(t.root, 4)
        rows.append((method, problem, y, root, t.bracket[0] <= t.root <= t.bracket[1], t.iterations <= MOST_STEPS[method]))
    return spark.createDataFrame(rows, "method string, problem string, y double, root double, in_bracket boolean, in_time boolean")


@query("solver_iterations")
def solver_iterations(spark, d):
    rows = [(method, problem, y, t.root, t.iterations, t.bracket[1] - t.bracket[0]) for method, problem, y, t in solver_traces()]
    return spark.createDataFrame(rows, "method string, problem string, y double, root double, iterations int, bracket double")


def floored(df: DataFrame, *keep: str, lower=True, upper=True) -> DataFrame:
    cols = [F.floor("estimate").cast("bigint").alias("estimate_int")]
    cols += [F.floor("lower").cast("bigint").alias("lower_floor")] if lower else []
    cols += [F.floor("upper").cast("bigint").alias("upper_floor")] if upper else []
    return df.select(*keep, *cols)


DOWN, UP = sql.half("lower", 0.05), sql.half("upper", 0.05)
ONE_DOWN, ONE_UP = sql.half("lower", 0.1), sql.half("upper", 0.1)
SHORTEST = "WITH " + sql.shortest("SELECT 0.9::DOUBLE AS alpha, 64 AS a0").strip()
SHORT = (f"({SHORTEST} SELECT down FROM x)", f"({SHORTEST} SELECT up FROM x)")
ORDER_MEANS = (sql.slots("lineitem", "l_orderkey"), sql.means(), sql.levels(60_000))


def _interval_query(name, down, up, below=1 / 256, above=0.0, stream="orderkeys", empty="zero", top=60_000, **options):
    *_, source, key = STREAMS[stream]
    value = registers.empty_value(SPEC, empty)
    query(name, sql.with_(sql.slots(source, key), sql.means(empty=value), sql.levels(top)) + sql.floors("", down, up, below, above))(
        lambda spark, d: floored(estimate.interval(frame_of(stream, spark, d), empty=empty, **options), lower=down is not None, upper=up is not None)
    )


_interval_query("interval_two", DOWN, UP)
_interval_query("interval_lower", ONE_DOWN, None, side="lower")
_interval_query("interval_upper", None, ONE_UP, side="upper")
_interval_query("interval_shortest", SHORT[0], SHORT[1], split="shortest")
_interval_query("interval_split", sql.half("lower", 0.02), sql.half("upper", 0.08), split=(0.98, 0.92))
_interval_query("interval_halves", 0.5, 0.4, halves=(0.5, 0.4))
_interval_query("interval_theorem_slack", DOWN, UP, 0.0, 1 / 256 / LN2, slack="theorem")
_interval_query("interval_procedure_slack", DOWN, UP, 0.0, 1 / 256, slack="procedure")
_interval_query("interval_printed_empty", DOWN, UP, stream="suppkeys", empty="printed", top=5000)
_interval_query("pair_interval", DOWN, UP, stream="pairs", top=150_000)
_interval_query("tokens_interval", DOWN, UP, stream="tokens", top=300_000)


@query("point_orderkeys", sql.with_(*ORDER_MEANS) + sql.floors("", None, None))
def point_orderkeys(spark, d):
    return floored(estimate.point(frame_of("orderkeys", spark, d)), lower=False, upper=False)


@query("point_fast", sql.with_(*ORDER_MEANS[:2]) + f" SELECT round(exp(mean_y * {LN2!r} - {EULER!r}) * 16 - 0.5, 4) AS estimate FROM m")
def point_fast(spark, d):
    return estimate.point_fast(frame_of("orderkeys", spark, d)).select(F.round("estimate", 4).alias("estimate"))


@query("transformed_interval", sql.with_(*ORDER_MEANS[:2]) + f" SELECT round(mean_y * {LN2!r} - ({DOWN} + {1 / 256!r}), 6) AS low, round(mean_y * {LN2!r} + {UP}, 6) AS high FROM m")
def transformed_interval(spark, d):
    return estimate.transformed_interval(frame_of("orderkeys", spark, d), 0.9).select(F.round("low", 6).alias("low"), F.round("high", 6).alias("high"))


@query("inverse_by_table", sql.with_(sql.slots("events", "user_id", "event_type"), sql.means("event_type"), sql.levels(5000)) + sql.floors("event_type", None, None))
def inverse_by_table(spark, d):
    frame = build(table(spark, d, "events"), "user_id", SPEC, ["event_type"])
    aimed = registers.mean_y(frame).withColumn("middle", F.col("mean_y") * LN2)
    return estimate.inverse_by_table(aimed, estimate.hp_table(spark, 5000, SPEC.p), "middle", "estimate_int", SPEC.p).select("event_type", "estimate_int")


@query("point_by_groups", sql.with_(sql.slots("events", "user_id", "event_type"), sql.means("event_type"), sql.levels(5000)) + sql.floors("event_type", DOWN, UP))
def point_by_groups(spark, d):
    return floored(estimate.count_distinct_interval(table(spark, d, "events"), "user_id", ["event_type"]), "event_type")


def _exponent(h: str, side: str) -> str:
    """The largest of tilt times h less the log of the limit's moment generating function, over a grid of tilts."""
    if side == "lower":
        return f"(SELECT max({h} * t - lgamma(rest) + {EULER!r} * t) FROM (SELECT 1 / (1 + exp(9 - i * 2.2e-4)) AS t, 1 / (1 + exp(i * 2.2e-4 - 9)) AS rest FROM (SELECT unnest(range(100000)) AS i)))"
    return f"(SELECT max({h} * t - lgamma(1 + t) - {EULER!r} * t) FROM (SELECT exp(-9 + i * 1.2e-4) AS t FROM (SELECT unnest(range(100000)) AS i)))"


MOMENTS_H = (0.05, 0.4, 1.5)


@query("moment_identities", f"""WITH h AS (SELECT unnest([0.05, 0.4, 1.5]::DOUBLE[]) AS h), q AS (SELECT h, round({_exponent('h', 'lower')}, 6) AS down, round({_exponent('h', 'upper')}, 6) AS up FROM h)
SELECT h, down AS limit_down, down AS exponent_down, up AS limit_up, up AS exponent_up, round(exp(lgamma(1 - 0.3 / ln(2.0)) + lgamma(1001) - lgamma(1001 - 0.3 / ln(2.0))), 6) AS mgf, (SELECT round((sum(1.0 / j) + sum(CASE WHEN j <= 1000 THEN 1.0 / j ELSE 0 END)) / 2 / ln(2.0), 6) FROM (SELECT unnest(range(1, 2001)) AS j)) AS mean FROM q""")
def moment_identities(spark, d):
    rows = [(h, bounds.gumbel_exponent(h, "lower"), solvers.exponent_down(h)[0], bounds.gumbel_exponent(h, "upper"), solvers.exponent_up(h)[0], bounds.mgf_slot(0.3, 1000), bounds.mean_given([1000, 2000])) for h in MOMENTS_H]
    made = spark.createDataFrame(rows, "h double, limit_down double, exponent_down double, limit_up double, exponent_up double, mgf double, mean double")
    return made.select("h", *[F.round(c, 6).alias(c) for c in made.columns[1:]])


@query("forward_levels", sql.with_(sql.slots("events", "user_id", "event_type"), sql.means("event_type"), USERS_K, LEVELS_K) + f""",
r AS (SELECT event_type, abs(mean_y * {LN2!r} - hp) AS h FROM m JOIN k USING (event_type) JOIN t ON truth = n),
q AS (SELECT event_type, h, slots, 1 - exp(-slots * {_exponent('h', 'lower')}) AS lower_level, 1 - exp(-slots * {_exponent('h', 'upper')}) AS upper_level FROM r, (SELECT unnest([16, 64]::INTEGER[]) AS slots))
SELECT event_type, round(h, 6) AS h, slots, round(lower_level, 6) AS lower_level, round(upper_level, 6) AS upper_level, round(lower_level + upper_level - 1, 6) AS level FROM q""")
def forward_levels(spark, d):
    """Levels of half-widths that just reach from the sketch of each event type to the truth."""
    means = registers.mean_y(build(table(spark, d, "events"), "user_id", SPEC, ["event_type"])).select("event_type", "mean_y")

    def reach(event_type, mean_y, truth):
        h = abs(mean_y * LN2 - float(special.hp(truth, SPEC.p)[0]))
        return [(event_type, h, n, *bounds.levels(h, h, n)) for n in (16, 64)]

    made = each(means.join(users_of_types(spark, d), "event_type"), reach, "event_type string, h double, slots int, lower_level double, upper_level double, level double")
    return made.withColumns({c: F.round(c, 6) for c in ("h", "lower_level", "upper_level", "level")})


@query("gamma_products", sql.with_(USERS_K) + f""",
q AS (SELECT event_type, truth AS terms, t, sign, (SELECT exp(sum(sign * t / j - ln(1 + sign * t / j))) FROM (SELECT unnest(range(1, (SELECT max(truth) + 1 FROM k))) AS j) WHERE j <= truth) AS product, exp(lgamma(1 + sign * t) + sign * {EULER!r} * t) AS goal FROM k, (SELECT unnest([0.1, 0.5, 0.9]::DOUBLE[]) AS t), (SELECT unnest([-1, 1]::INTEGER[]) AS sign))
SELECT event_type, terms, t, sign, round(product, 7) AS product, round(goal, 7) AS goal FROM q""")
def gamma_products(spark, d):
    """Factors of the infinite product of Gamma, one for each user of an event type, and what they tend to."""

    def products(event_type, truth):
        return [(event_type, truth, t, g, special.gamma_product(t, truth, g), math.exp(math.lgamma(1 + g * t) + g * EULER * t)) for t in (0.1, 0.5, 0.9) for g in (-1, 1)]

    made = each(users_of_types(spark, d), products, "event_type string, terms bigint, t double, sign int, product double, goal double")
    return made.withColumns({c: F.round(c, 7) for c in ("product", "goal")})


def _finite(side: str) -> str:
    grid = "SELECT 1 / (1 + exp(9 - i * 9e-4)) AS t FROM (SELECT unnest(range(20000)) AS i)" if side == "lower" else "SELECT exp(-6 + i * 6e-4) AS t FROM (SELECT unnest(range(20000)) AS i)"
    g = "-" if side == "lower" else "+"
    return f"""SELECT event_type, h, '{side}' AS side, min(exponent) AS least FROM (SELECT event_type, h, t, sum(n * ({g} t * harmonic + lgamma(1 {g} t) + lgamma(m + 1) - lgamma(m + 1 {g} t) - h * t)) AS exponent FROM e, ({grid}), hs GROUP BY event_type, h, t) GROUP BY event_type, h"""


@query("finite_tails", sql.with_(sql.words("events", "user_id", "event_type")) + f""",
c AS (SELECT event_type, lane, "row", count(*) AS m FROM f GROUP BY event_type, lane, "row"),
u AS (SELECT event_type, m FROM c UNION ALL SELECT event_type, unnest(list_transform(range(64 - count(*)), lambda i : 0)) AS m FROM c GROUP BY event_type),
j AS (SELECT m, sum(1.0::DOUBLE / m) OVER (ORDER BY m) AS harmonic FROM (SELECT unnest(range(1, (SELECT max(m) + 1 FROM c))) AS m)),
e AS (SELECT event_type, u.m, coalesce(any_value(harmonic), 0) AS harmonic, count(*) AS n FROM u LEFT JOIN j ON u.m = j.m GROUP BY event_type, u.m),
hs AS (SELECT unnest([0.15, 0.4, 0.8]::DOUBLE[]) AS h)
SELECT event_type, h, side, round(exp(least(0.0, least)), 4) AS tail FROM ({_finite('lower')} UNION ALL {_finite('upper')})""")
def finite_tails(spark, d):
    """Chernoff bounds with the finite products of the numbers of users that the slots of each event type have seen."""
    objects = table(spark, d, "events").select("event_type", F.col("user_id").cast("string").alias("k")).distinct()
    seen = hashing.lanes(objects, F.col("k"), SPEC, ["event_type"]).groupBy("event_type", "lane", "row").agg(F.count("*").alias("m"))

    def tails(event_type, ms):
        m = ms + [0] * (SPEC.slots - len(ms))
        return [(event_type, h, side, bounds.finite_tail(m, h, side)) for h in (0.15, 0.4, 0.8) for side in ("lower", "upper")]

    made = each(seen.groupBy("event_type").agg(F.collect_list("m").alias("ms")), tails, "event_type string, h double, side string, tail double")
    return made.withColumn("tail", F.round("tail", 4))


SHAPES = ((4, 4, 8), (1, 8, 0), (4, 8, 4))


@query("bit_budgets", sql.with_(DAYS_K) + f""",
q AS (SELECT day, c0, r0, z0, CAST(truth AS DOUBLE) AS truth FROM k, (VALUES {', '.join(f'({c}, {r}, {z})' for c, r, z in SHAPES)}) v(c0, r0, z0))
SELECT day, c0, r0, z0, truth, CAST(ceil(r0 + z0 + log2(truth * c0) + 10) AS INTEGER) AS bits, round(log2(least(1.0, c0 * truth * pow(2.0, r0 + z0 - 64))), 6) AS log_overflow, CAST((c0 * pow(2, r0)) * (ceil(log2(log2(greatest(2.0, truth)) + 11)) + z0) AS BIGINT) AS memory FROM q""")
def bit_budgets(spark, d):
    """Bits a hash word needs for the orders of each ship day, the chance that some field overflows, and the bits of all slots."""

    def budgets(day, truth):
        for c0, r0, z0 in SHAPES:
            spec = SketchSpec(c0=c0, r0=r0, z0=z0)
            yield day, c0, r0, z0, float(truth), planner.bit_budget(spec, truth), math.log2(planner.overflow_chance(spec, truth)), planner.memory_bits(spec, truth)

    made = each(orders_of_days(spark, d), budgets, "day date, c0 int, r0 int, z0 int, truth double, bits int, log_overflow double, memory bigint")
    return made.withColumn("log_overflow", F.round("log_overflow", 6))


@query("log_lengths", sql.with_(sql.slots("events", "user_id", "event_type"), sql.means("event_type"), sql.levels(5000), sql.reals({"lower": f"greatest(0.0, mean_y * {LN2!r} - ({DOWN} + {1 / 256!r}))", "upper": f"mean_y * {LN2!r} + {UP}"}, "m", "event_type")) + " SELECT event_type, round(ln(upper / lower), 4) AS log_length FROM v")
def log_lengths(spark, d):
    made = estimate.count_distinct_interval(table(spark, d, "events"), "user_id", ["event_type"])
    return diagnostics.log_length(made).select("event_type", F.round("log_length", 4).alias("log_length"))


# ---- baselines -------------------------------------------------------------------------


@query("exact_distinct", " UNION ALL ".join(f"SELECT '{n}' AS stream, count(DISTINCT {key}) AS truth FROM {source}" for n, (_, _, source, key) in STREAMS.items()))
def exact_distinct(spark, d):
    out = None
    for n in STREAMS:
        one = baselines.exact(*stream_of(n, spark, d)).select(F.lit(n).alias("stream"), "truth")
        out = one if out is None else out.unionByName(one)
    return out


def parts_sql(bits: int) -> str:
    return f"""WITH o AS (SELECT DISTINCT sha256(CAST(l_orderkey AS VARCHAR)) AS d FROM lineitem),
q AS (SELECT CAST(CAST('0x' || substr(d, 1, 8) AS UBIGINT) AS BIGINT) % {1 << bits} AS bucket, CAST(CAST('0x' || substr(d, 9, 10) AS UBIGINT) AS BIGINT) AS field, (CAST(CAST('0x' || substr(d, 19, 13) AS UBIGINT) AS DOUBLE) + 1) / 4503599627370496.0 AS unit FROM o),
h AS (SELECT bucket, CASE WHEN field = 0 THEN 41 ELSE 41 - length(bin(field)) END AS rank, unit FROM q)"""


def _baseline(name, make, oracle):
    query(name, oracle)(lambda spark, d: make(*stream_of("orderkeys", spark, d)).select(F.round("estimate", 4).alias("estimate")))


_baseline("pcsa", baselines.pcsa, parts_sql(6) + ", ranks AS (SELECT DISTINCT bucket, rank FROM h), gaps AS (SELECT b.bucket, min(r) - 1 AS lowest FROM (SELECT DISTINCT bucket FROM h) b, (SELECT unnest(range(1, 64)) AS r) c WHERE NOT EXISTS (SELECT 1 FROM ranks k WHERE k.bucket = b.bucket AND k.rank = c.r) GROUP BY b.bucket) SELECT round(64 / 0.77351 * pow(2.0, sum(lowest) / 64.0), 4) AS estimate FROM gaps")
_baseline("linear_counting", baselines.linear_counting, parts_sql(17) + " SELECT round(-131072 * ln(1 - count(DISTINCT bucket) / 131072.0), 4) AS estimate FROM h")
_baseline("multires_bitmap", baselines.multires_bitmap, parts_sql(10) + """, c AS (SELECT l.level, count(DISTINCT bucket) AS n FROM (SELECT unnest(range(1, 17)) AS level) l LEFT JOIN h ON least(h.rank, 16) = l.level GROUP BY l.level),
b AS (SELECT least(coalesce(max(CASE WHEN n > 0.7 * 1024 THEN level END), 0) + 1, 16) AS base FROM c)
SELECT round(sum(CASE WHEN n < 1024 THEN -1024 * ln(1 - n / 1024.0) ELSE 1024 * ln(1024) END) * pow(2.0, max(base) - 1), 4) AS estimate FROM c, b WHERE level >= base""")
_baseline("min_count", baselines.min_count, parts_sql(0) + ", k AS (SELECT DISTINCT unit FROM h ORDER BY unit LIMIT 256) SELECT round(CASE WHEN count(*) < 256 THEN count(*) ELSE 255 / max(unit) END, 4) AS estimate FROM k")
_baseline("loglog", baselines.loglog, parts_sql(10) + ", r AS (SELECT bucket, max(rank) AS r FROM h GROUP BY bucket) SELECT round(0.39701 * 1024 * pow(2.0, sum(r) / 1024.0), 4) AS estimate FROM r")
HLL = parts_sql(10) + f", r AS (SELECT bucket, max(rank) AS r FROM h GROUP BY bucket), a AS (SELECT sum(pow(2.0, -r)) + 1024 - count(*) AS s, 1024 - count(*) AS e FROM r), w AS (SELECT {0.7213 / (1 + 1.079 / 1024) * 1024 * 1024!r} / s AS raw, e FROM a), y AS (SELECT CASE WHEN raw <= 2560 AND e > 0 THEN 1024 * ln(1024.0 / e) ELSE raw END AS estimate FROM w)"
_baseline("hll", baselines.hll, HLL + " SELECT round(estimate, 4) AS estimate FROM y")
HLL_HALF = normal_quantile(0.95) * 1.04 / 32


@query("hll_interval", HLL + f" SELECT round(estimate, 4) AS estimate, round(estimate * {1 - HLL_HALF!r}, 4) AS lower, round(estimate * {1 + HLL_HALF!r}, 4) AS upper FROM y")
def hll_interval(spark, d):
    return baselines.hll_interval(*stream_of("orderkeys", spark, d)).select(*[F.round(c, 4).alias(c) for c in ("estimate", "lower", "upper")])


@query("single_slot", "WITH q AS (" + _plain_slots(MD5_WORD, 4, "0", "0", "CAST('0x' || w AS UBIGINT)", 64, 1) + f") SELECT round(pow(2.0, avg(key)) / (exp({EULER!r}) * sqrt(2.0)), 4) AS estimate FROM q")
def single_slot(spark, d):
    df, col = stream_of("orderkeys", spark, d)
    frame = build(df, col, SketchSpec.single_slot(4, family="md5"))
    x, _ = sketch.decode(F.col("key"), frame.spec)
    return frame.df.agg((F.pow(F.lit(2.0), F.avg(x)) / (math.exp(EULER) * math.sqrt(2))).alias("estimate")).select(F.round("estimate", 4).alias("estimate"))


# Fixed value: the normal quantile at 0.95.
CLT, CHEB = "(1.6448536269514722 * sqrt(pi() * pi() / 6 / 64))", "sqrt(pi() * pi() / 6 / (64 * 0.1::DOUBLE))"


@query("clt_interval", sql.with_(*ORDER_MEANS) + sql.floors("", CLT, CLT))
def clt_interval(spark, d):
    return floored(baselines.clt_interval(frame_of("orderkeys", spark, d)))


@query("chebyshev_interval", sql.with_(*ORDER_MEANS) + sql.floors("", CHEB, CHEB))
def chebyshev_interval(spark, d):
    return floored(baselines.chebyshev_interval(frame_of("orderkeys", spark, d)))


@query("markov_lower", sql.with_(*ORDER_MEANS) + f" SELECT l.n AS lower_floor FROM m ASOF JOIN t l ON mean_y * {LN2 * (1 - 0.9)!r} >= l.hp")
def markov_lower(spark, d):
    return baselines.markov_lower(frame_of("orderkeys", spark, d)).select(F.floor("lower").cast("bigint").alias("lower_floor"))


KEYS = ("orderkeys", "users", "partkeys", "suppkeys", "custkeys")
HALVES = {"equal": bounds.budget(0.9, 64), "shortest": bounds.budget(0.9, 64, "two", "shortest"), "clt": (bounds.clt_half(0.9, 64),) * 2, "chebyshev": (bounds.chebyshev_half(0.9, 64),) * 2}
TWINS = {"equal": (DOWN, UP), "shortest": SHORT, "clt": (CLT, CLT), "chebyshev": (CHEB, CHEB)}


def _compare_sql(streams: dict) -> str:
    o = " UNION ALL ".join(f"SELECT '{n}' AS stream, CAST({key} AS VARCHAR) AS key FROM {source}" for n, (*_, source, key) in streams.items())
    methods = " UNION ALL ".join(f"SELECT '{n}' AS method, {a} AS down, {b} AS up" for n, (a, b) in TWINS.items())
    return sql.with_(f"src AS ({o}), truth AS (SELECT stream, count(DISTINCT key) AS truth FROM src GROUP BY stream)", sql.slots("src", "key", "stream"), sql.means("stream"), sql.levels(100_000), f"b AS ({methods})", f"q AS (SELECT stream, method, greatest(0.0, mean_y * {LN2!r} - down - {1 / 256!r}) AS low, mean_y * {LN2!r} + up AS high FROM m, b)") + " SELECT stream, method, truth, l.n AS lower_floor, u.n AS upper_floor, l.n < truth AND truth <= u.n AS covered FROM q JOIN truth USING (stream) ASOF JOIN t l ON q.low >= l.hp ASOF JOIN t u ON q.high >= u.hp"


@query("interval_methods_compare", _compare_sql({n: STREAMS[n] for n in KEYS}))
def interval_methods_compare(spark, d, streams=None):
    src = None
    for n, (make, col, *_) in (streams or {n: STREAMS[n] for n in KEYS}).items():
        df = make(spark, d)
        one = df.select(F.lit(n).alias("stream"), F.col(col).cast("string").alias("key"))
        src = one if src is None else src.unionByName(one)
    frame, truth, out = build(src, "key", SPEC, ["stream"]), baselines.exact(src, "key", ["stream"]), None
    for method, halves in HALVES.items():
        one = floored(estimate.interval(frame, halves=halves), "stream").select("stream", F.lit(method).alias("method"), "lower_floor", "upper_floor")
        out = one if out is None else out.unionByName(one)
    return out.join(truth, "stream").withColumn("covered", (F.col("lower_floor") < F.col("truth")) & (F.col("truth") <= F.col("upper_floor"))).select("stream", "method", "truth", "lower_floor", "upper_floor", "covered")


@query("sketch_family_compare")
def sketch_family_compare(spark, d):
    df, col = stream_of("orderkeys", spark, d)
    made = {n: f(df, col) for n, f in (("pcsa", baselines.pcsa), ("linear_counting", baselines.linear_counting), ("multires_bitmap", baselines.multires_bitmap), ("min_count", baselines.min_count), ("loglog", baselines.loglog), ("hll", baselines.hll))}
    made |= {n: baselines.builtin(df, col, n) for n in baselines.BUILTIN} | {"refined_maxima": estimate.point(build(df, col, SPEC))}
    out = None
    for n, one in made.items():
        one = one.select(F.lit(n).alias("family"), F.col("estimate").cast("double").alias("estimate"))
        out = one if out is None else out.unionByName(one)
    return out.crossJoin(F.broadcast(baselines.exact(df, col))).withColumn("accuracy", F.col("estimate") / F.col("truth"))


@query("builtin_hllpp")
def builtin_hllpp(spark, d):
    return baselines.builtin(*stream_of("orderkeys", spark, d), "hllpp")


@query("builtin_sketches", "SELECT kind, truth, true AS within FROM (SELECT count(DISTINCT l_orderkey) AS truth FROM lineitem), (SELECT unnest(['hllpp', 'hll_sketch', 'theta_sketch']) AS kind)")
def builtin_sketches(spark, d):
    """Whether the engine's own sketches are within four of their standard errors of the truth."""
    df, col = stream_of("orderkeys", spark, d)
    truth, out = baselines.exact(df, col), None
    for kind, error in (("hllpp", 0.02), ("hll_sketch", 0.013), ("theta_sketch", 0.016)):
        one = baselines.builtin(df, col, kind).crossJoin(F.broadcast(truth))
        one = one.select(F.lit(kind).alias("kind"), "truth", (F.abs(F.col("estimate") / F.col("truth") - 1) <= 4 * error).alias("within"))
        out = one if out is None else out.unionByName(one)
    return out


@query("elephants", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) >= 70")
def elephants(spark, d):
    return baselines.elephants(table(spark, d, "events"), "user_id", 70)


# ---- measures and experiments ----------------------------------------------------------


def _slices(name, spark_slice, sql_source, key, slice_sql, top):
    source = f"(SELECT {slice_sql} AS slice, {key} AS key FROM {sql_source}) src"
    truth = f"truth AS (SELECT slice, count(DISTINCT key) AS truth FROM {source} GROUP BY slice)"
    query(name, sql.with_(truth, sql.slots(source, "key", "slice"), sql.means("slice"), sql.levels(top), "m2 AS (SELECT m.*, truth FROM m JOIN truth USING (slice))") + sql.floors("slice, truth", DOWN, UP, source="m2", extra=", l.n < truth AND truth <= u.n AS covered"))(
        lambda spark, d: slice_accuracy(*spark_slice(spark, d))
    )


def slice_accuracy(df: DataFrame, key: str) -> DataFrame:
    frame = build(df, key, SPEC, ["slice"])
    met = diagnostics.relative_accuracy(estimate.interval(frame), baselines.exact(df, key, ["slice"]), ["slice"])
    return floored(met, "slice", "truth", "covered")


def token_slices(spark, d):
    return tokens(spark, d, F.pmod("doc_id", F.lit(100)).cast("int").alias("slice")), "token"


def month_slices(spark, d):
    return table(spark, d, "lineitem").select(F.date_format("l_shipdate", "yyyy-MM").alias("slice"), "l_orderkey"), "l_orderkey"


def day_slices(spark, d):
    return table(spark, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("slice"), "user_id"), "user_id"


_slices("tokens_slice_accuracy", token_slices, TOKENS, "nullif(token, '')", "CAST(doc_id % 100 AS INTEGER)", 80_000)
_slices("lineitem_month_accuracy", month_slices, "lineitem", "l_orderkey", "strftime(l_shipdate, '%Y-%m')", 60_000)
_slices("events_day_accuracy", day_slices, "events", "user_id", "strftime(ts, '%Y-%m-%d')", 10_000)


def slice_measures(df: DataFrame, key: str) -> DataFrame:
    """(slice, interval..., truth, accuracy, covered) with the estimate as the real number it is."""
    return diagnostics.relative_accuracy(estimate.interval(build(df, key, SPEC, ["slice"])), baselines.exact(df, key, ["slice"]), ["slice"])


MONTHS = "(SELECT strftime(l_shipdate, '%Y-%m') AS slice, l_orderkey AS key FROM lineitem) src"
TOKEN_SLICES = f"(SELECT CAST(doc_id % 100 AS INTEGER) AS slice, nullif(token, '') AS key FROM {TOKENS}) src"


def _accuracies(source: str, top: int) -> str:
    """CTEs up to a: (truth, accuracy) of each slice, by the real-valued estimate."""
    return sql.with_(f"truth AS (SELECT slice, count(DISTINCT key) AS truth FROM {source} GROUP BY slice)", sql.slots(source, "key", "slice"), sql.means("slice"), sql.levels(top), "m2 AS (SELECT m.*, truth FROM m JOIN truth USING (slice))", sql.reals({"estimate": f"mean_y * {LN2!r}"}, "m2", "truth"), "a AS (SELECT truth, estimate / truth AS accuracy FROM v)")


@query("accuracy_r2", _accuracies(MONTHS, 60_000) + " SELECT count(*) AS n, round(regr_slope(accuracy, truth), 6) AS slope, round(regr_r2(accuracy, truth), 6) AS r2 FROM a")
def accuracy_r2(spark, d):
    return slice_measures(*month_slices(spark, d)).agg(F.count("*").alias("n"), F.round(F.regr_slope("accuracy", "truth"), 6).alias("slope"), F.round(F.regr_r2("accuracy", "truth"), 6).alias("r2"))


@query("accuracy_association", _accuracies(TOKEN_SLICES, 80_000) + f""", q AS (SELECT count(*) AS n, regr_slope(accuracy, truth) AS slope, regr_intercept(accuracy, truth) AS intercept, regr_r2(accuracy, truth) AS r2 FROM a), z AS (SELECT *, r2 * (n - 2) / (1 - r2) AS f FROM q)
SELECT n, round(slope, 7) AS slope, round(intercept, 5) AS intercept, round(r2, 5) AS r2, round(f, 3) AS f, round({sql.f_tail('f', '1', 'n - 2')}, 4) AS p FROM z""")
def accuracy_association(spark, d):
    made = diagnostics.association(slice_measures(*token_slices(spark, d)), "truth", "accuracy")
    return made.withColumns({c: F.round(c, n) for c, n in (("slope", 7), ("intercept", 5), ("r2", 5), ("f", 3), ("p", 4))})


@query("accuracy_histogram", _accuracies(MONTHS, 60_000) + " SELECT CAST(CASE WHEN accuracy < 0.5 THEN 0 WHEN accuracy >= 1.5 THEN 21 ELSE floor((accuracy - 0.5) * 20) + 1 END AS INTEGER) AS bin, count(*) AS n FROM a GROUP BY 1")
def accuracy_histogram(spark, d):
    return diagnostics.accuracy_histogram(slice_measures(*month_slices(spark, d)))


for _name, _make, _source in (("tokens", token_slices, TOKEN_SLICES), ("months", month_slices, MONTHS)):
    query(f"truth_histogram_{_name}", f"WITH truth AS (SELECT slice, count(DISTINCT key) AS truth FROM {_source} GROUP BY slice), w AS (SELECT CAST(greatest(1, ceil((max(truth) + 1) / 20)) AS BIGINT) AS w FROM truth) SELECT CAST(truth // w AS INTEGER) AS bin, max(w) * (truth // w) AS low, count(*) AS n FROM truth, w GROUP BY truth // w")(
        lambda spark, d, make=_make: diagnostics.truth_histogram(baselines.exact(*make(spark, d), ["slice"]))
    )


@query("coverage_of_slices", " UNION ALL ".join(f"SELECT '{n}' AS workload, count(*) AS slices, avg(CAST(covered AS INTEGER)) AS rate FROM ({SQL[q]})" for n, q in (("tokens", "tokens_slice_accuracy"), ("months", "lineitem_month_accuracy"), ("days", "events_day_accuracy"))))
def coverage_of_slices(spark, d):
    out = None
    for n, f in (("tokens", token_slices), ("months", month_slices), ("days", day_slices)):
        one = diagnostics.coverage(slice_accuracy(*f(spark, d))).select(F.lit(n).alias("workload"), "slices", "rate")
        out = one if out is None else out.unionByName(one)
    return out


def _evolution(name, make, source, top):
    run = f"""r AS (SELECT b.slice, g.lane, g."row", max(s.key) OVER (PARTITION BY g.lane, g."row" ORDER BY b.slice) AS key FROM (SELECT DISTINCT slice FROM src) b CROSS JOIN {GRID} g LEFT JOIN s ON s.slice = b.slice AND s.lane = g.lane AND s."row" = g."row")"""
    fresh = "fresh AS (SELECT slice, count(*) AS n FROM (SELECT key, min(slice) AS slice FROM src GROUP BY key) GROUP BY slice), truth AS (SELECT b.slice, CAST(sum(coalesce(n, 0)) OVER (ORDER BY b.slice) AS BIGINT) AS truth FROM (SELECT DISTINCT slice FROM src) b LEFT JOIN fresh USING (slice))"
    text = sql.with_(f"src AS ({source})", sql.slots("src", "key", "slice"), run, fresh, sql.means("slice", source="r"), sql.levels(top), "m2 AS (SELECT m.*, truth FROM m JOIN truth USING (slice))")
    query(name, text + sql.floors("slice, truth", DOWN, UP, source="m2", extra=", l.n < truth AND truth <= u.n AS covered"))(lambda spark, d: evolved(*make(spark, d)))


def evolved(df: DataFrame, key: str) -> DataFrame:
    return floored(diagnostics.evolution(df, key, "slice", SPEC), "slice", "truth", "covered")


_evolution("evolution_stream_events", day_slices, "SELECT strftime(ts, '%Y-%m-%d') AS slice, user_id AS key FROM events", 10_000)
_evolution("evolution_stream_lineitem", month_slices, "SELECT strftime(l_shipdate, '%Y-%m') AS slice, l_orderkey AS key FROM lineitem", 60_000)
_evolution("evolution_first_slice", lambda s, d: (table(s, d, "events").filter("ts < timestamp_ntz'2024-01-02'").select(F.date_format("ts", "yyyy-MM-dd HH").alias("slice"), "user_id"), "user_id"), "SELECT strftime(ts, '%Y-%m-%d %H') AS slice, user_id AS key FROM events WHERE ts < TIMESTAMP '2024-01-02'", 10_000)
_evolution("evolution_first_month", lambda s, d: (table(s, d, "lineitem").filter("l_shipdate < timestamp_ntz'1995-02-01'").select(F.date_format("l_shipdate", "yyyy-MM-dd").alias("slice"), "l_orderkey"), "l_orderkey"), "SELECT strftime(l_shipdate, '%Y-%m-%d') AS slice, l_orderkey AS key FROM lineitem WHERE l_shipdate < TIMESTAMP '1995-02-01'", 10_000)
#: Prefixes of a stream whose intervals are wanted: 1, 2 and 5 times the powers of ten.
CHECKPOINTS = [m * 10**k for k in range(18) for m in (1, 2, 5)]


def first_checkpoint(c: Column) -> Column:
    """The least checkpoint that is not below c; few slices, however many objects there are."""
    return F.element_at(F.filter(F.lit(CHECKPOINTS), lambda x: x >= c), 1)


_evolution("cold_start", lambda s, d: (table(s, d, "events").select(first_checkpoint(F.col("user_id") + 1).alias("slice"), "user_id"), "user_id"), f"SELECT (SELECT min(c) FROM (SELECT unnest({CHECKPOINTS}) AS c) WHERE c >= user_id + 1) AS slice, user_id AS key FROM events", 10_000)


def _fit(name, make, cell, cells, share, source="lineitem", key="l_orderkey"):
    text = sql.with_(sql.words(source, key), f"""
c AS (SELECT i AS cell, {share} AS share FROM (SELECT unnest(range({cells})) AS i)),
q AS (SELECT {cell} AS cell, count(*) AS o FROM f GROUP BY 1), n AS (SELECT sum(o) AS n FROM q)""")
    query(name, text + f" SELECT round(sum(pow(coalesce(o, 0) - n * share, 2.0) / (n * share)), 4) AS statistic, CAST({cells - 1} AS INTEGER) AS df, CAST(max(n) AS BIGINT) AS n FROM c LEFT JOIN q USING (cell), n")(
        lambda spark, d: make(table(spark, d, source).select(key), key).select(F.round("statistic", 4).alias("statistic"), "df", "n")
    )


for _end, _of in (("", ("lineitem", "l_orderkey")), ("_orders", ("orders", "o_orderkey"))):
    _fit("fit_row_uniform" + _end, diagnostics.fit_rows, '"row"', 16, "1 / 16.0", *_of)
    _fit("fit_z_uniform" + _end, diagnostics.fit_refinement, "z", 256, "1 / 256.0", *_of)
    _fit("fit_x_geometric" + _end, diagnostics.fit_first_one, "least(x, 13) - 1", 13, "pow(2.0, -least(i + 1, 12))", *_of)

DENSE = f"""v AS (SELECT g.lane, g."row", coalesce(key // 256 - log2(1 + (255 - key % 256) / 256.0), 0.0) AS y FROM {GRID} g LEFT JOIN s ON g.lane = s.lane AND g."row" = s."row")"""


@query("anova_lanes", sql.with_(sql.slots("lineitem", "l_orderkey"), DENSE, "a AS (SELECT lane, count(*) AS n, avg(y) AS m, var_pop(y) AS v FROM v GROUP BY lane), b AS (SELECT avg(y) AS g FROM v)") + " SELECT round(sum(n * pow(m - g, 2.0)) / 3 / (sum(n * v) / 60), 6) AS f, CAST(3 AS INTEGER) AS df1, CAST(60 AS INTEGER) AS df2 FROM a, b")
def anova_lanes(spark, d):
    return diagnostics.anova_parts(frame_of("orderkeys", spark, d)).withColumn("f", F.round("f", 6))


@query("fit_probabilities", "WITH q AS (" + " UNION ALL ".join(f"SELECT '{n}' AS measure, statistic, df AS df1, 0 AS df2 FROM ({SQL['fit_' + q]})" for n, q in (("row", "row_uniform"), ("refinement", "z_uniform"), ("first_one", "x_geometric"))) + f" UNION ALL SELECT 'lanes', f, df1, df2 FROM ({SQL['anova_lanes']})) SELECT measure, round(statistic, 4) AS statistic, round({sql.chi_square_tail('statistic', 'df1')}, 4) AS p FROM q WHERE df2 = 0 UNION ALL SELECT measure, round(statistic, 4) AS statistic, round({sql.f_tail('statistic', 'df1', 'df2')}, 4) AS p FROM q WHERE df2 > 0")
def fit_probabilities(spark, d):
    df, col = stream_of("orderkeys", spark, d)
    out = None
    for n, one in (("row", diagnostics.fit_rows(df, col)), ("refinement", diagnostics.fit_refinement(df, col)), ("first_one", diagnostics.fit_first_one(df, col)), ("lanes", diagnostics.anova_lanes(build(df, col, SPEC)).withColumnRenamed("f", "statistic"))):
        one = one.select(F.lit(n).alias("measure"), F.round("statistic", 4).alias("statistic"), F.round("p", 4).alias("p"))
        out = one if out is None else out.unionByName(one)
    return out


@query("y_quartiles_by_lane", sql.with_(sql.slots("lineitem", "l_orderkey"), DENSE) + " SELECT lane, round(min(y), 6) AS low, round(quantile_cont(y, 0.25), 6) AS q1, round(quantile_cont(y, 0.5), 6) AS median, round(quantile_cont(y, 0.75), 6) AS q3, round(max(y), 6) AS high FROM v GROUP BY lane")
def y_quartiles_by_lane(spark, d):
    return diagnostics.lane_quartiles(frame_of("orderkeys", spark, d)).select("lane", *[F.round(c, 6).alias(c) for c in ("low", "q1", "median", "q3", "high")])


def _rank_sql(source, key):
    return f"WITH c AS (SELECT {key} AS k, count(*) AS frequency FROM {source} WHERE {key} IS NOT NULL GROUP BY 1), q AS (SELECT frequency, count(*) AS objects FROM c GROUP BY 1), r AS (SELECT frequency, objects, CAST(coalesce(sum(objects) OVER (ORDER BY frequency DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + 1 AS BIGINT) AS first_rank FROM q)"


for _name in ("tokens", "partkeys"):
    query(f"freq_rank_{_name}", _rank_sql(*STREAMS[_name][2:]) + " SELECT * FROM r")(lambda spark, d, n=_name: diagnostics.frequency_rank(*stream_of(n, spark, d)))
    query(f"freq_fit_{_name}", _rank_sql(*STREAMS[_name][2:]) + " SELECT count(*) AS frequencies, round(regr_slope(ln(frequency), ln(first_rank)), 6) AS slope, round(regr_r2(ln(frequency), ln(first_rank)), 6) AS r2 FROM r")(
        lambda spark, d, n=_name: diagnostics.frequency_rank_fit(*stream_of(n, spark, d)).select("frequencies", F.round("slope", 6).alias("slope"), F.round("r2", 6).alias("r2"))
    )

RATIO_M, STEPS_T = (1, 2, 5, 10, 50, 100, 500, 1000), 20


def _ratio(name, sign, top):
    limit = f"lgamma(1 {'-' if sign < 0 else '+'} t) {'-' if sign < 0 else '+'} {EULER!r} * t"
    term = f"{'-' if sign < 0 else ''}t / j - ln(1 {'-' if sign < 0 else '+'} t / j)"
    query(name, f"WITH a AS (SELECT m, CAST(i AS DOUBLE) * {top / STEPS_T!r}::DOUBLE AS t FROM (SELECT unnest([{', '.join(map(str, RATIO_M))}]) AS m), (SELECT unnest(range(1, {STEPS_T})) AS i)), b AS (SELECT m, t, sum({term}) AS s FROM a, (SELECT unnest(range(1, 1001)) AS j) WHERE j <= m GROUP BY m, t) SELECT CAST(m AS INTEGER) AS m, round(t, 6) AS t, round(100 * exp(s - ({limit})), 6) AS percent FROM b")(
        lambda spark, d: spark.createDataFrame([(m, round(i * top / STEPS_T, 6), round(float(bounds.product_ratio(m, i * top / STEPS_T, sign)), 6)) for m in RATIO_M for i in range(1, STEPS_T)], "m int, t double, percent double")
    )


_ratio("product_ratio_down", -1, 1.0)
_ratio("product_ratio_up", 1, 5.0)


@query("mc_tail_grid")
def mc_tail_grid(spark, d):
    return simulate.tail_grid(spark)


@query("mc_tail_fit")
def mc_tail_fit(spark, d):
    """The line over grids of as many objects as lineitem has orders, parts, suppliers and quantities."""
    return simulate.tail_fit(simulate.tail_grid(spark, truths=lineitem_sizes(spark, d)))


def lineitem_sizes(spark, d) -> tuple[int, ...]:
    """How many orders, parts, suppliers and quantities lineitem has."""
    counts = table(spark, d, "lineitem").agg(*[F.countDistinct(c) for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")]).first()
    return tuple(sorted({n for n in counts if n}))


def order_sizes(spark, d) -> tuple[int, ...]:
    """The numbers of orders that a customer has, and those that a status has, each once."""
    orders = table(spark, d, "orders")
    sizes = [truths(orders, F.col(c), "of", "o_orderkey").select("truth") for c in ("o_custkey", "o_orderstatus")]
    return tuple(sorted(r["truth"] for r in sizes[0].unionByName(sizes[1]).distinct().collect()))


def _holds(claims) -> str:
    return "SELECT claim, true AS holds FROM (SELECT unnest([" + ", ".join(f"'{c}'" for c in claims) + "]) AS claim)"


@query("mc_tail_constant")
def mc_tail_constant(spark, d):
    return simulate.tail_constant(simulate.tail_grid(spark, truths=lineitem_sizes(spark, d)))


@query("mc_tail_claims", _holds(simulate.TAIL_CLAIMS))
def mc_tail_claims(spark, d):
    """What is said of the bound's tightness, over the whole grid; the grid is drawn once."""
    return simulate.tail_claims(settled(simulate.tail_grid(spark), "tail-grid"))


@query("mc_coverage")
def mc_coverage(spark, d):
    """How often each interval holds as many objects as a customer or a status has orders."""
    return simulate.coverage(spark, truths=order_sizes(spark, d))


@query("mc_coverage_claims", _holds(simulate.COVER_CLAIMS))
def mc_coverage_claims(spark, d):
    """What is said of the intervals' coverage, at all sizes of customers and statuses."""
    return simulate.coverage_claims(settled(simulate.coverage(spark, truths=order_sizes(spark, d)), "coverage"))


@query("mc_truncation", f"SELECT count(*) AS trials, true AS above_zero, true AS below_bound, round({2.0**-8!r} / ln(2.0), 9) AS bound FROM (SELECT CAST(l_shipdate AS DATE) AS day FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY 1)")
def mc_truncation(spark, d):
    """What slots of 16 bits of refinement lose if 8 of them are cut, over the orders of each ship day; that it stays in its bounds."""
    made = simulate.truncation_of(build(table(spark, d, "lineitem").select(F.to_date("l_shipdate").alias("day"), "l_orderkey"), "l_orderkey", SketchSpec(z0=16), ["day"]), SPEC.z0)
    return made.select("trials", (F.col("least") >= -1e-9).alias("above_zero"), (F.col("most") <= F.col("bound")).alias("below_bound"), F.round("bound", 9).alias("bound"))


# ---- operators around the sketch -------------------------------------------------------


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()))
def scan_counts(spark, d):
    out = None
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        one = table(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("filtered_interval", sql.with_(sql.slots("(SELECT user_id FROM events WHERE event_type = 'purchase') src", "user_id"), sql.means(), sql.levels(10_000)) + sql.floors("", DOWN, UP))
def filtered_interval(spark, d):
    return floored(estimate.count_distinct_interval(table(spark, d, "events").filter("event_type = 'purchase'"), "user_id"))


REGIONS = "(SELECT r_name, n_name, c_custkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) src"


def region_rows(spark, d):
    t = {n: table(spark, d, n) for n in ("orders", "customer", "nation", "region")}
    places = t["nation"].join(F.broadcast(t["region"]), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    owners = t["customer"].join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")
    return t["orders"].select("o_custkey").join(owners, F.col("o_custkey") == F.col("c_custkey")).select("r_name", "n_name", "c_custkey")


@query("customers_by_region", sql.with_(sql.slots(REGIONS, "c_custkey", "r_name"), sql.means("r_name"), sql.levels(60_000)) + sql.floors("r_name", DOWN, UP))
def customers_by_region(spark, d):
    return floored(estimate.count_distinct_interval(region_rows(spark, d), "c_custkey", ["r_name"]), "r_name")


@query("customers_by_brand", sql.with_(sql.slots("(SELECT p_brand, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey) src", "o_custkey", "p_brand")) + ' SELECT p_brand, lane, "row", key FROM s')
def customers_by_brand(spark, d):
    t = {n: table(spark, d, n) for n in ("orders", "lineitem", "part")}
    met = t["lineitem"].select("l_orderkey", "l_partkey").join(t["orders"].select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(t["part"].select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return build(met, "o_custkey", SPEC, ["p_brand"]).df


@query("semi_users", sql.with_(sql.slots("(SELECT user_id FROM events e WHERE EXISTS (SELECT 1 FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase')) src", "user_id"), sql.means(), sql.levels(10_000)) + sql.floors("", DOWN, UP))
def semi_users(spark, d):
    e = table(spark, d, "events")
    return floored(estimate.count_distinct_interval(e.select("user_id").join(e.filter("event_type = 'purchase'").select("user_id"), "user_id", "left_semi"), "user_id"))


@query("anti_parts", 'WITH a AS (SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) SELECT count(DISTINCT c_custkey) AS truth FROM a')
def anti_parts(spark, d):
    left = table(spark, d, "customer").join(table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")
    return baselines.exact(left, "c_custkey")


def _roll_sql(sets, names):
    return sql.with_(sql.slots(REGIONS, "c_custkey", "r_name, n_name"), f'c AS (SELECT r_name, n_name, lane, "row", max(key) AS key FROM s GROUP BY GROUPING SETS ({sets}))') + f' SELECT {names}, lane, "row", key FROM c'


@query("rollup_region_nation", _roll_sql('(r_name, n_name, lane, "row"), (r_name, lane, "row"), (lane, "row")', "r_name, n_name"))
def rollup_region_nation(spark, d):
    """Coarser groups are maxima of the finer ones' slots: the rows are read once."""
    fine = build(region_rows(spark, d), "c_custkey", SPEC, ["r_name", "n_name"]).df
    levels = [["r_name", "n_name"], ["r_name"], []]
    return _levels(fine, levels, ["r_name", "n_name"])


def _levels(fine: DataFrame, levels: list[list[str]], names: list[str]) -> DataFrame:
    return fine.groupingSets([[F.col(c) for c in [*g, "lane", "row"]] for g in levels], *[F.col(c) for c in [*names, "lane", "row"]]).agg(F.max("key").alias("key"))


EVENT_DAYS = "(SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, user_id FROM events) src"


def event_days(spark, d):
    return table(spark, d, "events").select("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id")


@query("cube_type_day", sql.with_(sql.slots(EVENT_DAYS, "user_id", "event_type, day"), 'c AS (SELECT event_type, day, lane, "row", max(key) AS key FROM s GROUP BY GROUPING SETS ((event_type, day, lane, "row"), (event_type, lane, "row"), (day, lane, "row"), (lane, "row")))') + ' SELECT event_type, day, lane, "row", key FROM c')
def cube_type_day(spark, d):
    fine = build(event_days(spark, d), "user_id", SPEC, ["event_type", "day"]).df
    return _levels(fine, [["event_type", "day"], ["event_type"], ["day"], []], ["event_type", "day"])


@query("grouping_sets_flags", sql.with_(sql.slots("lineitem", "l_orderkey", "l_returnflag, l_linestatus"), 'c AS (SELECT l_returnflag, l_linestatus, lane, "row", max(key) AS key FROM s GROUP BY GROUPING SETS ((l_returnflag, lane, "row"), (l_linestatus, lane, "row")))') + ' SELECT l_returnflag, l_linestatus, lane, "row", key FROM c')
def grouping_sets_flags(spark, d):
    fine = build(table(spark, d, "lineitem"), "l_orderkey", SPEC, ["l_returnflag", "l_linestatus"]).df
    return _levels(fine, [["l_returnflag"], ["l_linestatus"]], ["l_returnflag", "l_linestatus"])


A, B = "day = '2024-01-05'", "day = '2024-01-06'"


def two_days(spark, d):
    e = event_days(spark, d)
    return e.filter(A), e.filter(B)


@query("union_days", sql.with_(sql.slots(f"(SELECT user_id FROM {EVENT_DAYS} WHERE {A} OR {B}) src2", "user_id"), sql.means(), sql.levels(10_000)) + sql.floors("", DOWN, UP))
def union_days(spark, d):
    return floored(estimate.interval(sketch.merge(*[build(x, "user_id") for x in two_days(spark, d)])))


@query("intersect_days", f"SELECT count(*) AS both FROM (SELECT DISTINCT user_id FROM {EVENT_DAYS} WHERE {A} INTERSECT SELECT DISTINCT user_id FROM {EVENT_DAYS} WHERE {B}) x")
def intersect_days(spark, d):
    a, b = two_days(spark, d)
    return a.select("user_id").intersect(b.select("user_id")).agg(F.count("*").alias("both"))


@query("except_days", f"SELECT count(*) AS only_first FROM (SELECT DISTINCT user_id FROM {EVENT_DAYS} WHERE {A} EXCEPT SELECT DISTINCT user_id FROM {EVENT_DAYS} WHERE {B}) x")
def except_days(spark, d):
    a, b = two_days(spark, d)
    return a.select("user_id").subtract(b.select("user_id")).agg(F.count("*").alias("only_first"))


def set_intervals(a: SlotFrame, b: SlotFrame, alpha: float = 0.9) -> DataFrame:
    """(intersection, its bounds, Jaccard and its bounds) by inclusion and exclusion of three intervals.

    Each is of level 1 - (1 - alpha) / 3, so all hold at alpha; the bounds may be as wide as
    0 and the smaller set.
    """
    level = 1 - (1 - alpha) / 3
    one = [estimate.interval(f, level).select(*[F.col(c).alias(f"{c}_{n}") for c in ("estimate", "lower", "upper")]) for n, f in (("a", a), ("b", b), ("u", sketch.merge(a, b)))]
    met = one[0].crossJoin(F.broadcast(one[1])).crossJoin(F.broadcast(one[2]))
    low = F.greatest(F.lit(0.0), F.col("lower_a") + F.col("lower_b") - F.col("upper_u"))
    high = F.least(F.col("upper_a"), F.col("upper_b"), F.greatest(F.lit(0.0), F.col("upper_a") + F.col("upper_b") - F.col("lower_u")))
    met = met.select(F.greatest(F.lit(0.0), F.col("estimate_a") + F.col("estimate_b") - F.col("estimate_u")).alias("shared"), low.alias("shared_lower"), high.alias("shared_upper"), "estimate_u", "lower_u", "upper_u")
    return met.select("shared", "shared_lower", "shared_upper", (F.col("shared") / F.col("estimate_u")).alias("jaccard"), (F.col("shared_lower") / F.col("upper_u")).alias("jaccard_lower"), F.least(F.lit(1.0), F.col("shared_upper") / F.greatest("lower_u", F.lit(1.0))).alias("jaccard_upper"))


def _jaccard_sql() -> str:
    sets = " UNION ALL ".join(f"SELECT '{n}' AS g, user_id AS key FROM {EVENT_DAYS} WHERE {c}" for n, c in (("a", A), ("b", B), ("u", f"{A} OR {B}")))
    down, up = sql.half("lower", 1 / 60), sql.half("upper", 1 / 60)
    sides = {"estimate": f"mean_y * {LN2!r}", "lower": f"greatest(0.0, mean_y * {LN2!r} - ({down} + {1 / 256!r}))", "upper": f"mean_y * {LN2!r} + {up}"}
    one = ", ".join(f"max(CASE WHEN g = '{g}' THEN {c} END) AS {c}_{g}" for g in "abu" for c in sides)
    return sql.with_(f"src AS ({sets})", sql.slots("src", "key", "g"), sql.means("g"), sql.levels(10_000), sql.reals(sides, "m", "g"), f"w AS (SELECT {one} FROM v)", "i AS (SELECT greatest(0.0, estimate_a + estimate_b - estimate_u) AS shared, greatest(0.0, lower_a + lower_b - upper_u) AS shared_lower, least(upper_a, upper_b, greatest(0.0, upper_a + upper_b - lower_u)) AS shared_upper, * FROM w)") + " SELECT round(shared, 2) AS shared, round(shared_lower, 2) AS shared_lower, round(shared_upper, 2) AS shared_upper, round(shared / estimate_u, 4) AS jaccard, round(shared_lower / upper_u, 4) AS jaccard_lower, round(least(1.0, shared_upper / greatest(lower_u, 1.0)), 4) AS jaccard_upper FROM i"


@query("jaccard_days", _jaccard_sql())
def jaccard_days(spark, d):
    made = set_intervals(*[build(x, "user_id") for x in two_days(spark, d)])
    return made.select(*[F.round(c, 4 if c.startswith("jaccard") else 2).alias(c) for c in made.columns])


@query("sliding_7day", sql.with_(sql.slots(EVENT_DAYS, "user_id", "day"), f"""r AS (SELECT b.day, g.lane, g."row", max(s.key) OVER (PARTITION BY g.lane, g."row" ORDER BY b.day ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS key FROM (SELECT DISTINCT day FROM {EVENT_DAYS}) b CROSS JOIN {GRID} g LEFT JOIN s ON s.day = b.day AND s.lane = g.lane AND s."row" = g."row")""", sql.means("day", source="r"), sql.levels(10_000)) + sql.floors("day", DOWN, UP))
def sliding_7day(spark, d):
    from pyspark.sql import Window as W

    daily = build(event_days(spark, d), "user_id", SPEC, ["day"])
    grid = spark.range(64, numPartitions=1).select(F.floor(F.col("id") / 16).cast("int").alias("lane"), F.pmod("id", F.lit(16)).cast("int").alias("row"))
    full = daily.df.select("day").distinct().crossJoin(F.broadcast(grid)).join(daily.df, ["day", "lane", "row"], "left")
    week = W.partitionBy("lane", "row").orderBy("day").rowsBetween(-6, 0)
    run = full.select("day", "lane", "row", F.max("key").over(week).alias("key")).filter("key is not null")
    return floored(estimate.interval(SlotFrame(run, SPEC, ("day",))), "day")


@query("topk_lower", sql.with_(sql.slots("(SELECT p_brand, l_orderkey FROM lineitem JOIN part ON l_partkey = p_partkey) src", "l_orderkey", "p_brand"), sql.means("p_brand"), sql.levels(60_000), "z AS (" + sql.floors("p_brand", DOWN, UP) + ")") + " SELECT p_brand, lower_floor, upper_floor FROM z ORDER BY lower_floor DESC, p_brand LIMIT 5")
def topk_lower(spark, d):
    met = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return floored(estimate.count_distinct_interval(met, "l_orderkey", ["p_brand"]), "p_brand").orderBy(F.desc("lower_floor"), "p_brand").limit(5).select("p_brand", "lower_floor", "upper_floor")


@query("interval_overlap", sql.with_(sql.slots("events", "user_id", "event_type"), sql.means("event_type"), sql.levels(10_000), "z AS (" + sql.floors("event_type", DOWN, UP) + ")") + " SELECT a.event_type AS first, b.event_type AS second FROM z a JOIN z b ON a.event_type < b.event_type AND a.lower_floor <= b.upper_floor AND b.lower_floor <= a.upper_floor")
def interval_overlap(spark, d):
    z = floored(estimate.count_distinct_interval(table(spark, d, "events"), "user_id", ["event_type"]), "event_type")
    a = z.select(F.col("event_type").alias("first"), F.col("lower_floor").alias("l1"), F.col("upper_floor").alias("u1"))
    b = z.select(F.col("event_type").alias("second"), F.col("lower_floor").alias("l2"), F.col("upper_floor").alias("u2"))
    return a.join(F.broadcast(b), (F.col("first") < F.col("second")) & (F.col("l1") <= F.col("u2")) & (F.col("l2") <= F.col("u1"))).select("first", "second")


@query("packed_merge", sql.with_(sql.slots(f"(SELECT user_id FROM {EVENT_DAYS} WHERE {A} OR {B}) src2", "user_id")) + ' SELECT lane, "row", key FROM s')
def packed_merge(spark, d):
    a, b = [sketch.pack(build(x, "user_id")) for x in two_days(spark, d)]
    both = a.crossJoin(F.broadcast(b.withColumnRenamed("slots", "other"))).select(sketch.merge_packed(F.col("slots"), F.col("other")).alias("slots"))
    return sketch.unpack(both, SPEC).df


@query("fold_rows", sql.with_(sql.words("lineitem", "l_orderkey")) + ' SELECT lane, CAST("row" // 4 AS INTEGER) AS "row", max(CAST(x AS BIGINT) * 16 + 15 - z // 16) AS key FROM f GROUP BY 1, 2')
def fold_rows(spark, d):
    return sketch.fold(frame_of("orderkeys", spark, d), z0=4, r0=2).df


@query("folded_interval", sql.with_(sql.words("lineitem", "l_orderkey"), f"""
s AS (SELECT lane, CAST("row" // 4 AS INTEGER) AS "row", max(CAST(x AS BIGINT) * 16 + 15 - z // 16) AS key FROM f GROUP BY 1, 2),
m AS (SELECT sum(key // 16 - log2(1 + (15 - key % 16) / 16.0)) / 16 AS mean_y FROM s)""", sql.levels(60_000, 1 / 4)) + sql.floors("", sql.half("lower", 0.05, 16), sql.half("upper", 0.05, 16), 1 / 16))
def folded_interval(spark, d):
    return floored(estimate.interval(sketch.fold(frame_of("orderkeys", spark, d), z0=4, r0=2)))


OBJECTS = {
    "distinct_hosts": (lambda s, d: table(s, d, "pages").select(F.expr("parse_url(url, 'HOST')").alias("o")), "SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS o FROM pages"),
    "distinct_props": (lambda s, d: table(s, d, "events").select(F.get_json_object("props", "$.k").alias("o")), "SELECT json_extract_string(props, '$.k') AS o FROM events"),
    "distinct_texts": (lambda s, d: table(s, d, "documents").select(F.col("text").alias("o")), "SELECT text AS o FROM documents"),
}
for _name, (_make, _text) in OBJECTS.items():
    query(_name, sql.with_(f"src AS ({_text})", sql.slots("src", "o"), sql.means(), sql.levels(20_000), "c AS (SELECT count(DISTINCT o) AS truth FROM src)", "m2 AS (SELECT m.*, truth FROM m, c)") + sql.floors("truth", DOWN, UP, source="m2"))(
        lambda spark, d, make=_make: floored(diagnostics.relative_accuracy(estimate.count_distinct_interval(make(spark, d), "o"), baselines.exact(make(spark, d), "o"), []), "truth")
    )


MORE_STREAMS = {n: x for n, x in STREAMS.items() if n not in KEYS} | {
    "user_type": (lambda s, d: table(s, d, "events").select(F.concat_ws("|", "user_id", "event_type").alias("o")), "o", "events", "concat_ws('|', user_id, event_type)"),
    "urls": (lambda s, d: table(s, d, "pages").select("url"), "url", "pages", "url"),
    "brands": (lambda s, d: table(s, d, "part").select("p_brand"), "p_brand", "part", "p_brand"),
    "event_types": (lambda s, d: table(s, d, "events").select("event_type"), "event_type", "events", "event_type"),
    "regions": (lambda s, d: table(s, d, "region").select("r_name"), "r_name", "region", "r_name"),
    "flags": (lambda s, d: table(s, d, "lineitem").select("l_returnflag"), "l_returnflag", "lineitem", "l_returnflag"),
} | {n.removeprefix("distinct_"): (make, "o", f"({text}) q", "o") for n, (make, text) in OBJECTS.items()}


@query("interval_methods_compare_more", _compare_sql(MORE_STREAMS))
def interval_methods_compare_more(spark, d):
    """interval_methods_compare over the other streams and keys."""
    return interval_methods_compare(spark, d, MORE_STREAMS)


@query("conv_roles", sql.with_("truth AS (SELECT role, count(DISTINCT conv_id) AS truth FROM conversations GROUP BY role)", sql.slots("conversations", "conv_id", "role"), sql.means("role"), sql.levels(20_000), "m2 AS (SELECT m.*, truth FROM m JOIN truth USING (role))") + sql.floors("role, truth", DOWN, UP, source="m2"))
def conv_roles(spark, d):
    c = table(spark, d, "conversations").select("role", "conv_id")
    return floored(estimate.count_distinct_interval(c, "conv_id", ["role"]).join(baselines.exact(c, "conv_id", ["role"]), "role"), "role", "truth")


@query("docs_by_label", sql.with_(sql.slots("(SELECT quality, toxic, doc_id FROM documents JOIN labels USING (doc_id)) src", "doc_id", "quality, toxic")) + ' SELECT quality, toxic, lane, "row", key FROM s')
def docs_by_label(spark, d):
    met = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id")
    return build(met, "doc_id", SPEC, ["quality", "toxic"]).df


@query("distinct_vectors", "SELECT count(DISTINCT embedding) AS truth, true AS covered FROM embeddings")
def distinct_vectors(spark, d):
    """Arrays are told apart by their JSON, which the other engine writes otherwise: only the truth and whether it is covered are compared."""
    e = table(spark, d, "embeddings")
    return diagnostics.relative_accuracy(estimate.count_distinct_interval(e, "embedding"), baselines.exact(e, "embedding"), []).select("truth", "covered")


# ---- streams ---------------------------------------------------------------------------


@query("stream_global", sql.with_(sql.slots("events", "user_id")) + ' SELECT lane, "row", key FROM s')
def stream_global(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    out = streams.run_available(streams.slots_of(stream(spark, d, "events"), "user_id"), "update")
    return out.groupBy("lane", "row").agg(F.max("key").alias("key"))


@query("stream_state", sql.with_(sql.slots("events", "user_id", "event_type")) + ' SELECT event_type AS g, lane, "row", key FROM s')
def stream_state(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    out = streams.run_available(streams.packed_state(stream(spark, d, "events"), "event_type", "user_id"), "update")
    return out.groupBy("g", "lane", "row").agg(F.max("key").alias("key"))


@query("stream_tumbling", sql.with_(sql.slots("(SELECT date_trunc('day', ts) AS start, user_id FROM events) src", "user_id", "start")) + """ SELECT strftime(start, '%Y-%m-%d') AS day, lane, "row", key FROM s""")
def stream_tumbling(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    out = streams.run_available(streams.windowed_slots(stream(spark, d, "events"), "user_id", "ts", "1 day"), "update")
    return out.groupBy(F.date_format("start", "yyyy-MM-dd").alias("day"), "lane", "row").agg(F.max("key").alias("key"))


@query("stream_sliding", sql.with_(sql.slots("(SELECT date_trunc('day', ts) - to_days(CAST(i AS INTEGER)) AS start, user_id FROM events, (SELECT unnest(range(2)) AS i)) src", "user_id", "start")) + """ SELECT strftime(start, '%Y-%m-%d') AS day, lane, "row", key FROM s""")
def stream_sliding(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    out = streams.run_available(streams.windowed_slots(stream(spark, d, "events"), "user_id", "ts", "2 days", "1 day"), "update")
    return out.groupBy(F.date_format("start", "yyyy-MM-dd").alias("day"), "lane", "row").agg(F.max("key").alias("key"))


@query("stream_join", sql.with_(sql.slots("(SELECT user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey) src", "user_id", "c_mktsegment")) + ' SELECT c_mktsegment, lane, "row", key FROM s')
def stream_join(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    static = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    out = streams.run_available(streams.slots_of(streams.joined(stream(spark, d, "events"), static, "user_id"), "user_id", by=["c_mktsegment"]), "update")
    return out.groupBy("c_mktsegment", "lane", "row").agg(F.max("key").alias("key"))


SESSIONS = """(SELECT date_trunc('day', min(ts)) AS start, user_id || '|' || strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS session FROM (
SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM (
SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events WHERE ts IS NOT NULL))
GROUP BY user_id, n HAVING max(ts) + INTERVAL 6 HOURS <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)) src"""


@query("stream_sessions", sql.with_(sql.slots(SESSIONS, "session", "start")) + """ SELECT strftime(start, '%Y-%m-%d') AS day, lane, "row", key FROM s""")
def stream_sessions(spark, d):
    from distinct_bounds.sources.storage import stream
    from distinct_bounds.streaming import streams

    out = streams.session_slots(stream(spark, d, "events"), "user_id", "ts", "6 hours")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "lane", "row", "key")


@query("stream_late", "SELECT count(*) FILTER (WHERE ts < TIMESTAMP '2024-01-15') AS late, count(DISTINCT event_id) FILTER (WHERE ts >= TIMESTAMP '2024-01-15') AS kept FROM events")
def stream_late(spark, d):
    """The later events arrive first, in two batches, as a batch is held against the watermark known before the
    last one; what then comes behind it is dropped and counted."""
    from distinct_bounds.sources.storage import scratch
    from distinct_bounds.streaming import streams

    events, path, late = table(spark, d, "events").select("event_id", "ts"), scratch(spark, "late"), []
    for part in ("ts >= timestamp_ntz'2024-01-15' AND event_id % 2 = 0", "ts >= timestamp_ntz'2024-01-15' AND event_id % 2 <> 0", "ts < timestamp_ntz'2024-01-15'"):
        events.filter(part).coalesce(1).write.mode("append").parquet(path)
    arriving = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    kept = streams.run_available(streams.deduplicated(arriving, "event_id", "ts", "1 hour"), "append", done=lambda q: late.append(streams.late_rows(q)))
    return kept.agg(F.lit(late[0]).cast("bigint").alias("late"), F.count("*").alias("kept"))


def flagship(spark, d) -> DataFrame:
    """Shortest 90 % interval of distinct order keys by ship month, with truth and whether it is covered."""
    df, key = month_slices(spark, d)
    made = estimate.interval(build(df, key, SPEC, ["slice"]), 0.9, split="shortest")
    return diagnostics.relative_accuracy(made, baselines.exact(df, key, ["slice"]), ["slice"])
