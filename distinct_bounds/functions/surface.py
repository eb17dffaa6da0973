"""SQL names for the sketches: scalar functions, grouped aggregates and a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from distinct_bounds.functions import bounds
from distinct_bounds.functions.solvers import hp_inverse_vec, psi_inverse
from distinct_bounds.functions.special import LN2, hp
from distinct_bounds.sources.shipping import ship
from distinct_bounds.spec import SketchSpec


def mean_of(keys: np.ndarray, spec: SketchSpec) -> float:
    """Mean value of slots from their keys; slots without one count 0."""
    x, z = keys // spec.steps, spec.steps - 1 - keys % spec.steps
    return float((x - np.log2(1 + z / spec.steps)).sum() / spec.slots)


def packed_of(words: list[str], spec: SketchSpec) -> bytes:
    """A sketch of hex digests as packed numbers, for grouped aggregates: hexslice layout, a split digest."""
    held = np.zeros(spec.slots, np.int64)
    r, z = spec.r0 // 4, spec.z0 // 4
    for d in words:
        for lane in range(spec.c0):
            w = d[16 * lane : 16 * lane + 16]
            row, ref, v = int(w[:r] or "0", 16), int(w[16 - z :] or "0", 16), int(w[r : 16 - z], 16)
            x = spec.first_one_bits + 1 - v.bit_length()
            at = lane * spec.rows + row
            held[at] = max(held[at], x * spec.steps + spec.steps - 1 - ref)
    return held.tobytes()


def register(spark: SparkSession, spec: SketchSpec = SketchSpec()) -> None:
    """Define the functions in the session.

    sketch_y(key), sketch_row(word), sketch_key(word): plain SQL. distinct_hp(x),
    distinct_point(mean), digamma_inverse(y): vectorised. sketch_agg(text), sketch_merge(packed):
    grouped aggregates to packed sketches, for convenience: they see all rows of a group in
    one task, so large tables should be sketched with build(). distinct_interval(TABLE(lane,
    row, key), alpha): the interval of a table of slots.
    """
    if (spec.family, spec.layout) != ("sha2", "hexslice") or (spec.word_r0, spec.word_z0) != (spec.r0, spec.z0):
        raise ValueError("the SQL functions read split digests cut at hex digits")
    ship(spark)
    steps, p = spec.steps, spec.p
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_y(key BIGINT) RETURNS DOUBLE RETURN floor(key / {steps}) - log2(1 + ({steps - 1} - key % {steps}) / {float(steps)}D)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_row(word STRING) RETURNS INT RETURN CAST(conv(substr(word, 1, {spec.r0 // 4}), 16, 10) AS INT)")
    value = f"CAST(conv(substr(word, {1 + spec.r0 // 4}, {spec.first_one_bits // 4}), 16, 10) AS BIGINT)"
    first = f"(CASE WHEN {value} = 0 THEN {spec.saturated} ELSE {spec.first_one_bits + 1} - length(bin({value})) END)"
    ref = f"CAST(conv(substr(word, {17 - spec.z0 // 4}, {spec.z0 // 4}), 16, 10) AS BIGINT)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_key(word STRING) RETURNS BIGINT RETURN CAST({first} AS BIGINT) * {steps} + {steps - 1} - {ref}")

    @F.pandas_udf("double")
    def distinct_hp(x: pd.Series) -> pd.Series:
        return pd.Series(hp(x.to_numpy(float), p))

    @F.pandas_udf("double")
    def distinct_point(mean: pd.Series) -> pd.Series:
        return pd.Series(hp_inverse_vec(mean.to_numpy(float) * LN2, p))

    @F.pandas_udf("double")
    def digamma_inverse(y: pd.Series) -> pd.Series:
        return y.map(psi_inverse)

    @F.pandas_udf("binary")
    def sketch_agg(texts: pd.Series) -> bytes:
        import hashlib

        return packed_of([hashlib.sha256(str(t).encode()).hexdigest() for t in texts.dropna()], spec)

    @F.pandas_udf("binary")
    def sketch_merge(packed: pd.Series) -> bytes:
        held = np.zeros(spec.slots, np.int64)
        for x in packed.dropna():
            held = np.maximum(held, np.frombuffer(x, np.int64))
        return held.tobytes()

    for name, f in (("distinct_hp", distinct_hp), ("distinct_point", distinct_point), ("digamma_inverse", digamma_inverse), ("sketch_agg", sketch_agg), ("sketch_merge", sketch_merge)):
        spark.udf.register(name, f)

    class DistinctInterval:
        def __init__(self):
            self.keys, self.alpha = [], 0.9

        def eval(self, row, alpha: float):
            self.keys.append(row["key"])
            self.alpha = float(alpha)

        def terminate(self):
            middle = mean_of(np.array(self.keys, np.int64), spec) * LN2
            down, up = bounds.budget(self.alpha, spec.slots)
            found = hp_inverse_vec(np.array([middle, max(0.0, middle - down - 2.0**-spec.z0), middle + up]), p)
            yield float(found[0]), float(found[1]), float(found[2])

    spark.udtf.register("distinct_interval", F.udtf(DistinctInterval, returnType="estimate double, lower double, upper double"))
