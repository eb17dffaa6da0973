"""From objects to hash words and from words to row, refinement and first-one position."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from distinct_bounds.spec import SketchSpec


def object_key(df: DataFrame, *names: str) -> Column:
    """The text by which objects are told apart; null only for one null column, which is no object.

    Numbers, booleans, dates and texts are their own text; -0.0 is 0.0 and all NaN are one;
    time stamps are their microseconds; arrays, structs and several columns are JSON with
    nulls; the entries of maps are put in order first.
    """
    if len(names) > 1:
        return F.to_json(F.struct(*[_plain(F.col(n), df.schema[n].dataType).alias(n) for n in names]), {"ignoreNullFields": "false"})
    return _text(F.col(names[0]), df.schema[names[0]].dataType)


def _plain(c: Column, kind: T.DataType) -> Column:
    return c if isinstance(kind, (T.IntegralType, T.StringType, T.BooleanType)) else _text(c, kind)


def _text(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        c = c.cast("double")
        return F.when(F.isnan(c), F.lit("NaN")).when(c == 0, F.lit("0.0")).otherwise(c.cast("string"))
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c).cast("string")
    if isinstance(kind, T.TimestampNTZType):
        return F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
    if isinstance(kind, T.BinaryType):
        return F.hex(c)
    if isinstance(kind, (T.DayTimeIntervalType, T.YearMonthIntervalType)):
        return c.cast("string")
    if isinstance(kind, T.MapType):
        return F.to_json(F.array_sort(F.map_entries(c)), {"ignoreNullFields": "false"})
    if isinstance(kind, (T.ArrayType, T.StructType)):
        return F.to_json(c, {"ignoreNullFields": "false"})
    return c.cast("string")


def with_words(df: DataFrame, key: Column, spec: SketchSpec) -> DataFrame:
    """df with `_w0`, `_w1`, ...: the 64-bit hash word of each lane as a signed number.

    A digest is a column of its own below the words, as Catalyst would else compute it once a
    lane; a word is read from its 16 hex digits once. Seeded xxhash64 gives numbers as it is.
    """
    if spec.family == "xxhash64":
        return df.withColumns({f"_w{lane}": F.xxhash64(F.lit(lane), key) for lane in range(spec.c0)})
    if spec.family == "sha2":
        digest = F.sha2(key.cast("binary"), 256 if spec.c0 <= 4 else 512)
        held, digits = df.withColumn("_digest", digest), [F.substring("_digest", 16 * lane + 1, 16) for lane in range(spec.c0)]
    else:
        held, digits = df, [F.substring(F.md5(F.concat(F.lit(f"{lane}:"), key).cast("binary")), 1, 16) for lane in range(spec.c0)]
    return held.withColumns({f"_w{lane}": F.conv(d, 16, -10).cast("bigint") for lane, d in enumerate(digits)})


def low_bits(c: Column, n: int) -> Column:
    return c if n >= 64 else c.bitwiseAND(F.lit((1 << n) - 1).cast("bigint"))


def fields(word: Column, spec: SketchSpec) -> tuple[Column, Column, Column]:
    """(row, refinement, first-one field) of a hash word, by shifts and masks."""
    r, z, bits = spec.word_r0, spec.word_z0, spec.first_one_bits
    row = F.shiftrightunsigned(word, 64 - r) if r else F.lit(0)
    if spec.layout == "prefix" and spec.row_bits == "lsb" and r:
        row = sum((F.shiftright(row, r - 1 - i).bitwiseAND(F.lit(1)) * (1 << i) for i in range(1, r)), F.shiftright(row, r - 1).bitwiseAND(F.lit(1)))
    if spec.layout == "hexslice":
        refinement, value = low_bits(word, z), low_bits(F.shiftrightunsigned(word, z), bits)
    else:
        refinement, value = low_bits(F.shiftrightunsigned(word, bits), z), low_bits(word, bits)
    kept = F.shiftright(row, r - spec.r0) if r > spec.r0 else row
    held = F.shiftright(refinement, z - spec.z0) if z > spec.z0 else refinement
    return kept.cast("int"), (held if z else F.lit(0)).cast("int"), value


def with_first_one(df: DataFrame, value: str, into: str, spec: SketchSpec) -> DataFrame:
    """df with the position of the first one of `value` from the left, from 1 on; one more than the field's bits if there is none.

    All bits below the first one are set, by one doubling shift a projection, and counted.
    """
    df = df.withColumn(into, F.col(value))
    for step in (1, 2, 4, 8, 16, 32):
        df = df.withColumn(into, F.col(into).bitwiseOR(F.shiftrightunsigned(into, step)))
    return df.withColumn(into, (F.lit(spec.saturated) - F.bit_count(into)).cast("int"))


def slot_key(x: Column, z: Column, spec: SketchSpec) -> Column:
    """One number that orders slots: later first-one positions win, and of equal ones the smaller refinement."""
    return (x.cast("bigint") * spec.steps + (spec.steps - 1) - z).cast("bigint")


def lanes(df: DataFrame, key: Column, spec: SketchSpec, by: list[str] | None = None, keep: bool = False) -> DataFrame:
    """(by..., [_object], lane, row, z, v, x) for every object and lane; null keys are left out."""
    by = by or []
    held = df.select(*by, key.alias("_object")).filter(F.col("_object").isNotNull())
    named = [*by, *(["_object"] if keep else [])]
    words = F.array(*[F.struct(F.lit(lane).alias("lane"), F.col(f"_w{lane}").alias("_word")) for lane in range(spec.c0)])
    spread = with_words(held, F.col("_object"), spec).select(*named, F.inline(words))
    row, z, value = fields(F.col("_word"), spec)
    return with_first_one(spread.select(*named, "lane", row.alias("row"), z.alias("z"), value.alias("v")), "v", "x", spec)


def fields_from_bits(bits: str, spec: SketchSpec) -> tuple[int, int, int]:
    """(row, z, x) of a string of bits laid out as prefix: row, refinement, then first-one bits."""
    row_bits, z_bits, rest = bits[: spec.r0], bits[spec.r0 : spec.r0 + spec.z0], bits[spec.r0 + spec.z0 :]
    row = int(row_bits or "0", 2) if spec.row_bits == "msb" else int(row_bits[::-1] or "0", 2)
    return row + 1, int(z_bits or "0", 2), (rest.find("1") + 1) or len(rest) + 1
