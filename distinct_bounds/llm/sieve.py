"""A Bloom filter as a table of bitmaps, built and read with SQL functions alone."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import materialize

#: A filter never has more bits, so no more than 64 MB are broadcast. One that is to hold more rows than that lets
#: more through; exact copies deal their rows to as many filters as keep BITS_A_ROW bits for each row.
MOST_BITS = 1 << 29
LEAST_BITS = 1 << 16
BITS_A_ROW = 16


@dataclass(frozen=True)
class Sieve:
    """bitmaps: (bucket, bits), at most bits / 32768 rows of 4 KB; two cells of each hash are looked up."""

    bitmaps: DataFrame
    bits: int

    def passing(self, df: DataFrame, hash_col: str, flag: str) -> DataFrame:
        """df with a boolean `flag`: whether both cells of hash_col are set. A broadcast join for each cell, no shuffle."""
        for k, cell in enumerate(cells(F.col(hash_col), self.bits)):
            side = F.broadcast(self.bitmaps.select(F.col("bucket").alias(f"_bucket{k}"), F.col("bits").alias(f"_bits{k}")))
            place = F.bitmap_bit_position(cell)
            octet = F.substring(F.col(f"_bits{k}"), F.floor(place / 8).cast("int") + 1, F.lit(1))
            df = df.withColumn(f"_at{k}", F.bitmap_bucket_number(cell)).join(side, F.col(f"_at{k}") == F.col(f"_bucket{k}"), "left")
            df = df.withColumn(f"_set{k}", F.coalesce(F.getbit(F.conv(F.hex(octet), 16, 10).cast("bigint"), (place % 8).cast("int")) == 1, F.lit(False)))
        return df.withColumn(flag, F.col("_set0") & F.col("_set1")).drop(*[f"{n}{k}" for n in ("_at", "_bucket", "_bits", "_set") for k in (0, 1)])


def cells(hashed: Column, bits: int) -> tuple[Column, Column]:
    """Two cells of a 64-bit hash, from 1 on."""
    return hashed.bitwiseAND(F.lit(bits - 1)) + 1, F.shiftrightunsigned(hashed, 33).bitwiseAND(F.lit(bits - 1)) + 1


def filters_for(rows: int) -> int:
    """How many filters of MOST_BITS it takes to keep BITS_A_ROW bits for each row."""
    return max(1, -(-rows * BITS_A_ROW // MOST_BITS))


def size_for(rows: int) -> int:
    return min(MOST_BITS, max(LEAST_BITS, 1 << math.ceil(math.log2(max(2, BITS_A_ROW * rows)))))


def build(hashes: DataFrame, rows: int, least: int = 1) -> Sieve:
    """The filter of a one-column DataFrame of 64-bit hashes: cells that at least `least` of its rows hit.

    Cells are counted per task before the shuffle, so a hash that fills the table costs
    one row a task.
    """
    bits, name = size_for(rows), hashes.columns[0]
    hit = hashes.select(F.explode(F.array_distinct(F.array(*cells(F.col(name), bits)))).alias("cell"))
    met = hit.groupBy("cell").agg(F.count("*").alias("n")).filter(F.col("n") >= least)
    maps = met.groupBy(F.bitmap_bucket_number("cell").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("cell")).alias("bits"))
    return Sieve(materialize(maps, "sieve"), bits)
