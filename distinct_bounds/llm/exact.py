"""Exact duplicates: a first pass finds cells of a Bloom filter that are hit twice, a second one lets
only rows whose cells are all hit twice into a shuffle. DataFrame functions only."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm import sieve
from distinct_bounds.llm.common import col, materialize, scratch_dir, table, without

OUTPUTS = ("keep_id", "group_size", "kept", "text_sha256")


def normalised(text: Column) -> Column:
    """The text with each run of ASCII white space as one space; null counts as empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")


def mark_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slim: bool = False) -> DataFrame:
    """docs with keep_id, group_size, kept and text_sha256.

    Of rows with equal normalised text the one with the smallest id is kept, null ids last;
    of rows that repeat that id one is kept. keep_id is the kept row's id, null only where
    all ids of the group are null. Null texts equal empty ones. An empty table gives an
    empty one. With slim only the id and the new columns are returned, and texts are read
    once. A filter has 16 bits for each row and is broadcast, 64 MB at most: rows of a table
    that needs more are written in parts by a hash of their digest, without a shuffle, and each
    part has a filter of its own. Rows that pass the filter are written to the shared folder with a number of their
    own, so that the choice among repeated rows survives lost executors.
    """
    kept = [id_col] if slim else without(docs, OUTPUTS).columns
    sha = F.sha2(normalised(col(text_col)).cast("binary"), 256).alias("_sha")
    base = docs.select(F.struct(*[col(c) for c in kept]).alias("_doc"), col(id_col).alias("_id"), sha)
    rows = docs.count()
    parts = sieve.filters_for(rows)
    if parts == 1:
        return named(marked(materialize(base, "digests") if slim else base, rows), kept)
    dealt = materialize(base.withColumn("_part", F.pmod(F.xxhash64("_sha", F.lit("part")), F.lit(parts)).cast("int")), "digests", by="_part")
    path = f"{scratch_dir(docs.sparkSession).rstrip('/')}/marked-{uuid.uuid4().hex}"
    for part in range(parts):
        made = marked(dealt.filter(F.col("_part") == part).drop("_part"), -(-rows // parts))
        made.write.parquet(f"{path}/part={part}")
    return named(docs.sparkSession.read.schema(made.schema).parquet(*[f"{path}/part={part}" for part in range(parts)]), kept)


def marked(base: DataFrame, rows: int) -> DataFrame:
    """(_doc, _sha, _keep, _n, _kept) of base(_doc, _id, _sha), of about so many rows, by one filter."""
    hashed = base.withColumn("_hash", F.xxhash64("_sha"))
    filter_ = sieve.build(hashed.select("_hash"), rows, least=2)
    flagged = filter_.passing(hashed, "_hash", "_maybe").drop("_hash")

    alone = flagged.filter(~F.col("_maybe"))
    alone = alone.select("_doc", "_sha", F.col("_id").alias("_keep"), F.lit(1).cast("bigint").alias("_n"), F.lit(True).alias("_kept"))

    maybe = materialize(flagged.filter("_maybe").drop("_maybe").withColumn("_row", F.monotonically_increasing_id()), "candidates")
    first = F.min(F.struct(F.col("_id").isNull().alias("none"), F.col("_id").alias("id"), F.col("_row").alias("row"))).alias("_first")
    groups = materialize(maybe.groupBy(F.col("_sha").alias("_group")).agg(first, F.count("*").alias("_n")), "groups")
    met = maybe.join(groups, F.col("_sha") == F.col("_group"))
    met = met.select("_doc", "_sha", F.col("_first.id").alias("_keep"), "_n", (F.col("_row") == F.col("_first.row")).alias("_kept"))
    return alone.unionByName(met)


def named(made: DataFrame, kept: list[str]) -> DataFrame:
    new = zip(("_keep", "_n", "_kept", "_sha"), OUTPUTS, strict=True)
    return made.select(*[F.col("_doc")[c].alias(c) for c in kept], *[F.col(a).alias(b) for a, b in new])


def op9_exact(spark, sf_dir: str) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every document."""
    return mark_copies(table(spark, sf_dir, "documents").select("doc_id", "text"), slim=True).select("doc_id", *OUTPUTS)


def drop_copies(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: one row of each group of equal texts, with the documents' own columns. Null texts equal empty
    ones, so one of them stays; of rows that repeat the smallest id one stays; an empty table stays empty."""
    return mark_copies(docs).filter("kept").select(*[col(c) for c in docs.columns])


OP9_SQL = r"""
WITH d AS (
  SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS h FROM documents
)
SELECT doc_id, min(doc_id) OVER (PARTITION BY h) AS keep_id, count(*) OVER (PARTITION BY h) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY h) AS kept, h AS text_sha256
FROM d
"""
