"""The corpus pipeline: five stages over `documents`, each on all that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from distinct_bounds.llm.bpe import encode_stage
from distinct_bounds.llm.common import discard, materialize, swept, table
from distinct_bounds.llm.exact import drop_copies
from distinct_bounds.llm.mixing import take_mix
from distinct_bounds.llm.ngram_join import drop_near_copies
from distinct_bounds.llm.quality import keep_good

#: Name and function (spark, docs, sf_dir) of each stage; all but the last return the columns of documents.
STAGES = [
    ("quality_classifier", keep_good),
    ("exact_dedup", drop_copies),
    ("ngram_jaccard", drop_near_copies),
    ("source_mixing", take_mix),
    ("bpe_encoding", encode_stage),
]

#: A trained classifier decides in the first stage, which SQL cannot express; tests hold the
#: stages against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage over what is left; of the stages before it only the newest output is kept on disk."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        with swept() as keep:
            docs = materialize(stage(spark, docs, sf_dir), name)
            keep.append(docs)
        if before is not None:
            discard(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
