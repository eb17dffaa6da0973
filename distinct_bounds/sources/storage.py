"""Tables, streams, the slot store and scratch space."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from distinct_bounds.operators.sketch import SlotFrame
from distinct_bounds.spec import SketchSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table as a stream of its files. The path is a pattern, as a plain one would have to be a folder."""
    return spark.readStream.schema(table(spark, sf_dir, name).schema).parquet(f"{sf_dir}/{name}.parque[t]")


def by_file(spark: SparkSession, path: str, format_: str = "parquet", **options) -> DataFrame:
    """A table of many files, compressed or not, with the file of each row as `slice_file`."""
    return spark.read.format(format_).options(**options).load(path).withColumn("slice_file", F.col("_metadata.file_path"))


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder of the cluster. Where none is named, a temporary one in local mode only:
    on a cluster the executors would not share it."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        found = tempfile.mkdtemp(prefix="scratch-")
        spark.sparkContext.setCheckpointDir(found)
    return f"{found.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def settled(df: DataFrame, label: str) -> DataFrame:
    """df written to scratch space and read again, where several plans are to read it."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def save_slots(frame: SlotFrame, path: str, mode: str = "overwrite", partition_by: list[str] | None = None) -> None:
    """Slots as Parquet, with the fingerprint of their spec, so that other sketches are not merged by mistake."""
    out = frame.df.withColumn("fingerprint", F.lit(frame.spec.fingerprint())).write.mode(mode)
    (out.partitionBy(*partition_by) if partition_by else out).parquet(path)


def load_slots(spark: SparkSession, path: str, spec: SketchSpec, by: tuple[str, ...] = ()) -> SlotFrame:
    """Slots of the spec from a store; of equal slots written more than once the larger counts."""
    df = spark.read.parquet(path)
    if df.filter(F.col("fingerprint") != spec.fingerprint()).limit(1).count():
        raise ValueError("the store holds slots of another spec")
    return SlotFrame(df.groupBy(*by, "lane", "row").agg(F.max("key").alias("key")), spec, by)
