"""What the operators share: scratch tables, Arrow text functions, bounded labelled samples."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from distinct_bounds.sources.shipping import ship

#: Rows that become Python strings at a time, so that long texts never pile up.
CHUNK = 256

#: Setting of the session, and bytes of rows that Spark hands to Python at a time where it is unset.
BATCH_KEY, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", "4m"

#: Setting of the session by which an action's shuffle files go when it ends.
FREE_KEY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def col(name: str) -> Column:
    return F.col(quoted(name))


def without(df: DataFrame, names: Sequence[str]) -> DataFrame:
    """df without the columns that bear one of the names, in any case."""
    gone = {n.lower() for n in names}
    return df.select(*[col(c) for c in df.columns if c.lower() not in gone])


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder of the cluster. Where none is named, a folder of our own in local mode only, as executors
    of a cluster would not share it."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        found = tempfile.mkdtemp(prefix="scratch-")
        spark.sparkContext.setCheckpointDir(found)
    return found


@contextlib.contextmanager
def freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the actions within go when an action ends. Otherwise they stay until the driver happens to
    collect its garbage, so that a job of many actions holds nearly all of its shuffles at once."""
    had = spark.conf.get(FREE_KEY)
    spark.conf.set(FREE_KEY, "true")
    try:
        yield
    finally:
        spark.conf.set(FREE_KEY, had)


def materialize(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """df written to the shared folder, in parts by a column if one is named, and read again: lineage ends here, lost
    executors cost nothing, and the shuffles that made it are deleted."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    with freed(spark):
        (df.write.partitionBy(by) if by else df.write).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    if SWEPT:
        SWEPT[-1].append(out)
    return out


#: What materialize() wrote within each swept() that is under way.
SWEPT: list[list[DataFrame]] = []


@contextlib.contextmanager
def swept() -> Iterator[list[DataFrame]]:
    """At the end all that materialize() wrote within is deleted, but for the tables that are put into the list given;
    these are an outer one's to delete."""
    keep: list[DataFrame] = []
    SWEPT.append([])
    try:
        yield keep
    finally:
        made, stay = SWEPT.pop(), {df._scratch_path for df in keep}
        for df in made:
            if df._scratch_path not in stay:
                discard(df)
        if SWEPT:
            SWEPT[-1].extend(df for df in made if df._scratch_path in stay)


def discard(df: DataFrame) -> None:
    """Delete what materialize() wrote, once all that was made of it is written elsewhere."""
    path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._scratch_path)
    path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def settle() -> None:
    """Give memory that a task has freed back to the system; workers serve many tasks and would keep it."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def bound_batches(spark: SparkSession) -> None:
    """Bound the batches of this session in bytes, not in rows alone: ten thousand texts, or a few very long ones, would
    be held by the executor and by Python at once. A bound that the session has already is kept."""
    if spark.conf.get(BATCH_KEY, None) is None:
        spark.conf.set(BATCH_KEY, BATCH_BYTES)


def map_arrow(df: DataFrame, function, schema: str) -> DataFrame:
    """mapInArrow with this package's code on the executors."""
    ship(df.sparkSession)
    bound_batches(df.sparkSession)

    def run(batches):
        yield from function(batches)
        settle()

    return df.mapInArrow(run, schema)


def text_udf(schema: str, names: Sequence[str], make: Callable[[], Callable[[list], Sequence]]):
    """An Arrow function of one text column that returns a struct.

    make() runs once a task and returns a function from a list of texts (None included)
    to one sequence or Arrow array for each field. It is marked nondeterministic only so
    that Catalyst evaluates it once, however often its fields are used.
    """
    from pyspark.sql.pandas.types import to_arrow_type
    from pyspark.sql.types import StructType

    kinds = {f.name: to_arrow_type(f.dataType) for f in StructType.fromDDL(schema).fields}

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        work = make()
        for batch in batches:
            parts = []
            for at in range(0, len(batch), CHUNK):
                got = work(batch.slice(at, CHUNK).to_pylist())
                parts.append([x if isinstance(x, pa.Array) else pa.array(x, kinds[n]) for n, x in zip(names, got, strict=True)])
            fields = [pa.concat_arrays(x) for x in zip(*parts, strict=True)] if parts else [pa.array([], kinds[n]) for n in names]
            yield pa.StructArray.from_arrays(fields, fields=[pa.field(n, kinds[n]) for n in names])
            del batch, parts, fields
        del work
        settle()

    ship(SparkSession.active())
    bound_batches(SparkSession.active())
    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, f"struct<{schema}>").asNondeterministic()


def with_outputs(docs: DataFrame, function, text_col: str, names: Sequence[str]) -> DataFrame:
    """docs with the fields that an Arrow text function returns for text_col."""
    held = f"_r{uuid.uuid4().hex[:8]}"
    kept = [c for c in docs.columns if c.lower() not in {n.lower() for n in names}]
    return docs.withColumn(held, function(col(text_col))).select(*[col(c) for c in kept], *[F.col(f"{held}.{n}").alias(n) for n in names])


def id_remainder(id_col: str, by: int) -> Column:
    """crc32 of the id's text, modulo by; a null id counts as an empty text."""
    return F.crc32(F.coalesce(col(id_col).cast("string"), F.lit(""))) % by


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, learn: Column, limit: int, id_col: str, text_col: str) -> DataFrame:
    """At most `limit` labelled documents as (id, text, y), the same on every run.

    learn says which label rows may be learnt from. Of the label rows of one document the
    largest label counts, of its text rows the smallest text. The documents with the
    smallest hash of the id are taken, so that the sample is spread over the whole table.
    """
    ids = (
        labels.filter(learn & col(label).isNotNull() & col(id_col).isNotNull())
        .groupBy(col(id_col).alias("id"))
        .agg(F.max(col(label)).cast("int").alias("y"))
        .orderBy(F.xxhash64("id"), "id")
        .limit(limit)
    )
    texts = docs.select(col(id_col).alias("id"), F.coalesce(col(text_col), F.lit("")).alias("text"))
    return texts.join(F.broadcast(ids), "id").groupBy("id").agg(F.min("text").alias("text"), F.max("y").alias("y"))
