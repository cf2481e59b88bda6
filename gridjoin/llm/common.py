"""Helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StringType, StructType

#: White space that separates words, as SQL and Java patterns read it.
WORD = r"[^\x20\x09-\x0D]+"

_local_dir: str | None = None


#: Bytes of a record batch that goes to a Python worker.
BATCH_BYTES = 1 << 23


def small_batches(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """Lets Spark cut record batches at so many bytes, a runtime setting of the session: a batch and its copies, in the executor and in the worker, are
    what a task with Python needs beside its own arrays, and 10,000 long texts would be far more."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if int(spark.conf.get(key).rstrip("bB")) > most:
        spark.conf.set(key, str(most))


def hand_back(spark: SparkSession) -> None:
    """Asks the executors' JVMs to collect garbage, after which they give free heap back to the system: before a stage whose memory is in Python workers, when one with
    large sorts has filled the heap. A task for each core; an executor that gets none merely keeps its heap."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.expr("java_method('java.lang.System', 'gc')")).collect()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one where a local session names none (tests)."""
    global _local_dir
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if _local_dir is None:
        _local_dir = tempfile.mkdtemp(prefix="gridjoin_")
        atexit.register(shutil.rmtree, _local_dir, ignore_errors=True)
    return f"file://{_local_dir}"


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Cuts the lineage: writes df as Parquet into the shared folder and reads it back, so a lost executor costs only
    the tasks that were under way."""
    small_batches(df.sparkSession)
    path = fresh_path(df.sparkSession, name)
    writer = df.write
    for k, v in options.items():
        writer = writer.option(k, v)
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete_path(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def drop_stored(df: DataFrame) -> None:
    """Removes what stored() wrote for df; df is of no use afterwards."""
    files = df.inputFiles()
    if files:
        delete_path(df.sparkSession, files[0].rsplit("/", 1)[0])


def settled(df: DataFrame, name: str, *used: DataFrame) -> DataFrame:
    """df as a written table, for results that are small beside the tables they were made from, which are removed."""
    out = stored(df, name)
    for x in used:
        drop_stored(x)
    return out


#: Rows of a table of ids up to which it is broadcast.
MAX_IDS = 1_000_000


def without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of docs whose doc_id is not in ids (doc_id); a null doc_id stays. The ids are written first, and broadcast while they are at most
    MAX_IDS, so that the texts need not be shuffled; above that both sides are."""
    ids = stored(ids.select("doc_id").where("doc_id IS NOT NULL").distinct(), "ids")
    few = F.broadcast if ids.count() <= MAX_IDS else (lambda d: d)
    return docs.join(few(ids), "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])


def set_aside(docs: DataFrame, names: tuple[str, ...]) -> tuple[DataFrame, list]:
    """docs with columns of these names renamed, for an operator that would replace them, and the columns that bring all back as they were."""
    taken = {c: f"__own_{c}" for c in docs.columns if c.lower() in names}
    return docs.withColumnsRenamed(taken), [F.col(f"`{taken.get(c, c)}`").alias(c) for c in docs.columns]


def text_or_empty(name: str = "text"):
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def with_columns_of(schema: StructType, *names: str) -> str:
    """A DDL string of some columns of a schema."""
    return ", ".join(f"`{n}` {schema[n].dataType.simpleString()}" for n in names)


def is_text(schema: StructType, name: str) -> bool:
    return isinstance(schema[name].dataType, StringType)


def pieces(batches, rows: int = 256):
    """Record batches cut small, for functions that make Python objects of their values."""
    for batch in batches:
        for i in range(0, batch.num_rows, rows):
            yield batch.slice(i, rows)


def sized(batches, column: str, most: int):
    """Record batches cut at about ``most`` bytes of a string column; a longer value stands alone."""
    import numpy as np
    import pyarrow.compute as pc

    for batch in batches:
        size = pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
        at = np.cumsum(size)
        i = 0
        while i < batch.num_rows:
            j = max(i + 1, int(np.searchsorted(at, (at[i - 1] if i else 0) + most, "right")))
            yield batch.slice(i, j - i)
            i = j


def lean(run):
    """A function for mapInArrow that hands freed memory back to the system when a task ends: workers live on, and stages with other needs follow."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            import ctypes

            import pyarrow as pa

            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # not glibc
                pass

    return task
