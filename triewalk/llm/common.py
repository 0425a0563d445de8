"""Helpers shared by the training-data operators: scratch tables, text normalisation, row reading."""

from __future__ import annotations

import atexit
import ctypes
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager, suppress

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; the path may be in any store that Spark can read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares (spark.checkpoint.dir); a temporary one only where none is set on a local master, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        import tempfile

        found = f"file://{tempfile.mkdtemp(prefix='triewalk-')}"
        spark.sparkContext.setCheckpointDir(found)
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, removed when the driver ends."""
    path = f"{scratch_dir(spark)}/triewalk/{name}-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    return path


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if jvm is None or spark.sparkContext._jsc is None:
        return
    try:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the JVM may be gone already when the driver ends
        return


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes df as Parquet to the shared folder and reads it back: cuts the lineage, survives lost executors and gives later joins their sizes."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


#: Rows of an Arrow batch that carries texts or sets of hashes: a batch is held whole on both sides of the pipe to a Python worker.
TEXT_ROWS = 512


@contextmanager
def text_batches(spark: SparkSession) -> Iterator[None]:
    """Jobs run inside move TEXT_ROWS rows a batch at most to and from Python workers; the session's own number holds again after."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    spark.conf.set(key, str(min(int(was), TEXT_ROWS) if int(was) > 0 else TEXT_ROWS))
    try:
        yield
    finally:
        spark.conf.set(key, was)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run, which returns what it has freed to the machine when a task's batches end: Python workers stay for later tasks."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        with suppress(OSError, AttributeError):  # another C library than glibc
            ctypes.CDLL("libc.so.6").malloc_trim(0)

    return wrapped


def materialize_texts(df: DataFrame, name: str) -> DataFrame:
    """materialize for a frame made by Python workers from whole texts or sets of hashes."""
    with text_batches(df.sparkSession):
        return materialize(df, name)


def discard(*tables: DataFrame) -> None:
    """Removes tables that materialize gave, once nothing reads them any more."""
    for df in tables:
        _remove(df.sparkSession, df._scratch_path)


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only. Texts of ASCII alone take the fast path, which gives the same there."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


#: Bits of a bitmap: 2**26 in 2048 rows of 4096 bytes, so a broadcast is 8 MB whatever the input.
BITMAP_BITS = 26


def bitmap_slot(key: Column) -> Column:
    """Position of a hashed key in the bitmap, from 1, which is where Spark's bitmap functions count from."""
    return F.pmod(key, F.lit(1 << BITMAP_BITS)) + 1


def bitmap_of(keys: DataFrame, key: Column, name: str) -> DataFrame:
    """(bucket, bits) of the keys of a frame, written out; its size does not depend on the number of keys."""
    slots = keys.select(bitmap_slot(key).alias("slot"))
    return materialize(slots.groupBy(F.bitmap_bucket_number("slot").alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("_bits")), name)


def marked(df: DataFrame, bitmap: DataFrame, key: Column, out: str) -> DataFrame:
    """df with a flag: false where the key is surely not among the bitmap's; true for all that are, and for a few others by chance."""
    at = F.bitmap_bit_position(bitmap_slot(key))
    byte = F.conv(F.hex(F.substring("_bits", (at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    bit = F.coalesce(F.getbit(byte, F.pmod(at, F.lit(8)).cast("int")) == 1, F.lit(False))
    bitmap = bitmap.select(F.col("_bucket").alias("_bb"), "_bits")
    return df.join(F.broadcast(bitmap), F.bitmap_bucket_number(bitmap_slot(key)) == F.col("_bb"), "left").withColumn(out, bit).drop("_bb", "_bits")


def without_ids(df: DataFrame, gone: DataFrame, id_col: str) -> DataFrame:
    """The rows of df whose id is not in gone (one column). Only rows that the bitmap of gone marks are shuffled for the
    anti join; all others pass as they are, with their texts."""
    gone = gone.select(F.col(gone.columns[0]).alias("_gone_id"))
    flagged = marked(df, bitmap_of(gone, F.xxhash64("_gone_id"), "gone-bitmap"), F.xxhash64(F.col(id_col)), "_maybe")
    rest = flagged.where("not _maybe").select(*df.columns)
    return rest.unionByName(flagged.where("_maybe").select(*df.columns).join(gone, F.col(id_col).eqNullSafe(F.col("_gone_id")), "left_anti"))


def total_partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
