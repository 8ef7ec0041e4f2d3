"""Shared pieces of the text operators.

Rules that hold for every operator here: a null text is an empty text, a null
``doc_id`` is carried through, repeated rows are kept as rows, whole texts are
read, and a column of the input whose name an operator uses for its own result
is replaced by that result.
"""

from __future__ import annotations

import ctypes
import gc
import hashlib
import os
import re
import sys
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same words over UTF-8 bytes that are lower-cased already.
WORD_BYTES = re.compile(rb"[0-9a-z\x80-\xff]+")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def text_of(col: str | Column = "text") -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def ascii_lower(col: Column) -> Column:
    return F.translate(col, UPPER, UPPER.lower())


def word_list(col: Column) -> Column:
    """Lower-cased words of a text, on the JVM."""
    return F.regexp_extract_all(ascii_lower(col), F.lit(f"({WORD})"), F.lit(1))


def words_of(raw: bytes) -> list[bytes]:
    """Lower-cased words of a text's UTF-8 bytes (``bytes.lower`` is ASCII only)."""
    return WORD_BYTES.findall(raw.lower())


def raw_texts(batch: pa.RecordBatch, name: str = "text") -> list[bytes]:
    """UTF-8 bytes of a string column, null as empty."""
    column = batch.column(batch.schema.get_field_index(name))
    return [x if x is not None else b"" for x in column.cast(pa.binary()).to_pylist()]


_MEMORY: list = [None, None]


def fresh_worker() -> None:
    """What a Python stage without a memory of its own calls first: whatever an earlier stage left in a reused worker goes back to the system."""
    _MEMORY[:] = [None, None]
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library: nothing to trim
        pass


def worker_memory(owner, make):
    """What ``make`` gives, kept by this Python worker between tasks until another owner asks: one operator's memory at a time."""
    if _MEMORY[0] != owner:
        fresh_worker()
        _MEMORY[:] = [owner, make()]
    return _MEMORY[1]


def weight(*values: str) -> int:
    """Bytes that strings take as entries of a dictionary."""
    return 104 + sum(map(sys.getsizeof, values))


def small(batches, rows: int = 256):
    """The batches in shorter pieces, so that a worker holds few rows as Python objects at once."""
    for batch in batches:
        for i in range(0, batch.num_rows, rows):
            yield batch.slice(i, rows)


def sha256_hex(raw: bytes) -> str:
    return hashlib.sha256(raw).hexdigest()


def slices(sizes: list[int], most: int):
    """Ranges (start, end) of consecutive rows of at most ``most`` bytes, one row at least."""
    start = total = 0
    for i, n in enumerate(sizes):
        if i > start and total + n > most:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield start, len(sizes)


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of the session; a temporary one only where none is set and all runs on one machine (tests)."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        where = os.path.join(tempfile.gettempdir(), "sparsehop-checkpoints")
    return where.rstrip("/")


def _release(spark: SparkSession) -> None:
    """Let Spark's cleaner remove the shuffle files of frames that nobody holds any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def persist_shared(df: DataFrame) -> DataFrame:
    """Write a frame to the shared folder and read it back: lineage ends in files that outlive executors.

    The shuffle files behind the frame are of no more use; collecting the driver's
    garbage lets Spark's cleaner remove them from the executors' disks. Events that
    still wait to be told hold the plan that has just ended, so the next call
    collects again before it writes.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stage-{uuid.uuid4().hex}"
    _release(spark)
    df.write.parquet(path)
    _release(spark)
    return spark.read.schema(df.schema).parquet(path)


def forget_shared(df: DataFrame) -> None:
    """Remove the files behind ``persist_shared`` once nothing reads them any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(conf).delete(path, True)


def salted(rows: DataFrame, keys: list[str], hot: DataFrame, by: Column, salts: int = 64) -> DataFrame:
    """``rows`` with ``salt``: spread by ``by`` where the keys are hot, 0 elsewhere. ``hot`` is what ``hot_keys`` gives, so small enough to send along."""
    flagged = rows.join(F.broadcast(hot.withColumn("_hot", F.lit(True))), keys, "left")
    return flagged.withColumn("salt", F.when(F.col("_hot"), F.pmod(F.xxhash64(by), F.lit(salts)).cast("int")).otherwise(0)).drop("_hot")


def repeated_for_salts(rows: DataFrame, keys: list[str], hot: DataFrame, salts: int = 64) -> DataFrame:
    """The other side of a salted join: rows of hot keys once for every salt."""
    flagged = rows.join(F.broadcast(hot.withColumn("_hot", F.lit(True))), keys, "left")
    return flagged.withColumn("salt", F.explode(F.when(F.col("_hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("_hot")


def hot_keys(counted: DataFrame, keys: list[str], n: str, share: int = 2000) -> DataFrame:
    """Keys that stand for more than one row in ``share``: fewer than ``share`` of them, whatever the size of the table."""
    total = counted.agg(F.coalesce(F.sum(n), F.lit(0))).first()[0]
    return counted.filter(F.col(n) * share > F.lit(int(total))).select(*keys)
