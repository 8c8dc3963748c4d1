"""What the operators share: tables, cuts in the lineage, keys and word splitting."""

from __future__ import annotations

import re
import tempfile
import uuid
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Characters between words, as a Java regular expression class.
SPACE = r"[\x20\x09-\x0D]"
_WORDS = re.compile(rb"[^\x20\x09-\x0D]+")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; Spark opens it, so any store that Spark reads will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: what the session names, or (one machine only) a temporary one."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
    return sc._jsc.sc().getCheckpointDir().get()


#: What removes the shuffle files of a query when it ends; a table that is written needs them no more.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, by: str | None = None) -> DataFrame:
    """df written as Parquet to the shared folder (a folder for each value of by) and read again: a cut in the lineage that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tables/{uuid.uuid4().hex}"
    was = spark.conf.get(_CLEAN, None)
    spark.conf.set(_CLEAN, "true")
    try:
        df.write.parquet(path, partitionBy=by)
    finally:
        spark.conf.unset(_CLEAN) if was is None else spark.conf.set(_CLEAN, was)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def discard(*tables: DataFrame, folder: str = "") -> None:
    """Removes tables that materialise() wrote (or one folder of each) and that no later plan reads."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{t.written_at}/{folder}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def crc(value: Column) -> Column:
    """crc32 of a number written as text."""
    return F.crc32(value.cast("string").cast("binary"))


def crc_of(value) -> int:
    return zlib.crc32(str(value).encode())


def lower_words(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lower-cased, as UTF-8 (bytes.lower and bytes.split know ASCII alone)."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def let(value: Column, body) -> Column:
    """body(value) with value computed once: a lambda variable is bound to it, so no rewrite copies the expression."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def slices(stream, rows: int = 512):
    """Arrow batches in slices of at most `rows`, so that the Python objects made of one stay few; what earlier tasks freed goes back to the system first."""
    release()
    try:
        for batch in stream:
            for at in range(0, batch.num_rows, rows):
                yield batch.slice(at, rows)
    finally:
        release()


def freeing(f):
    """f, a function of Arrow tables, that gives freed memory back when it is done with a group."""

    def run(t):
        try:
            return f(t)
        finally:
            release(collect=False)

    def run_two(a, b):
        try:
            return f(a, b)
        finally:
            release(collect=False)

    return run if f.__code__.co_argcount == 1 else run_two


def release(collect: bool = True) -> None:
    """Freed memory back to the system. A worker process serves many stages, and what it keeps is lost to the next one."""
    import ctypes
    import gc

    import pyarrow as pa

    if collect:
        gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # only glibc has it
        pass


def batches(rows: list[tuple], schema):
    """Rows as one Arrow batch."""
    import pyarrow as pa

    cols = list(zip(*rows, strict=True)) if rows else [[] for _ in schema]
    return pa.RecordBatch.from_arrays([pa.array(list(c), type=f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)
