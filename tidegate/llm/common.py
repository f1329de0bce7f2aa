"""What the corpus operators share: stored intermediate tables, byte access to Arrow text, small expressions."""

from __future__ import annotations

import ctypes
import os
import uuid
from contextlib import contextmanager, suppress

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegate.sources.tables import shared_dir

ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: bytes.translate table that lower-cases A-Z and leaves every other byte
LOWER_BYTES = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: a word is a run of characters other than these; they are also the characters bytes.split() parts at
WORD = r"[^\x20\x09-\x0D]+"


def stored(df: DataFrame, name: str, compression: str = "zstd") -> DataFrame:
    """df written once to the shared folder and read again: its lineage ends there, and lost executors lose nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes stored() tables that nothing will read again."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(t.stored_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def ascii_lower(c: Column) -> Column:
    """A-Z lower-cased, nothing else changed."""
    return F.translate(c, ASCII_UPPER, ASCII_UPPER.lower())


def as_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """The UTF-8 bytes of each text, null as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def splitmix(x: np.ndarray, step: int) -> np.ndarray:
    """A second, third, ... well mixed 64-bit hash made from a first one."""
    with np.errstate(over="ignore"):
        z = x + np.uint64((0x9E3779B97F4A7C15 * step) & 0xFFFFFFFFFFFFFFFF)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


def local_tokenizers() -> str:
    """The folder of public tokenizer files; TIDEGATE_TOKENIZERS overrides the installed package's."""
    if named := os.environ.get("TIDEGATE_TOKENIZERS"):
        return named
    import public_tokenizers

    return os.path.dirname(public_tokenizers.__file__)


def arrow_function(kind: str):
    """Decorator: pa.Array -> pa.Array becomes Columns -> Column. The UDF is built when called, as workers that import the
    module have no session to parse its type with."""

    def made(f):
        def call(*columns) -> Column:
            return F.arrow_udf(f, kind)(*columns)

        call.__doc__ = f.__doc__
        return call

    return made


@contextmanager
def arrow_rows(spark: SparkSession, rows: int):
    """What is carried out in here passes at most so many rows at a time to Python; the session's setting is put back."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before) if int(before) > 0 else rows)))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def give_back() -> None:
    """Returns memory that Arrow and the C library hold without using it: workers share their machine with the JVM."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)
