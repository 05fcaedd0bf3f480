"""Helpers shared by the text operators: reading, workers, Arrow columns."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.plan import checkpointed, importable

__all__ = ["checkpointed"]

#: ASCII white space of the contracts: space, tab, newline, vertical tab, form feed, carriage return.
SPACE = b" \t\n\x0b\x0c\r"
#: The workers' allocators give freed memory back, as a worker is used again for other operators.
ALLOCATORS = {"MALLOC_ARENA_MAX": "2", "MALLOC_TRIM_THRESHOLD_": "4194304", "MALLOC_MMAP_THRESHOLD_": "4194304", "ARROW_DEFAULT_MEMORY_POOL": "system"}
#: Rows of an Arrow batch: rows hold whole texts.
ROWS = "2000"


def prepare(spark: SparkSession) -> SparkSession:
    """Sends this package to the Python workers, and lets them hold little memory. Settings that were given stay."""
    spark.sparkContext.environment.update({k: v for k, v in ALLOCATORS.items() if k not in spark.sparkContext.environment})
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ROWS)
    return importable(spark)


def returning(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """run with the memory of its task given back to the system at its end."""

    def wrapped(batches):
        yield from run(batches)
        released()

    return wrapped


def released() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return prepare(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def with_fields(schema: T.StructType, fields: list[T.StructField]) -> T.StructType:
    """schema with these fields at its end; a field of the same name, in any case, is replaced."""
    taken = {f.name.lower() for f in fields}
    return T.StructType([f for f in schema.fields if f.name.lower() not in taken] + fields)


def text_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text of an Arrow column; null counts as empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def texts(column: pa.Array) -> list[str]:
    return ["" if x is None else x for x in column.to_pylist()]


def chunks(batch: pa.RecordBatch, column: int, most: int = 2 << 20):
    """Slices of a batch with about `most` bytes of text in this column each; a longer text stands alone."""
    sizes = np.fromiter((x or 0 for x in pc.binary_length(batch.column(column)).to_pylist()), np.int64, batch.num_rows)
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)


def id_of(column: str = "doc_id"):
    """A non-null order key for document ids: null counts as below every id."""
    return F.coalesce(F.col(column).cast("long"), F.lit(-(2**63)))


def power_of_two(n: float, least: int, most: int) -> int:
    """The exponent of the first power of two that is not below n, held between two exponents."""
    return int(min(most, max(least, np.ceil(np.log2(max(n, 1))))))


#: Parts into which rows of one key are dealt before they meet the single row of that key on the other side.
SALTS = 16


def salted_join(many: DataFrame, one: DataFrame, key: str, by: str) -> DataFrame:
    """many joined to one on key, where one has a row for each key and a key may have a third of all rows of many.

    Rows of many are dealt by the hash of column `by`; the other side's rows are copied to each deal.
    """
    a = many.withColumn("__salt", F.expr(f"pmod(xxhash64(`{by}`), {SALTS}L)"))
    b = one.withColumn("__salt", F.expr(f"explode(sequence(0L, {SALTS - 1}L))"))
    return a.join(b, [key, "__salt"]).drop("__salt")
