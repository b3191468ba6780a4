"""What all operators share: table access, scratch space that every executor sees, cutting of lineage."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.session import cut, scratch_path, scratch_root

__all__ = ["ascii_lower", "cut", "give_back", "lean", "scratch_path", "scratch_root", "table", "text_bytes", "text_or_empty"]

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only. Rows that are pure ASCII take the fast path, with the same result."""
    plain = F.octet_length(text) == F.char_length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def text_bytes(docs: DataFrame, text: str = "text") -> tuple[int, int]:
    """Rows and UTF-8 bytes of a text column: one narrow scan, one row to the driver."""
    row = docs.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length(text_or_empty(text)).cast("long")).alias("b")).first()
    return int(row["n"]), int(row["b"] or 0)


def give_back() -> None:
    """Freed memory that Arrow and the C library keep for later goes back to the system."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not the GNU C library
        pass


def lean(task: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The task of a mapInArrow, which gives its freed memory back at its end: workers live on between tasks, and what they keep counts for their executor."""

    def run(batches: Iterator) -> Iterator:
        try:
            yield from task(batches)
        finally:
            give_back()

    return run
