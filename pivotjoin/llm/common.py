"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..operators.tables import discard, materialize, remove, shared_dir

__all__ = ["BROADCAST_ROWS", "WORD", "discard", "field", "gapless_rank", "hash32", "materialize", "remove", "shared_dir", "small", "table", "tidy", "word_count"]

Batches = Iterator[pa.RecordBatch]

#: ASCII white space; everything else belongs to a word.
WORD = r"[^\x20\x09-\x0D]+"
#: A table is broadcast only when it was counted and has at most so many rows.
BROADCAST_ROWS = 200_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if a count proves it has at most ``limit`` rows, else as it is."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


def word_count(text: Column) -> Column:
    """Number of words of a text; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def hash32(seed: int, *cols: Column) -> Column:
    """A 32-bit hash that every SQL engine with md5 can repeat."""
    parts = [F.coalesce(c.cast("string"), F.lit("")) for c in cols]
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *parts)), 1, 8), 16, 10).cast("long")


def gapless_rank(df: DataFrame, key: str, order: list[Column], out: str, low_bits: int = 10) -> DataFrame:
    """Adds ``out``: the row's place, from 0, in the order (key, *order).

    ``key`` is a non-negative integer with many values, none of them frequent, so each window
    is small. The places before a key come from its count in two steps (the keys of one upper
    half, then the upper halves), so that no task sees more than 2**low_bits of either.
    """
    counts = df.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).withColumn("_hi", F.shiftright(F.col(key), low_bits))
    before = lambda w: F.coalesce(F.sum("_n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    upper = counts.groupBy("_hi").agg(F.sum("_n").alias("_n"))
    upper = upper.select("_hi", before(Window.orderBy("_hi")).alias("_before_hi"))
    lower = counts.select(key, "_hi", before(Window.partitionBy("_hi").orderBy(key)).alias("_before_lo"))
    offsets = lower.join(F.broadcast(upper), "_hi").select(key, (F.col("_before_hi") + F.col("_before_lo")).alias("_before"))
    ranked = df.withColumn("_rn", F.row_number().over(Window.partitionBy(key).orderBy(*order)))
    return ranked.join(offsets, key).withColumn(out, F.col("_before") + F.col("_rn") - 1).drop("_before", "_rn")


def field(name: str, kind: str, nullable: bool = True) -> T.StructField:
    return T.StructField(name, T._parse_datatype_string(kind), nullable)


def tidy(run: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """The same function of batches, which gives freed memory back to the system when its task ends: workers outlive tasks."""

    @functools.wraps(run)
    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # GNU's C library has it
            if trim:
                trim(0)

    return tidied
