"""What the training-data operators share: scratch tables, the word rule, columns under safe names."""

from __future__ import annotations

import gc
import sys
import types

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import discard, written

#: A word is a longest run of anything but the six ASCII white-space characters.
SPACE_CHARS = " \t\n\x0b\x0c\r"
SPACE_RUN = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"

#: A table written once in the shared scratch folder and read back, and how to delete it.
materialize = written


def words(text: Column) -> Column:
    """Array of the words of a text; empty for null, empty and blank texts."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE_CHARS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_RUN))


def word_count(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def without_gc(run):
    """``run`` over batches without garbage collection: for code that makes millions of small objects and no cycles. A worker that is used again has it back."""

    def wrapped(batches):
        gc.disable()
        try:
            yield from run(batches)
        finally:
            gc.enable()

    return wrapped


def per_worker(key: tuple, make):
    """An object that a Python worker makes once and keeps for its later tasks. Its memory must be bounded."""
    store = sys.modules.setdefault("_topomap_worker", types.ModuleType("_topomap_worker")).__dict__
    if key not in store:
        store[key] = make()
    return store[key]


__all__ = ["SPACE_CHARS", "SPACE_RUN", "WORD", "discard", "load", "materialize", "per_worker", "without_gc", "word_count", "words", "written"]
