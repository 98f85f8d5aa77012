"""Helpers shared by the text operators."""

from __future__ import annotations

import ctypes
import gc
from functools import wraps

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from cadenza.storage import keep

#: A word of the operators on words, after A-Z are lower-cased: a run of digits, a-z and code points from U+0080.
WORD_PATTERN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"
_TO_LOWER = str.maketrans(UPPER, LOWER)


def lower_ascii(text: str) -> str:
    """A-Z to a-z and nothing else."""
    return text.lower() if text.isascii() else text.translate(_TO_LOWER)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def numbered(df: DataFrame, *cols: str) -> tuple[DataFrame, list[str]]:
    """df with its columns named c0, c1, ..., so no name of its own clashes with those used beside them; and the new names of some of them."""
    names = df.columns
    return df.toDF(*(f"c{i}" for i in range(len(names)))), [f"c{names.index(c)}" for c in cols]


#: Bytes of an Arrow batch that goes to a Python worker, about.
BATCH_BYTES = 4 << 20
_BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def in_small_batches(df: DataFrame) -> DataFrame:
    """df, whose session from now on bounds Arrow batches by BATCH_BYTES, so 10,000 long texts don't become one batch. A lower bound that is set stays."""
    spark = df.sparkSession
    known = spark.conf.get(_BATCH_SETTING, None)
    if known is None or not known.isdigit() or int(known) > BATCH_BYTES or int(known) <= 0:
        spark.conf.set(_BATCH_SETTING, str(BATCH_BYTES))
    return df


def tidy(run):
    """run, a function over batches, that gives memory it has no more use for back to the system when its task ends: workers are used again, by other operators too."""

    @wraps(run)
    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # no such function in this system's library
                pass

    return tidied


def cut(df: DataFrame) -> DataFrame:
    """df, computed once and kept in the shared checkpoint folder, so lost executors don't lose it."""
    return keep(df)
