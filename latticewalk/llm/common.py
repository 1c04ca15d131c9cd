"""Helpers that the corpus operators share."""

from __future__ import annotations

import ctypes
import functools
import gc
import sys
import tempfile
from collections.abc import Callable, Iterator
from types import ModuleType

import pyarrow as pa

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words of a text, wherever a contract counts or shingles words.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder of the session. Where none is set, a local one in local mode (tests), and an error on a cluster."""
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="checkpoints-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(found)
    return found


def cut(df: DataFrame) -> DataFrame:
    """Compute now and cut the lineage, in the shared checkpoint folder."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def n_groups(rows: int, each: int) -> int:
    """How many groups of about `each` rows hold `rows` rows."""
    return max(1, -(-rows // each))


def held_out(column: str = "doc_id"):
    """Rows of the test fold: crc32 of the id as text is divisible by five."""
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def once(key: tuple, make: Callable):
    """A thing that a Python worker makes once and keeps for all its tasks, such as a vocabulary with its memo."""
    kept = sys.modules.setdefault("_corpus_worker", ModuleType("_corpus_worker")).__dict__
    if key not in kept:
        kept[key] = make()
    return kept[key]


def give_back() -> None:
    """Hand memory that this Python worker no longer uses back to the system: idle workers stay beside busy ones."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:  # glibc alone has it
        trim(0)


def trimmed(f: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The same function over batches, giving memory back at the end of a task."""

    @functools.wraps(f)
    def run(batches: Iterator) -> Iterator:
        try:
            yield from f(batches)
        finally:
            give_back()

    return run
