"""Helpers that several operators share: reading tables, cutting lineage, words, uniforms."""

from __future__ import annotations

import ctypes
import itertools
import re
import tempfile
from collections.abc import Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values of the contracts: what parts words, and a word.
SPACE_CHARS = " \t\n\x0b\x0c\r"
WORD_RE = r"[^\x20\x09-\x0D]+"
MASK64 = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table of the given folder, with only the named columns if there are any."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def checkpoint_ready(spark: SparkSession) -> None:
    """Use the shared folder that the session names in spark.checkpoint.dir. Only a local master, whose executors are the driver, may do without one."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="tierdraw-ckpt-"))


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared checkpoint folder: they survive the loss of any executor."""
    checkpoint_ready(df.sparkSession)
    return df.checkpoint(eager=True)


def n_words(text: Column) -> Column:
    """Number of words ``[^\\x20\\x09-\\x0D]+`` of a text; null counts as empty."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD_RE)).cast("bigint")


def mix64(x: int) -> int:
    """A 64-bit finaliser (multiply and xor-shift) for plain integers."""
    x = ((x ^ (x >> 33)) * 0xFF51AFD7ED558CCD) & MASK64
    x = ((x ^ (x >> 33)) * 0xC4CEB9FE1A85EC53) & MASK64
    return x ^ (x >> 33)


def unit(x: int) -> float:
    """A number in [0, 1) from a 64-bit hash."""
    return (mix64(x & MASK64) >> 11) / float(1 << 53)


def free_memory() -> None:
    """Give what a Python worker has freed back to the system: workers stay between the stages of a job."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not the GNU library
        return


def unused_name(names: Sequence[str], stem: str) -> str:
    """A column name that is not among ``names``, by Spark's rules (case does not count)."""
    taken = {n.lower() for n in names}
    return next(n for n in itertools.chain([stem], (f"{stem}_{k}" for k in itertools.count())) if n.lower() not in taken)


def other_columns(names: Sequence[str], without: Sequence[str]) -> Column:
    """All other columns of a row as one text: an order among rows that agree in the named ones."""
    rest = [F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(names) if c not in without]
    return F.to_json(F.struct(*rest)) if rest else F.lit("")
