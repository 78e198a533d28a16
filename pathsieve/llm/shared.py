"""Helpers that several operators of this subpackage use."""

from __future__ import annotations

import ctypes
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one where that is unset and all is on one machine (a local master); else an error."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext.getCheckpointDir()
        if not held and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = held.rsplit("/", 1)[0] if held else tempfile.mkdtemp(prefix="pathsieve-")
    return found.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Writes df to the shared checkpoint folder and reads it from there: lineage ends here, and the rows outlive lost executors."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        context.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint(eager=True)


def fresh_path(spark: SparkSession, stem: str) -> str:
    return f"{shared_dir(spark)}/{stem}-{uuid.uuid4().hex}"


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z, nothing else."""
    return F.translate(text, UPPER, LOWER)


def sha256_hex(text: Column) -> Column:
    return F.sha2(text.cast("binary"), 256)


def own_columns(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns: whatever else a table brings can't clash with an operator's own columns."""
    return df.select(*[F.col(f"`{n}`") for n in names])


def masked(docs: DataFrame, *named: str) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """docs under names that no operator uses, but for the columns `named`; and the way back to docs' own names and order."""
    names = [c if c in named else f"given_column_{k}" for k, c in enumerate(docs.columns)]
    return docs.toDF(*names), lambda df: df.select(*[F.col(f"`{m}`").alias(c) for m, c in zip(names, docs.columns, strict=True)])


@cache
def _lean() -> Callable[[], object]:
    """Has Arrow take memory from the C library, and gives the call by which that returns what is free: idle workers should hold little."""
    pa.set_memory_pool(pa.system_memory_pool())
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    return (lambda: trim(0)) if trim else (lambda: None)


def forget_tokenizers() -> None:
    """For work without tokens: a worker that encoded texts before gives its tokenizers and their caches back."""
    tokens = sys.modules.get("pathsieve.llm.tokens")
    if tokens:
        tokens.encoder.cache_clear()
        _lean()()


def trim() -> None:
    _lean()()


def text_slices(batch: pa.RecordBatch, column: str, most: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about `most` bytes of text, one row at least: what Python holds at a time doesn't depend on the batch."""
    _lean()
    sizes = np.nan_to_num(pc.binary_length(batch.column(column)).to_numpy(zero_copy_only=False).astype(float))
    group = (np.cumsum(sizes) - sizes) // most
    edges = [*np.flatnonzero(np.diff(group, prepend=-1)), batch.num_rows]
    for a, b in zip(edges, edges[1:], strict=False):
        yield batch.slice(a, b - a)
    trim()
