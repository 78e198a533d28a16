"""Reading tables and edge lists."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def shared_folder(spark: SparkSession, stem: str) -> str:
    """A new folder that driver and executors share, under spark.checkpoint.dir; where that is unset, a temporary one if all is on one machine (a local master), else an error."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="pathsieve-")
    return f"{base.rstrip('/')}/{stem}-{uuid.uuid4().hex}"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: Column | str) -> Column:
    """A time as microseconds since 1970: comparable, subtractable, and free of the session's time zone."""
    column = F.col(ts) if isinstance(ts, str) else ts
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), column.cast("timestamp_ntz"))


def read_edges(spark: SparkSession, path: str, fmt: str, schema: str | StructType, **options: str) -> DataFrame:
    """An edge list in any format that Spark reads (csv, json, orc, parquet), with its schema given rather than inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def stream_edges(spark: SparkSession, path: str, schema: str | StructType, time: str, delay: str, fmt: str = "parquet", files_a_batch: int | None = None) -> DataFrame:
    """An edge stream over a folder of files, with a watermark on its event time."""
    reader = spark.readStream.format(fmt).schema(schema)
    if files_a_batch:
        reader = reader.option("maxFilesPerTrigger", files_a_batch)
    return reader.load(path).withWatermark(time, delay)


def write_paths(df: DataFrame, path: str, mode: str = "overwrite") -> None:
    df.write.mode(mode).parquet(path)
