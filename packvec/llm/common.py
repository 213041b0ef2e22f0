"""Small things that several operators share: table paths, working folders, text keys."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Code points 0x20 and 0x09-0x0D, as Java's regular expressions write them.
SPACES = r"[\x20\x09-\x0D]+"
#: Rows of a table of numbers that is broadcast at most; a longer one is joined by a shuffle.
BROADCAST_ROWS = 200_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The cluster's shared working folder; a folder under /tmp where none is set and all runs on one machine."""
    context = spark.sparkContext
    configured = context.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    if not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(f"/tmp/checkpoints/{uuid.uuid4().hex}")
    return context.getCheckpointDir()


def bounded(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df (a written table of a few narrow columns), to be broadcast if it has so many rows at most; counted, not guessed."""
    return F.broadcast(df) if df.count() <= rows else df


def written(df: DataFrame, name: str) -> DataFrame:
    """df, written once into the shared folder and read from there: later uses neither recompute nor lose it."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def word_count(text: Column) -> Column:
    """Words [^\\x20\\x09-\\x0D]+ of a text; 0 for null. Counts word starts without building the words."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")
