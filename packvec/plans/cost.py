"""The cost model of a run (M67), daily cost and break-even."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Prices:
    """Of an invocation, a MB-second, an object-store request, a byte read from the shared file system. The text prints none."""

    invocation: float = 2e-7
    mb_second: float = 1.6e-8
    get: float = 4e-7
    byte_read: float = 3e-11


RUNLOG = "run_id long, role string, worker_id long, mem_mb double, seconds double, gets long, full_reads long"


def total(runlog: DataFrame, prices: Prices, vector_bytes: int) -> DataFrame:
    """run_id, invocations, run, object_store, file_read, total: query costs only, storage rent left out.

    The coordinator is started by the user, so its start is counted once as well.
    """
    sums = runlog.groupBy("run_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("mem_mb") * F.col("seconds")).alias("mbs"), F.sum("gets").alias("g"), F.sum("full_reads").alias("r"))
    parts = {"invocations": F.col("n") * prices.invocation, "run": F.col("mbs") * prices.mb_second, "object_store": F.col("g") * prices.get, "file_read": F.col("r") * vector_bytes * prices.byte_read}
    out = sums.select("run_id", *[F.round(v, 12).alias(k) for k, v in parts.items()])
    return out.withColumn("total", F.round(F.col("invocations") + F.col("run") + F.col("object_store") + F.col("file_read"), 12))


def memory_ok(runlog: DataFrame, least: float = 128, most: float = 10_240) -> DataFrame:
    """Workers whose memory the platform does not offer."""
    return runlog.where(~F.col("mem_mb").between(least, most))


def daily(volumes: DataFrame, per_query: dict[str, float], hourly: dict[str, float], instances: int = 2) -> DataFrame:
    """volumes with solution and cost of a day: by query for some, by the hour for servers, of which two stand ready."""
    rows = [F.struct(F.lit(k).alias("solution"), F.round(F.col("volume") * F.lit(c), 6).alias("cost")) for k, c in per_query.items()]
    rows += [F.struct(F.lit(k).alias("solution"), F.lit(round(24.0 * c * instances, 6)).alias("cost")) for k, c in hourly.items()]
    return volumes.select("*", F.inline(F.array(*rows)))


def break_even(spark: SparkSession, per_query: float, hourly: dict[str, float], instances: int = 2) -> DataFrame:
    """server, volume: queries a day from which that server costs less than paying by query."""
    return spark.createDataFrame([(k, float(c)) for k, c in hourly.items()], "server string, hourly double").select("server", F.ceil(F.col("hourly") * 24 * instances / per_query).alias("volume"))
