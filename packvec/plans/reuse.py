"""What is kept between searches: loaded indexes (M64) and results."""

from __future__ import annotations

from collections.abc import Callable

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packvec.plans import index as ix
from packvec.plans import search as se
from packvec.plans.shared import stored


class Retainer:
    """Indexes by path and fingerprint: loaded once, kept on the executors, loaded anew when the fingerprint differs.

    on=False loads every time. loads and reuses count what happened; answers are the same either way.
    """

    def __init__(self, spark: SparkSession, on: bool = True):
        self.spark, self.on, self.kept, self.loads, self.reuses = spark, on, {}, 0, 0

    def get(self, path: str) -> ix.Index:
        stamp = self.spark.read.schema("facts string").json(f"{path}/facts").first()["facts"]
        have = self.kept.get(path)
        if self.on and have and have[0] == stamp:
            self.reuses += 1
            return have[1]
        if have:
            have[1].rows.unpersist()
        found = ix.load(self.spark, path)
        self.loads += 1
        if self.on:
            found.rows.persist(StorageLevel.MEMORY_AND_DISK)
            self.kept[path] = (stamp, found)
        return found

    def release(self) -> None:
        for _, found in self.kept.values():
            found.rows.unpersist()
        self.kept.clear()

    def report(self) -> DataFrame:
        return self.spark.createDataFrame([(self.loads, self.reuses)], "loads int, reuses int")


class ResultCache:
    """Results by vector, predicate and k in a folder; off unless a search is given one. Entries end after ttl seconds."""

    def __init__(self, spark: SparkSession, path: str, ttl: int | None = None):
        self.spark, self.path, self.ttl, self.hits, self.misses = spark, path, ttl, 0, 0

    def entries(self) -> DataFrame:
        try:
            found = self.spark.read.parquet(self.path)
        except Exception as error:  # nothing has been written yet
            if "PATH_NOT_FOUND" not in str(error):
                raise
            return self.spark.createDataFrame([], "key string, rank int, vec_id long, dist double, at timestamp")
        return found.where(F.col("at") > F.current_timestamp() - F.make_interval(secs=F.lit(self.ttl))) if self.ttl else found

    def search(self, queries: DataFrame, k: int, run: Callable[[DataFrame], DataFrame]) -> DataFrame:
        """run(queries that are not kept) and the kept answers of the others, as one; equal requests are run once."""
        keyed = se.with_predicates(queries).withColumn("k", F.lit(k)).withColumn("key", F.sha2(F.to_json(F.struct("qvec", "pred", "k")), 256))
        have = self.entries()
        new = keyed.join(have.select("key").distinct(), "key", "left_anti")
        once = stored(new.groupBy("key").agg(F.min("query_id").alias("query_id"), F.first("qvec").alias("qvec"), F.first("pred").alias("pred")), "requests")
        total, fresh = keyed.count(), once.count()
        self.hits, self.misses = self.hits + total - fresh, self.misses + fresh
        if fresh:
            found = run(once.select("query_id", "qvec", "pred")).join(once.select("query_id", "key"), "query_id")
            found.select("key", F.col("rank").cast("int").alias("rank"), "vec_id", "dist", F.current_timestamp().alias("at")).write.mode("append").parquet(self.path)
        return keyed.select("query_id", "key").join(self.entries(), "key").select("query_id", "rank", "vec_id", "dist")
