"""Which partitions a query visits."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packvec.functions.vectors import l2


def rank(queries: DataFrame, centroids: DataFrame) -> DataFrame:
    """query_id, part_id, dist, rank, ratio: centroids by distance from each query, and their ratio to the nearest.

    centroids is an index table of one row a partition; it is broadcast, and its size is checked where it is written.
    """
    pairs = queries.crossJoin(F.broadcast(centroids.select("part_id", "centroid"))).select("query_id", "part_id", F.round(l2(F.col("qvec"), F.col("centroid")), 9).alias("dist"))
    w = Window.partitionBy("query_id").orderBy("dist", "part_id")
    nearest = F.min("dist").over(Window.partitionBy("query_id"))
    ratio = F.when(nearest > 0, F.round(F.col("dist") / nearest, 9)).when(F.col("dist") == 0, 1.0).otherwise(F.lit(float("inf")))
    return pairs.withColumns({"rank": F.row_number().over(w), "ratio": ratio})


def reach(ranked: DataFrame, counts: DataFrame, threshold: float, k: int, policy: str = "both", nprobe: int = 1) -> DataFrame:
    """query_id, part_id, rank, ratio, n_pass, cum_before of the partitions to visit, in one pass.

    Going outward, a query stops where the ratio exceeds the threshold and the partitions before already hold k passing
    rows; as the ratio rises and the sum too, that is a condition on each row. Partitions without passing rows are left
    out. policy: both; threshold or k alone; nprobe nearest; all. counts: [query_id,] part_id, n_pass.
    """
    on = [c for c in ("query_id", "part_id") if c in counts.columns]
    joined = ranked.join(counts, on, "left").withColumn("n_pass", F.coalesce("n_pass", F.lit(0)))
    before = Window.partitionBy("query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    out = joined.withColumn("cum_before", F.coalesce(F.sum("n_pass").over(before), F.lit(0)))
    near, short = F.col("ratio") <= threshold, F.col("cum_before") < k
    go = {"both": near | short, "threshold": near, "k": short, "nprobe": F.col("rank") <= nprobe, "all": F.lit(True)}[policy]
    return out.where(go & (F.col("n_pass") > 0)).select("query_id", "part_id", "rank", "ratio", "n_pass", "cum_before")


def balance(ranked: DataFrame, reached: DataFrame, target: int) -> DataFrame:
    """Pairs to add so that partitions with fewer than target queries get those which most narrowly missed them.

    A query offers itself to the first partition that it was pruned from.
    """
    missed = ranked.join(reached.select("query_id", "part_id"), ["query_id", "part_id"], "left_anti")
    first = missed.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("rank"))).where("r = 1")
    load = reached.groupBy("part_id").agg(F.count(F.lit(1)).alias("load"))
    order = Window.partitionBy("part_id").orderBy("ratio", "query_id")
    offered = first.join(load, "part_id", "left").withColumns({"load": F.coalesce("load", F.lit(0)), "place": F.row_number().over(order)})
    return offered.where(F.col("load") + F.col("place") <= target).select("query_id", "part_id", "rank", "ratio")


def home_ratios(vectors: DataFrame, centroids: DataFrame) -> DataFrame:
    """vec_id, part_id (the home), other, ratio of the distance to each centroid to that of the home centroid."""
    each = vectors.crossJoin(F.broadcast(centroids.select(F.col("part_id").alias("other"), "centroid"))).select("vec_id", "part_id", "other", l2(F.col("embedding"), F.col("centroid")).alias("dist"))
    home = F.max(F.when(F.col("other") == F.col("part_id"), F.col("dist"))).over(Window.partitionBy("vec_id"))
    return each.withColumn("home", home).where(F.col("home") > 0).select("vec_id", "part_id", "other", (F.col("dist") / F.col("home")).alias("ratio"))


def centroid_factor(vectors: DataFrame, centroids: DataFrame, d: int, beta: float = 0.001) -> DataFrame:
    """threshold, mean_of_means, mean_of_stddevs, share_below_one: the factor of the nearest centroid's distance up to which partitions are visited.

    vectors: vec_id, part_id, embedding; a sample will do at scale.
    """
    rows = home_ratios(vectors, centroids).groupBy("vec_id").agg(F.avg("ratio").alias("m"), F.stddev_pop("ratio").alias("s"), F.avg((F.col("ratio") < 1).cast("double")).alias("b"))
    total = rows.agg(F.avg("m").alias("m"), F.avg("s").alias("s"), F.avg("b").alias("b"))
    return total.select(F.round(1 + F.col("s") / F.col("m") + beta * d**0.5, 6).alias("threshold"), F.round("m", 6).alias("mean_of_means"), F.round("s", 6).alias("mean_of_stddevs"), F.round("b", 6).alias("share_below_one"))
