"""Accuracy and work measures."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(hits: DataFrame, truth: DataFrame, k: int, ties: bool = False, literal: bool = False) -> DataFrame:
    """recall: mean over the truth's queries of the share of their k nearest that was found.

    The denominator is k or, if fewer rows pass, their number (literal: always k). ties: a hit counts if it is no
    farther than the truth's last.
    """
    size = truth.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("last"))
    if ties:
        found = hits.join(size, "query_id").where(F.col("dist") <= F.col("last") + 1e-9).groupBy("query_id").agg(F.count(F.lit(1)).alias("found"))
    else:
        found = hits.join(truth.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_semi").groupBy("query_id").agg(F.count(F.lit(1)).alias("found"))
    of = F.lit(k) if literal else F.least(F.lit(k), F.col("n"))
    return size.join(found, "query_id", "left").agg(F.round(F.avg(F.least(F.coalesce("found", F.lit(0)), of) / of), 6).alias("recall"))


def timed(run: Callable[[], DataFrame], runs: int = 3) -> float:
    """Mean seconds of materialised runs."""
    total = 0.0
    for _ in range(runs):
        start = time.time()
        run().write.format("noop").mode("overwrite").save()
        total += time.time() - start
    return total / runs


def selectivity(df: DataFrame, passing) -> DataFrame:
    """Passing rows, all rows and their share."""
    return df.agg(F.count_if(passing).alias("n_pass"), F.count(F.lit(1)).alias("n_rows")).withColumn("share", F.round(F.try_divide("n_pass", "n_rows"), 6))


def visited(reached: DataFrame) -> DataFrame:
    """Partitions a query and queries a partition."""
    each = reached.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return each.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("n"), 6).alias("mean_partitions"), F.max("n").cast("long").alias("most_partitions"))


def rank_correlation(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """query_id, pearson, spearman of two columns over a query's rows."""
    rank = lambda c: F.avg("r").over(Window.partitionBy("query_id", c))
    ranked = pairs
    for c, out in ((a, "_ra"), (b, "_rb")):
        ranked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(c))).withColumn(out, rank(c)).drop("r")
    return ranked.groupBy("query_id").agg(F.round(F.corr(a, b), 6).alias("pearson"), F.round(F.corr("_ra", "_rb"), 6).alias("spearman"))


def lid(knn: DataFrame) -> DataFrame:
    """lid: local intrinsic dimensionality by maximum likelihood over nearest distances, averaged (A10). knn: query_id, dist."""
    far = F.max("dist").over(Window.partitionBy("query_id"))
    each = knn.where("dist > 0").withColumn("far", far).groupBy("query_id").agg(F.avg(F.ln(F.col("dist") / F.col("far"))).alias("m"))
    return each.where("m < 0").agg(F.round(F.avg(-1 / F.col("m")), 4).alias("lid"))


def balance(loads: DataFrame, by: str) -> DataFrame:
    """Groups, mean, greatest and least over mean."""
    n = loads.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.count(F.lit(1)).alias("groups"), F.round(F.avg("n"), 4).alias("mean"), F.round(F.max("n") / F.avg("n"), 6).alias("most_over_mean"), F.round(F.min("n") / F.avg("n"), 6).alias("least_over_mean"))


def tightness(pairs: DataFrame) -> DataFrame:
    """Mean of bound over distance, and bounds above their distance, which must be none (A13). pairs: bound, dist."""
    return pairs.agg(F.round(F.avg(F.try_divide("bound", "dist")), 6).alias("tightness"), F.count_if(F.col("bound") > F.col("dist") + 1e-6).alias("violations"), F.count(F.lit(1)).alias("pairs"))


def lookup_savings(bits: DataFrame, candidates: int) -> DataFrame:
    """Squared differences computed directly and with tables, and their ratio."""
    direct = F.count(F.lit(1)) * candidates
    table = F.sum("cells") - 1
    return bits.agg(direct.cast("long").alias("direct"), table.cast("long").alias("table"), F.round(direct / table, 6).alias("ratio"))


def memory(rows: int, d: int, bits: int, seg_bits: int, graph_degree: int = 16) -> list[tuple[str, float]]:
    """Bytes a vector held for searching, by solution."""
    words = -(-bits // seg_bits) * seg_bits // 8
    return [("packed", words + d / 8), ("packed without low bits", float(words)), ("one word a dimension", d * seg_bits / 8), ("8 bit uniform", float(d)), ("product codes", d / 4), ("graph with full vectors", 4 * d + 4.0 * graph_degree), ("graph with codes", words + 4.0 * graph_degree)]


def io(log: DataFrame, full_bytes: int) -> DataFrame:
    """run_id, gets of index files, workers that held theirs and fetched none, full vectors read and their bytes (A09). log: see cost."""
    each = log.groupBy("run_id").agg(F.sum("gets").alias("gets"), F.count_if(F.col("gets") == 0).alias("loads_avoided"), F.sum("full_reads").alias("full_reads"))
    return each.withColumn("full_bytes", F.col("full_reads") * full_bytes)


def cache_ratio_to_beat(seconds_by_ratio: dict[int, float], queries: int, qps: float) -> int | None:
    """Least duplication at which a cached search answers more queries a second than qps."""
    return min((r for r, s in seconds_by_ratio.items() if queries / s > qps), default=None)


def spearman(a: np.ndarray, b: np.ndarray) -> float:
    return float(np.corrcoef(np.argsort(np.argsort(a)), np.argsort(np.argsort(b)))[0, 1])
