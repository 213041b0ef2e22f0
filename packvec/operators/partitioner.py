"""Coarse partitions (M13, M14) and residency."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten(), float).reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def lists(matrix: np.ndarray) -> pa.Array:
    n, d = matrix.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(matrix).ravel()))


def starting_centroids(df: DataFrame, p: int, seed: int = 7) -> np.ndarray:
    """p rows of distinct vectors by the order of a hash of their ids, one from each p-th of a bounded sample's spread."""
    sample = df.orderBy(F.xxhash64("vec_id", F.lit(seed))).limit(max(64 * p, 1000)).select("embedding").toArrow()
    x = np.unique(_matrix(sample.column(0).combine_chunks()), axis=0)
    rng = np.random.Generator(np.random.PCG64(seed))
    picked = [x[rng.integers(len(x))]]
    while len(picked) < min(p, len(x)):  # each next one in proportion to its squared distance from those picked
        d2 = np.min([((x - c) ** 2).sum(1) for c in picked], axis=0)
        picked.append(x[rng.choice(len(x), p=d2 / d2.sum())])
    return np.array(picked)


def _nearest(df: DataFrame, centroids: np.ndarray, m: int) -> DataFrame:
    """vec_id, choice (rank), part_id, dist: the m nearest centroids of each row. The centroids are an index artefact of p * d numbers."""
    c, m = centroids, min(m, len(centroids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column(1))
            if not len(x):
                continue
            d = np.sqrt(np.maximum((x**2).sum(1)[:, None] - 2 * x @ c.T + (c**2).sum(1)[None, :], 0))
            order = np.argsort(d, axis=1, kind="stable")[:, :m]
            ids = np.repeat(np.asarray(batch.column(0)), m)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.tile(np.arange(m, dtype=np.int32), len(x))), pa.array(order.ravel().astype(np.int32)), pa.array(np.take_along_axis(d, order, 1).ravel())], names=["vec_id", "choice", "part_id", "dist"])

    return df.select("vec_id", "embedding").mapInArrow(run, "vec_id long, choice int, part_id int, dist double")


def _means(df: DataFrame, homes: DataFrame, centroids: np.ndarray) -> np.ndarray:
    """New centroids: sums by task first, then by partition."""
    p, d = centroids.shape

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n = np.zeros((p, d)), np.zeros(p, np.int64)
        for batch in batches:
            home = np.asarray(batch.column(1))
            np.add.at(sums, home, _matrix(batch.column(0)))
            n += np.bincount(home, minlength=p)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(p, dtype=np.int32)), pa.array(n), lists(sums)], names=["part_id", "n", "s"])

    parts = df.join(homes, "vec_id").select("embedding", "part_id").mapInArrow(run, "part_id int, n long, s array<double>")
    got = parts.select("part_id", "n", F.posexplode("s").alias("dim", "x")).groupBy("part_id", "dim").agg(F.sum("n").alias("n"), F.sum("x").alias("x")).toArrow()
    out = centroids.copy()
    part, dim, n, x = (got.column(c).to_numpy() for c in ("part_id", "dim", "n", "x"))
    some = n > 0
    out[part[some], dim[some]] = x[some] / n[some]
    return out


def capacity_rounds(choices: DataFrame, n: int, p: int, slack: float) -> DataFrame:
    """vec_id, part_id with at most ceil((1 + slack) * n / p) rows a partition.

    Each round the rows without a home ask for their next choice; a partition takes those that would lose most by
    going elsewhere. All choices must be in `choices` for every row to find a place.
    """
    cap = int(np.ceil((1 + slack) * n / p))
    regret = F.coalesce(F.lead("dist").over(Window.partitionBy("vec_id").orderBy("choice")) - F.col("dist"), F.lit(float("inf")))
    asked = choices.withColumn("regret", regret)
    placed, waiting = None, asked
    for turn in range(p):
        now = waiting.where(F.col("choice") == turn)
        used = placed.groupBy("part_id").agg(F.count(F.lit(1)).alias("used")) if placed is not None else None
        now = now.join(used, "part_id", "left").withColumn("used", F.coalesce("used", F.lit(0))) if used is not None else now.withColumn("used", F.lit(0))
        order = F.row_number().over(Window.partitionBy("part_id").orderBy(F.desc("regret"), "vec_id"))
        taken = now.withColumn("r", order).where(F.col("r") + F.col("used") <= cap).select("vec_id", "part_id").checkpoint()
        placed = taken if placed is None else placed.unionByName(taken)
        waiting = waiting.join(taken.select("vec_id"), "vec_id", "left_anti").checkpoint()
        if waiting.isEmpty():
            break
    return placed


def kmeans(df: DataFrame, p: int, rounds: int = 5, balanced: bool = False, slack: float = 0.05, train: int = 1_000_000) -> tuple[DataFrame, np.ndarray]:
    """(vec_id, part_id) of all rows, and the centroids. Training takes at most `train` rows, by a hash of their ids.

    balanced: capacities are met by capacity_rounds in the final assignment (M13); else the nearest centroid is home (M14).
    """
    from packvec.plans.shared import ensure_checkpoint_dir

    ensure_checkpoint_dir(df.sparkSession)
    n = df.count()
    some = df if n <= train else df.where(F.pmod(F.xxhash64("vec_id"), F.lit(1_000_000)) < int(1_000_000 * train / n))
    some = some.select("vec_id", "embedding")
    centroids = starting_centroids(some, p)
    p = len(centroids)
    for _ in range(rounds):
        homes = _nearest(some, centroids, 1).select("vec_id", "part_id")
        centroids = _means(some, homes, centroids)
    if not balanced:
        return _nearest(df, centroids, 1).select("vec_id", "part_id"), centroids
    return capacity_rounds(_nearest(df, centroids, p).checkpoint(), n, p, slack), centroids


def by_column(df: DataFrame, column: str) -> DataFrame:
    return df.select("vec_id", F.col(column).cast("int").alias("part_id"))


def fused(df: DataFrame, attributes: list[str], weight: float) -> DataFrame:
    """df with scaled attribute values appended to its vectors, for clustering by both."""
    stats = df.agg(*[f(a).alias(f"{n}_{a}") for a in attributes for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    extra = [F.coalesce((F.col(a) - stats[f"m_{a}"]) / F.lit(stats[f"s_{a}"] or 1.0), F.lit(0.0)) * weight for a in attributes]
    return df.withColumn("embedding", F.concat("embedding", F.array(*extra)))


def centroid_table(df: DataFrame, centroids: np.ndarray) -> DataFrame:
    return df.sparkSession.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(centroids)], "part_id int, centroid array<double>")


def residency(homes: DataFrame) -> DataFrame:
    """part_id, bucket, bitmap, n: which ids live in a partition. Bitmaps count from 1, so ids are moved by one."""
    at = F.col("vec_id") + 1
    built = homes.groupBy("part_id", F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bitmap"))
    return built.withColumn("n", F.bitmap_count("bitmap"))
