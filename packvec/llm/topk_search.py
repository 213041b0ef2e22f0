"""Operator 4: exact top-k inner products, by products of query groups and row batches.

Queries and rows meet on a grid (plans.tiles): a task holds a bounded group of queries and takes its rows batch by batch,
so neither a join nor a batch carries a matrix, whatever the number of partitions. Each task keeps the k best of every
query it holds; these lists are merged by query. Products are of whole numbers below 2 ** 53 in double precision and so
exact.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packvec.plans import tiles

#: Rows and queries of one product.
TILE, BLOCK = 2048, 2048


def whole_numbers(embedding: str, factor: int = 256):
    """floor(factor * x) of each component as double."""
    return F.transform(F.col(embedding), lambda x: F.floor(x.cast("double") * F.lit(float(factor))).cast("double"))


def usable(embedding: str):
    bad = F.exists(F.col(embedding), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.col(embedding).isNotNull() & (F.size(embedding) > 0) & ~bad


def best_of(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best of each row by score, ties to the smaller id. -inf counts as absent."""
    if scores.shape[1] <= k:
        return scores, np.broadcast_to(ids, scores.shape)
    order = np.argsort(ids, kind="stable")
    scores, ids = scores[:, order], ids[order]
    last = -np.partition(-scores, k - 1, axis=1)[:, k - 1 : k]  # the k-th best score; of those equal to it the first are taken
    above, level = scores > last, scores == last
    taken = above | (level & (np.cumsum(level, 1) <= k - above.sum(1, keepdims=True)))
    picked = np.nonzero(taken)[1].reshape(len(scores), k)
    return np.take_along_axis(scores, picked, 1), ids[picked]


def search(queries: DataFrame, rows: DataFrame, k: int = 5, id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k rows with the largest products for each query, a row with its id left out.

    Scores are products of floor(256 * x); ties go to the smaller id. Edge cases: rows with a null id, a null or empty
    vector or a null, NaN or infinite component take no part; vectors of other lengths are not compared; a query with
    fewer candidates gets all of them; queries that share an id and a vector give one list; repeated rows are
    candidates of their own; other columns are not looked at; an empty side gives an empty result.
    """
    def clean(df: DataFrame, key: str, vector: str) -> DataFrame:
        return df.where(usable(embedding) & F.col(id).isNotNull()).select(F.col(id).cast("long").alias(key), whole_numbers(embedding).alias(vector))

    lists = tiles.meet(clean(queries, "query_id", "qvec").distinct(), clean(rows, "vec_id", "embedding"), tiles.nearest(k, "dot", other=True, whole=True, rows=TILE, block=BLOCK), tiles.FOUND)
    scored = lists.select("query_id", "vec_id", (-F.col("dist")).cast("long").alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))))
    return ranked.where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
