"""Brute force (M53): the truth that searches are measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packvec.plans import tiles


def knn(queries: DataFrame, vectors: DataFrame, k: int = 10, metric: str = "l2", predicate: str | None = None) -> DataFrame:
    """query_id, rank, vec_id, dist: every query against every passing row, by products of query groups and row batches.

    metric: l2, cosine (1 - similarity) or dot (-product). Ties go to the smaller id, at nine decimals. Null vectors and
    those with null or non-finite components take no part, nor do zero vectors with cosine; vectors of other lengths
    are not compared.
    """
    rows = vectors.where(predicate) if predicate else vectors
    found = tiles.meet(queries.select("query_id", "qvec"), rows.select("vec_id", "embedding"), tiles.nearest(k, metric), tiles.FOUND)
    return ranked(found, k)


def ranked(found: DataFrame, k: int) -> DataFrame:
    """query_id, rank, vec_id, dist: the k nearest of what the cells found."""
    scored = found.select("query_id", "vec_id", F.round("dist", 9).alias("dist"))
    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "dist")
