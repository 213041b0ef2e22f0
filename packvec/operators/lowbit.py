"""One-bit codes (M20), Hamming distances and pruning by them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def words(vector: Column, mean: Column, d: int) -> list[Column]:
    """ceil(d / 64) long columns: bit 1 where a component is above the mean, from the highest bit on.

    Scale does not change the sign, so centring is all that standardising comes to.
    """
    out = []
    for g in range(-(-d // 64)):
        word = F.lit(0).cast("long")
        for j in range(g * 64, min(d, (g + 1) * 64)):
            word = word.bitwiseOR(F.when(F.get(vector, j) > F.get(mean, j), F.shiftleft(F.lit(1).cast("long"), 63 - j % 64)).otherwise(F.lit(0).cast("long")))
        out.append(word.alias(f"low_{g:02d}"))
    return out


def distance(pairs: list[tuple[Column, Column]]) -> Column:
    """Differing bits over pairs of words."""
    total = F.lit(0)
    for a, b in pairs:
        total = total + F.bit_count(a.bitwiseXOR(b))
    return total.cast("int")


def kept(n: Column, percent: float, floor: int = 0) -> Column:
    """Candidates that pruning leaves of n: percent of them, but floor at least (floor 0: the percentage alone)."""
    return F.greatest(F.ceil(n * percent / 100), F.lit(floor)).cast("int")


def prune(candidates: DataFrame, percent: float, floor: int, *by: str) -> DataFrame:
    """The candidates (with ham and vec_id) of least distance in each group."""
    w = Window.partitionBy(*by)
    ranked = candidates.withColumns({"r": F.row_number().over(w.orderBy("ham", "vec_id")), "n": F.count(F.lit(1)).over(w)})
    return ranked.where(F.col("r") <= kept(F.col("n"), percent, floor)).drop("r", "n")


def pack_signs(matrix: np.ndarray) -> np.ndarray:
    return np.packbits(matrix > 0, axis=1)


def matrix_distances(rows: np.ndarray, query: np.ndarray) -> np.ndarray:
    return np.bitwise_count(rows ^ query).sum(1, dtype=np.int32)
