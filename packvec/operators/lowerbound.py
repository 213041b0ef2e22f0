"""Lower bounds of distances from cell numbers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def gap(q: Column, lo: Column, hi: Column) -> Column:
    """Distance of q to the interval [lo, hi]; 0 inside."""
    return F.greatest(lo - q, q - hi, F.lit(0.0))


def table(query: np.ndarray, edges: list[np.ndarray]) -> list[np.ndarray]:
    """For each dimension the squared distances of the query to all its cells."""
    out = []
    for q, e in zip(query, edges):
        lo, hi = e[:-1], e[1:]
        out.append(np.maximum(np.maximum(lo - q, q - hi), 0.0) ** 2)
    return out


def by_table(codes: np.ndarray, tables: list[np.ndarray]) -> np.ndarray:
    """Bounds of all rows by looking up each code."""
    total = np.zeros(len(codes))
    for j, t in enumerate(tables):
        if len(t) > 1:
            total += t[codes[:, j]]
        else:
            total += t[0]
    return np.sqrt(total)


def direct(codes: np.ndarray, query: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    """Bounds of all rows straight from the edges of their cells."""
    total = np.zeros(len(codes))
    for j, e in enumerate(edges):
        c = np.minimum(codes[:, j], len(e) - 2)
        total += np.maximum(np.maximum(e[c] - query[j], query[j] - e[c + 1]), 0.0) ** 2
    return np.sqrt(total)


def fuse(bits: list[int], most: int = 12) -> list[list[int]]:
    """Consecutive dimensions in groups of at most `most` bits together."""
    groups: list[list[int]] = []
    for j, b in enumerate(bits):
        if groups and sum(bits[i] for i in groups[-1]) + b <= most:
            groups[-1].append(j)
        else:
            groups.append([j])
    return groups


def fused(codes: np.ndarray, query: np.ndarray, edges: list[np.ndarray], bits: list[int], most: int = 12) -> np.ndarray:
    """Bounds with one table for each group of dimensions, indexed by their joined codes."""
    tables, total = table(query, edges), np.zeros(len(codes))
    for group in fuse(bits, most):
        joint, index = np.zeros(1), np.zeros(len(codes), np.int64)
        for j in group:
            full = np.zeros(1 << bits[j])
            full[: len(tables[j])] = tables[j]
            joint = (joint[:, None] + full[None, :]).ravel()
            index = (index << bits[j]) | codes[:, j]
        total += joint[index]
    return np.sqrt(total)


def centre(codes: np.ndarray, query: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    """Distances to the middles of the cells (M46): an estimate, not a bound."""
    total = np.zeros(len(codes))
    for j, e in enumerate(edges):
        c = np.minimum(codes[:, j], len(e) - 2)
        total += ((e[c] + e[c + 1]) / 2 - query[j]) ** 2
    return np.sqrt(total)
