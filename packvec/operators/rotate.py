"""Unitary rotation to the principal axes, one basis a partition or one for all."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def basis(n: int, sums: np.ndarray, products: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(mean, columns of eigenvectors by falling eigenvalue) from summed vectors and outer products; signs are fixed."""
    mean = sums / max(n, 1)
    values, vectors = np.linalg.eigh(products / max(n, 1) - np.outer(mean, mean))
    vectors = vectors[:, np.argsort(-values, kind="stable")]
    top = np.abs(vectors).argmax(0)
    return mean, vectors * np.sign(vectors[top, np.arange(len(sums))])


def moments(df: DataFrame, d: int) -> DataFrame:
    """part_id, n, s (sum), ss (outer products, d * d), summed within tasks and then by partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            x = np.asarray(batch.column(1).flatten(), float).reshape(-1, d)
            part = np.asarray(batch.column(0))
            for p in np.unique(part):
                own = x[part == p]
                h = held.setdefault(int(p), [0, np.zeros(d), np.zeros((d, d))])
                h[0] += len(own)
                h[1] += own.sum(0)
                h[2] += own.T @ own
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([*held], pa.int32()), pa.array([h[0] for h in held.values()], pa.int64()), pa.array([np.r_[h[1], h[2].ravel()].tolist() for h in held.values()], pa.list_(pa.float64()))], names=["part_id", "n", "m"])

    parts = df.select(F.col("part_id").cast("int"), "embedding").mapInArrow(run, "part_id int, n long, m array<double>")
    total = parts.select("part_id", "n", F.posexplode("m").alias("i", "x")).groupBy("part_id", "i").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    return total.groupBy("part_id").agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda t: t["x"]).alias("m"))


def fit(df: DataFrame, d: int, scope: str = "partition") -> DataFrame:
    """part_id, mean, rotation (d * d, row by row); scope global gives every partition the same."""
    own = df if scope == "partition" else df.withColumn("part_id", F.lit(0))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [basis(n, np.array(m[:d]), np.array(m[d:]).reshape(d, d)) for n, m in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([m.tolist() for m, _ in found], pa.list_(pa.float64())), pa.array([r.ravel().tolist() for _, r in found], pa.list_(pa.float64()))], names=["part_id", "mean", "rotation"])

    out = moments(own, d).mapInArrow(run, "part_id int, mean array<double>, rotation array<double>")
    if scope == "partition":
        return out
    return df.select("part_id").distinct().crossJoin(F.broadcast(out.select("mean", "rotation")))


def apply(df: DataFrame, model: DataFrame, d: int) -> DataFrame:
    """df (part_id, ..., embedding) with embedding centred and rotated by its partition's model."""
    joined = df.join(model, "part_id")
    keep = [c for c in df.columns if c != "embedding"]
    kinds = {f.name: f.dataType.simpleString() for f in joined.schema.fields}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            t = pa.Table.from_batches([batch])
            x, m, r = (np.asarray(t.column(c).combine_chunks().flatten(), float) for c in ("embedding", "mean", "rotation"))
            x, m, r = x.reshape(-1, d), m.reshape(-1, d), r.reshape(-1, d, d)
            y = np.einsum("nd,nde->ne", x - m, r)
            values = pa.ListArray.from_arrays(pa.array(np.arange(len(y) + 1, dtype=np.int32) * d), pa.array(y.ravel()))
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.names.index(c)) for c in keep), values], names=[*keep, "embedding"])

    return joined.select(*keep, "embedding", "mean", "rotation").mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in keep) + ", embedding array<double>")
