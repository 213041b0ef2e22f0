"""Cell edges of one-dimensional quantizers (M03, M04) and encoding."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def uniform(values: DataFrame, bits: DataFrame, *by: str) -> DataFrame:
    """by, dim, edges: cells of equal width between the least and the greatest value."""
    ends = values.groupBy(*by, "dim").agg(F.min("x").alias("lo"), F.max("x").alias("hi")).join(bits, [*by, "dim"])
    at = lambda i: F.round(F.col("lo") + (F.col("hi") - F.col("lo")) * i / F.col("cells"), 9)
    return ends.select(*by, "dim", F.transform(F.sequence(F.lit(0).cast("long"), F.col("cells")), at).alias("edges"))


def equal_depth(values: DataFrame, bits: DataFrame, *by: str, accuracy: int = 10_000) -> DataFrame:
    """by, dim, edges: cells of equal counts. Exact percentiles, interpolated between ranks.

    Approximate percentiles on both sides of each wanted rank bracket it; values outside the brackets are only counted,
    within the tasks, and those inside are counted one by one. A task holds the bracketed values of a group: for each
    edge about 4 / accuracy of its values, at distinct ones.
    """
    group = [*by, "dim"]
    kinds = [r["bits"] for r in bits.select("bits").distinct().collect()]  # as many as there are widths, at most 64
    values = values.where(F.col("x").isNotNull())
    out = None
    for b in kinds:
        share, off = [i / 2**b for i in range(2**b + 1)], 2 / accuracy
        wide = values.join(F.broadcast(bits.where(F.col("bits") == b).select(*group)), group, "left_semi")
        probe = lambda side: F.percentile_approx("x", [min(max(s + side * off, 0.0), 1.0) for s in share], accuracy)
        ends = wide.groupBy(*group).agg(probe(-1).alias("los"), probe(1).alias("his"), F.min("x").alias("least"), F.max("x").alias("most"), F.count(F.lit(1)).alias("n"))
        fixed = lambda c, end, at: F.transform(c, lambda e, i: F.when(i == at, F.col(end)).otherwise(e))
        ends = ends.select(*group, fixed("los", "least", 0).alias("los"), fixed("his", "most", 2**b).alias("his"), "n")
        below, ended = F.size(F.filter("los", lambda e: e <= F.col("x"))), F.size(F.filter("his", lambda e: e < F.col("x")))
        placed = wide.join(F.broadcast(ends.drop("n")), group).select(*group, "x", below.alias("s"), (below > ended).alias("inside"))
        counted = placed.groupBy(*group, "s", "inside", F.when(F.col("inside"), F.col("x")).alias("at")).agg(F.count(F.lit(1)).alias("c"), F.min("x").alias("x"))
        past = F.sum("c").over(Window.partitionBy(*group).orderBy("x"))
        spans = counted.withColumn("past", past).join(F.broadcast(ends.select(*group, "n")), group)
        position = F.transform(F.array(*map(F.lit, share)), lambda p: p * (F.col("n") - 1))
        ranks = F.array_distinct(F.concat(F.transform(position, lambda p: F.floor(p)), F.transform(position, lambda p: F.ceil(p))))
        hit = spans.withColumn("rank", F.explode(F.filter(ranks, lambda r: (r >= F.col("past") - F.col("c")) & (r < F.col("past")))))
        sure = F.when(F.col("inside"), F.col("x")).otherwise(F.raise_error(F.lit("a rank lies outside its bracket")).cast("double"))
        found = hit.groupBy(*group).agg(F.map_from_entries(F.collect_list(F.struct("rank", sure.alias("x")))).alias("at"), F.first("n").alias("n"))

        def edge(p):
            low, high = F.element_at("at", F.floor(p)), F.element_at("at", F.ceil(p))
            return F.round(F.when(low == high, low).otherwise((F.ceil(p) - p) * low + (p - F.floor(p)) * high), 9)

        part = found.select(*group, F.transform(position, edge).alias("edges"))
        out = part if out is None else out.unionByName(part)
    return out


def lloyd_edges(x: np.ndarray, cells: int, rounds: int = 15) -> np.ndarray:
    """Edges of the best cells that rounds of one-dimensional k-means find from equal-depth cells.

    Outer edges are the least and greatest value. Fewer distinct values than cells give as many cells as values.
    """
    x = np.sort(np.asarray(x, float))
    distinct = np.unique(x)
    cells = min(cells, len(distinct))
    if cells <= 1:
        return np.array([x[0], x[-1]])
    centres = np.unique(np.quantile(x, (np.arange(cells) + 0.5) / cells))
    if len(centres) < cells:
        centres = distinct[np.linspace(0, len(distinct) - 1, cells).round().astype(int)]
    sums = np.r_[0.0, np.cumsum(x)]
    for _ in range(rounds):
        cut = np.r_[0, np.searchsorted(x, (centres[1:] + centres[:-1]) / 2, "right"), len(x)]
        n = np.diff(cut)
        means = np.where(n > 0, (sums[cut[1:]] - sums[cut[:-1]]) / np.maximum(n, 1), centres)
        if np.array_equal(means, centres):
            break
        centres = np.sort(means)
    return np.r_[x[0], np.clip((centres[1:] + centres[:-1]) / 2, x[0], x[-1]), x[-1]]


def lloyd(values: DataFrame, bits: DataFrame, *by: str, rounds: int = 15, sample: int = 1_000_000) -> DataFrame:
    """by, dim, edges by one-dimensional k-means. A group takes at most `sample` of its values, chosen by a hash.

    values: by, vec_id, dim, x.
    """
    counted = values.groupBy(*by, "dim").agg(F.count(F.lit(1)).alias("n"))
    share = F.least(F.lit(sample) / F.col("n"), F.lit(1.0))
    kept = values.join(counted.join(bits, [*by, "dim"]), [*by, "dim"]).where(F.pmod(F.xxhash64("vec_id", "dim"), F.lit(1_000_000)) < share * 1_000_000)
    kinds = {f.name: f.dataType.simpleString() for f in kept.schema.fields}

    def fit(table: pa.Table) -> pa.Table:
        edges = lloyd_edges(table.column("x").to_numpy(), int(table.column("cells")[0].as_py()), rounds)
        return pa.table({**{c: table.column(c).slice(0, 1) for c in (*by, "dim")}, "edges": pa.array([edges.tolist()], pa.list_(pa.float64()))})

    schema = ", ".join(f"{c} {kinds[c]}" for c in (*by, "dim")) + ", edges array<double>"
    return kept.select(*by, "dim", "x", "cells").groupBy(*by, "dim").applyInArrow(fit, schema)


def cell(x, edges):
    """Number of the cell that x is in; the last cell is closed, values outside count to the outer cells."""
    return F.greatest(F.least(F.size(F.filter(edges, lambda e: e <= x)) - 1, F.size(edges) - 2), F.lit(0)).cast("int")


def encode(values: DataFrame, edges: DataFrame, *by: str) -> DataFrame:
    """values with the code of each component. edges is an index artefact of one row a dimension; it is broadcast."""
    return values.join(F.broadcast(edges), [*by, "dim"]).withColumn("code", cell(F.col("x"), F.col("edges"))).drop("edges")


def distortion(values: DataFrame, edges: DataFrame, *by: str) -> DataFrame:
    """Mean squared distance of the values to the middle of their cells, by dimension."""
    coded = values.join(edges, [*by, "dim"]).withColumn("code", cell(F.col("x"), F.col("edges")))
    middle = (F.element_at("edges", F.col("code") + 1) + F.element_at("edges", F.col("code") + 2)) / 2
    return coded.groupBy(*by, "dim").agg(F.round(F.avg((F.col("x") - middle) * (F.col("x") - middle)), 9).alias("distortion"))
