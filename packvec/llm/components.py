"""Connected components of an edge table: forests within tasks, then alternating large and small stars."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packvec.llm.common import written

#: Edges that one task may hold as a forest.
HELD = 500_000


class Forest:
    """Trees of numbers whose root is their least."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, i: int) -> int:
        up = self.up
        while (j := up.get(i, i)) != i:
            up[i] = up.get(j, j)
            i = up[i]
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.root(i), self.root(j)
        self.up[max(i, j)] = min(i, j)


def contract(held: int):
    """(u, v) rows into (u, root) rows that connect the same numbers; what a task holds is bounded by held edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = Forest()

        def stars() -> pa.RecordBatch:
            low = [(u, r) for u in list(forest.up) if (r := forest.root(u)) != u]
            return pa.RecordBatch.from_arrays([pa.array([x[c] for x in low], pa.int64()) for c in (0, 1)], names=["u", "v"])

        for batch in batches:
            for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if len(forest.up) >= held and (u not in forest.up or v not in forest.up):
                    yield stars()
                    forest = Forest()
                forest.join(u, v)
        if forest.up:
            yield stars()

    return run


def components(edges: DataFrame, a: str = "a", b: str = "b", held: int = HELD) -> DataFrame:
    """node, root for every node of edges (long columns); root is the least node that it can reach.

    Tasks first replace their edges by a spanning forest, without a shuffle. Each round then joins edges with the least
    neighbour of one end and writes the new edges to the shared folder, until they no longer change or are so few that
    one task's forest holds them all, which ends it. The number of rounds grows with the logarithm of the nodes. Edges
    from a node to itself leave no node; an empty table gives an empty result.
    """
    def ordered(x: DataFrame) -> DataFrame:
        return x.where(F.col("u") != F.col("v")).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    found = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where(F.col("u") != F.col("v"))
    now = written(found.mapInArrow(contract(held), "u long, v long"), "edges")
    before = None
    while True:
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before or not state[0]:
            break
        if state[0] <= held:
            now = written(now.coalesce(1).mapInArrow(contract(held + 1), "u long, v long"), "edges")
            break
        before = state
        # Large star: each neighbour above u goes to the least of u and its neighbours.
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")).select(F.col("u").alias("w"), "m")
        large = ordered(both.where(F.col("v") > F.col("u")).join(least, F.col("u") == F.col("w")).select(F.col("v").alias("u"), F.col("m").alias("v")))
        # Small star: neighbours below u, and u, go to the least of them.
        least = large.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("w"), "m")
        moved = large.join(least, F.col("u") == F.col("w")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = written(ordered(moved.unionByName(least.select(F.col("w").alias("u"), F.col("m").alias("v")))), "edges")
    rooted = now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
    return rooted.unionByName(rooted.select(F.col("root").alias("node"), "root").distinct())
