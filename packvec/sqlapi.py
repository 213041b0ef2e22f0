"""SQL names of the engine: macros over built-in functions, table functions, the vector file source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from packvec.functions import vectors
from packvec.sources import vecfile


@udtf(returnType="node_id: long, parent_id: long, level: int")
class DispatchTree:
    """SELECT * FROM dispatch_tree(fan, depth): the invocation tree in depth-first order."""

    def eval(self, fan: int, depth: int) -> Iterator[tuple]:
        stack, n = [(None, 1)] * fan, 0
        while stack:
            parent, level = stack.pop()
            yield n, parent, level
            if level < depth:
                stack += [(n, level + 1)] * fan
            n += 1


@udtf(returnType="cell: int, lo: double, hi: double")
class Cells:
    """SELECT * FROM quantizer_cells(array(edges)): a row for each cell."""

    def eval(self, edges: list) -> Iterator[tuple]:
        for i, (lo, hi) in enumerate(zip(edges, edges[1:])):
            yield i, lo, hi


def register(spark: SparkSession) -> None:
    vectors.register(spark)
    vecfile.register(spark)
    spark.udtf.register("dispatch_tree", DispatchTree)
    spark.udtf.register("quantizer_cells", Cells)
