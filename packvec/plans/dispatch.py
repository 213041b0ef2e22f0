"""The invocation tree and the work it spreads."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def size(fan: int, depth: int) -> int:
    """Workers below the root of a tree of that fan-out and depth."""
    return depth if fan == 1 else sum(fan**level for level in range(1, depth + 1))


def tree(spark: SparkSession, fan: int, depth: int) -> DataFrame:
    """node_id, parent_id (null: the root starts it), level, subtree_lo, subtree_hi: ids in depth-first order from 0.

    A subtree below level l spans a run of ids, so each node knows its children from its own id, the fan-out and the
    depth: child c of a node begins behind the node and the c subtrees before it. Levels are joined on, not looped over
    node by node.
    """
    below = [size(fan, depth - level) + 1 for level in range(1, depth + 1)]  # ids of a subtree whose top is at that level
    now = spark.range(fan).select((F.col("id") * below[0]).alias("node_id"), F.lit(None).cast("long").alias("parent_id"), F.lit(1).alias("level"))
    out = now
    for level in range(2, depth + 1):
        child = F.explode(F.sequence(F.lit(0), F.lit(fan - 1)))
        now = now.select("node_id", child.alias("c")).select((F.col("node_id") + 1 + F.col("c") * below[level - 1]).alias("node_id"), F.col("node_id").alias("parent_id"), F.lit(level).alias("level"))
        out = out.unionByName(now)
    span = F.element_at(F.array(*[F.lit(b) for b in below]), F.col("level"))
    return out.select("node_id", "parent_id", "level", F.col("node_id").alias("subtree_lo"), (F.col("node_id") + span - 1).alias("subtree_hi"))


def dealt(nodes: DataFrame, ids: DataFrame, workers: int) -> DataFrame:
    """nodes with n_queries: how many of the queries (one column, a whole number) each gets that are dealt round by id."""
    n = ids.toDF("id").where("id IS NOT NULL").groupBy(F.pmod(F.col("id").cast("long"), F.lit(workers)).alias("node_id")).agg(F.count(F.lit(1)).alias("n_queries"))
    return nodes.join(n, "node_id", "left").withColumn("n_queries", F.coalesce("n_queries", F.lit(0)))


def assign(queries: DataFrame, workers: int) -> DataFrame:
    """query_id, allocator: queries spread evenly, a run of ids each."""
    return queries.select("query_id", (F.ntile(workers).over(Window.orderBy("query_id")) - 1).alias("allocator"))


def load(assigned: DataFrame) -> DataFrame:
    """Workers, and queries a worker: least, most, mean."""
    each = assigned.groupBy("allocator").agg(F.count(F.lit(1)).alias("n"))
    return each.agg(F.count(F.lit(1)).alias("workers"), F.min("n").alias("least"), F.max("n").alias("most"), F.round(F.avg("n"), 4).alias("mean"))


def fan_in(nodes: DataFrame, mode: str = "tree") -> DataFrame:
    """Responses that each receiving node gets: by its children, or all by the root (mode flat). The root is -1."""
    to = F.coalesce("parent_id", F.lit(-1)) if mode == "tree" else F.lit(-1).cast("long")
    return nodes.groupBy(to.alias("receiver")).agg(F.count(F.lit(1)).alias("responses"))


def fan_in_report(nodes: DataFrame) -> DataFrame:
    """mode, workers, depth, root_responses, most_responses for the tree and the flat way."""
    out = None
    for mode in ("tree", "flat"):
        got = fan_in(nodes, mode)
        row = got.agg(F.sum("responses").alias("workers"), F.max(F.when(F.col("receiver") == -1, F.col("responses"))).alias("root_responses"), F.max("responses").alias("most_responses"))
        depth = nodes.agg(F.max("level").alias("depth")) if mode == "tree" else nodes.agg(F.lit(1).alias("depth"))
        row = row.crossJoin(F.broadcast(depth)).select(F.lit(mode).alias("mode"), "workers", "depth", "root_responses", "most_responses")
        out = row if out is None else out.unionByName(row)
    return out


def roles(reached: DataFrame, assigned: DataFrame) -> DataFrame:
    """role, workers of a run: one coordinator, the allocators, and a processor for each (allocator, partition)."""
    pairs = reached.select("query_id", "part_id").join(assigned, "query_id").select("allocator", "part_id").distinct()
    n = pairs.agg(F.count(F.lit(1)).alias("processors"), F.count_distinct("allocator").alias("allocators"))
    return n.select(F.inline(F.array(F.struct(F.lit("coordinator").alias("role"), F.lit(1).cast("long").alias("workers")), F.struct(F.lit("allocator").alias("role"), F.col("allocators").alias("workers")), F.struct(F.lit("processor").alias("role"), F.col("processors").alias("workers")))))


def interleaved(batches: list, prepare, process) -> list:
    """process(prepare(b)) of each batch; the next batch is prepared while one is processed."""
    out = []
    with ThreadPoolExecutor(1) as pool:
        ready = pool.submit(prepare, batches[0]) if batches else None
        for i in range(len(batches)):
            now = ready.result()
            ready = pool.submit(prepare, batches[i + 1]) if i + 1 < len(batches) else None
            out.append(process(now))
    return out
