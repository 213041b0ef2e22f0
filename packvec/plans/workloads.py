"""The experiments on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packvec.plans import exact, index, measures, search
from packvec.plans.shared import stored
from packvec.sources import tables as tb


def calibrate(found: index.Index, queries: DataFrame, truth: DataFrame, k: int, target: float, percents: tuple = (10.0, 30.0, 50.0, 100.0), reranks: tuple = (2.0, 5.0)) -> DataFrame:
    """hperc, rerank, recall of a small grid, cheapest first, up to the first that reaches the target."""
    truth, rows = stored(truth, "truth"), []
    for rerank in reranks:
        for h in percents:
            got = measures.recall(search.search(found, queries, k, search.Plan(hperc=h, rerank=rerank)), truth, k, ties=True).first()["recall"]
            rows.append((float(h), float(rerank), got))
            if got >= target:
                return queries.sparkSession.createDataFrame(rows, "hperc double, rerank double, recall double")
    return queries.sparkSession.createDataFrame(rows, "hperc double, rerank double, recall double")


def recall_by_pruning(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """partitions, hperc, recall, visited: how recall moves with pruning and partitions. visited: partitions a query, on average."""
    base, queries = tb.base_and_queries(tb.embeddings(spark, sf_dir))
    truth, rows = stored(exact.knn(queries, base, k), "truth"), []
    for p in (1, 4):
        found = index.build(base, [], index.Config(partitions=p, rounds=8))
        visited = measures.visited(search.reach(found, search.with_predicates(queries), search.Plan(), k)).first()["mean_partitions"]  # chosen before rows are pruned
        for h in (10.0, 30.0, 100.0):
            plan = search.Plan(hperc=h)
            got = measures.recall(search.search(found, queries, k, plan), truth, k, ties=True).first()["recall"]
            rows.append((p, h, got, visited))
    return spark.createDataFrame(rows, "partitions int, hperc double, recall double, visited double")


def selectivity_sweep(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """share, n_pass, recall with all partitions and no pruning: predicates over one to four attributes."""
    df = tb.uniform_attributes(tb.embeddings(spark, sf_dir))
    base, queries = tb.base_and_queries(df)
    found, rows = index.build(base, [f"u{j}" for j in range(4)], index.Config(partitions=1, rounds=4)), []
    for n, width in ((1, 0.1), (1, 0.5), (2, 0.5), (4, 0.532), (4, 0.9)):
        pred = " AND ".join(f"u{j} < {width}" for j in range(n))
        truth = stored(exact.knn(queries, base, k, predicate=pred), "truth")
        got = measures.recall(search.search(found, queries.withColumn("pred", F.lit(pred)), k, search.Plan(hperc=100, rerank=5)), truth, k).first()["recall"]
        rows.append((n, width, base.where(pred).count(), got))
    return spark.createDataFrame(rows, "attributes int, width double, n_pass long, recall double")


def allocator_sweep(spark: SparkSession, reached: DataFrame, shapes: tuple = ((10, 1), (4, 2), (4, 3), (5, 3), (6, 3), (4, 4))) -> DataFrame:
    """workers, queries a worker, processors launched, by shape of the tree."""
    from packvec.plans import dispatch

    reached, rows = stored(reached, "reach"), []
    for fan, depth in shapes:
        n = dispatch.size(fan, depth)
        roles = {r["role"]: r["workers"] for r in dispatch.roles(reached, dispatch.assign(reached.select("query_id").distinct(), n)).collect()}
        rows.append((fan, depth, n, roles["allocator"], roles["processor"]))
    return spark.createDataFrame(rows, "fan int, depth int, workers int, allocators long, processors long")


def suitability(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """solution, bytes_a_vector, recall at a shortlist of twice k (Tab. 1 as measured figures)."""
    from packvec.plans import baselines

    base, queries = tb.base_and_queries(tb.embeddings(spark, sf_dir))
    truth = stored(exact.knn(queries, base, k), "truth")
    size = dict(measures.memory(0, 64, 256, 8))
    one = index.build(base, [], index.Config(partitions=1, rounds=8))
    hits = {
        "packed": search.search(one, queries, k, search.Plan(hperc=50)),
        "product codes": baselines.product_search(base, queries, k, rerank=2),
        "graph with full vectors": baselines.graph(base, queries, k, partitions=1),
        "graph with codes": baselines.graph(base, queries, k, partitions=1, codes="sq"),
        "graph with full vectors, 8 partitions": baselines.graph(base, queries, k, partitions=8, ef=10),
    }
    rows = [(name, size[name.split(",")[0]], measures.recall(h, truth, k, ties=True).first()["recall"]) for name, h in hits.items()]
    return spark.createDataFrame(rows, "solution string, bytes_a_vector double, recall double")


def dataset_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """set, n, d, lid of the vector sets."""
    rows = []
    for name, df in (("embeddings", tb.embeddings(spark, sf_dir)), ("documents 64", tb.documents_vd(spark, sf_dir, 64))):
        df = stored(df.select("vec_id", "embedding"), "profile")
        base, queries = tb.base_and_queries(df)
        rows.append((name, df.count(), 64, measures.lid(exact.knn(queries, base, 50)).first()["lid"]))
    return spark.createDataFrame(rows, "name string, n long, d int, lid double")


__all__ = ["allocator_sweep", "calibrate", "dataset_profile", "recall_by_pruning", "selectivity_sweep", "suitability"]
