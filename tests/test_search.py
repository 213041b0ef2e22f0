"""The packed search against brute force, and the pieces around it."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from packvec.operators import partitioner, rotate
from packvec.plans import baselines, exact, index, measures, reuse, search
from packvec.plans.shared import stored
from packvec.sources import tables, vecfile

PRED = "totalprice BETWEEN 100000 AND 400000 AND priority <= '2-HIGH'"


@pytest.fixture(scope="module")
def small(spark, sf_dir):
    df = stored(tables.hybrid_ve(spark, sf_dir).where("vec_id < 200"), "small")
    base, queries = tables.base_and_queries(df, 20)
    return base, queries, index.build(base, ["totalprice", "priority", "status"], index.Config(partitions=3, rounds=4, chunk_rows=40))


def pairs(df):
    return {(r["query_id"], r["rank"], r["vec_id"]) for r in df.collect()}


def test_exact_stop(small):
    base, queries, found = small
    plan = search.Plan(hperc=100, policy="all", exact_stop=True)
    assert pairs(search.search(found, queries, 5, plan)) == pairs(exact.knn(queries, base, 5))
    assert pairs(search.search(found, queries.withColumn("pred", F.lit(PRED)), 5, plan)) == pairs(exact.knn(queries, base, 5, predicate=PRED))


def test_guarantee(small):
    """As many rows as pass, up to k, come back in one pass even from the tightest threshold."""
    base, queries, found = small
    narrow = "totalprice < 60000"
    n = base.where(narrow).count()
    hits = search.search(found, queries.withColumn("pred", F.lit(narrow)), 15, search.Plan(threshold=1.0))
    assert {r["n"] for r in hits.groupBy("query_id").agg(F.count("*").alias("n")).collect()} == {min(n, 15)}
    assert search.search(found, queries.withColumn("pred", F.lit("totalprice < 0")), 5).count() == 0


def test_recall_and_funnel(small):
    base, queries, found = small
    truth = exact.knn(queries, base, 5)
    low = measures.recall(search.search(found, queries, 5), truth, 5).first()["recall"]
    high = measures.recall(search.search(found, queries, 5, search.Plan(hperc=100, policy="all", rerank=6)), truth, 5).first()["recall"]
    assert high >= max(low, 0.97)
    for r in search.funnel(found, queries, 5).collect():
        assert r["n_rows"] >= r["n_filter"] >= r["n_low"] >= r["n_short"] > 0


def test_save_load_retain_cache(small, spark, tmp_path):
    base, queries, found = small
    found.save(str(tmp_path / "index"))
    keep = reuse.Retainer(spark)
    a, b = keep.get(str(tmp_path / "index")), keep.get(str(tmp_path / "index"))
    assert a is b and (keep.loads, keep.reuses) == (1, 1)
    want = pairs(search.search(found, queries, 5))
    assert pairs(search.search(a, queries, 5)) == want
    cache = reuse.ResultCache(spark, str(tmp_path / "cache"))
    run = lambda q: search.search(found, q, 5)
    assert pairs(cache.search(queries, 5, run)) == want == pairs(cache.search(queries, 5, run))
    n = queries.count()
    assert (cache.hits, cache.misses) == (n, n)
    keep.release()


def test_balanced(small):
    base, _, _ = small
    homes, _ = partitioner.kmeans(base, 4, rounds=2, balanced=True)
    sizes = [r["n"] for r in homes.groupBy("part_id").agg(F.count("*").alias("n")).collect()]
    assert sum(sizes) == base.count() and max(sizes) <= np.ceil(base.count() * 1.05 / 4)


def test_rotation(small):
    base, _, _ = small
    df = base.select(F.lit(0).alias("part_id"), "vec_id", "embedding")
    turned = rotate.apply(df, rotate.fit(df, 64), 64).toPandas()
    x = np.stack(turned["embedding"])
    c = x.T @ x / len(x)
    assert np.abs(c - np.diag(np.diag(c))).max() < 1e-9 and (np.diff(np.diag(c)) < 1e-9).all()


def test_graph_and_filters(small):
    base, queries, _ = small
    truth = exact.knn(queries, base, 5)
    assert measures.recall(baselines.graph(base, queries, 5, partitions=2), truth, 5).first()["recall"] > 0.8
    passing = exact.knn(queries, base, 5, predicate=PRED)
    assert measures.recall(baselines.graph(base, queries, 5, partitions=2, predicate=PRED, filter="during"), passing, 5).first()["recall"] > 0.5


def test_vector_files(spark, tmp_path):
    vecfile.register(spark)
    x = np.arange(30, dtype="f4").reshape(10, 3)
    vecfile.write_vectors(x, str(tmp_path / "a.fvecs"))
    rows = spark.read.format("packvec_vectors").option("dim", 3).option("rows", 4).load(str(tmp_path / "a.fvecs")).orderBy("vec_id").collect()
    assert [r["vec_id"] for r in rows] == list(range(10)) and [r["embedding"] for r in rows] == x.tolist()


def test_quarantine(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [float("nan"), 1.0]), (4, [1.0]), (5, [None, 1.0]), (6, [])], "vec_id long, embedding array<double>")
    good, bad = tables.split_valid(df, d=2)
    assert [r["vec_id"] for r in good.collect()] == [1] and sorted(r["vec_id"] for r in bad.collect()) == [2, 3, 4, 5, 6]


def test_registration(spark):
    from packvec import sqlapi

    sqlapi.register(spark)
    assert spark.sql("SELECT count(*) n FROM dispatch_tree(4, 3)").first()["n"] == 84
    assert spark.sql("SELECT pv_l2(array(0D, 3D), array(4D, 0D)) d").first()["d"] == 5.0


def test_plan_reads_no_vectors_for_counts(small):
    """Counting what passes reads attribute columns only."""
    _, _, found = small
    plan = search.counts(found, {"": ()})._jdf.queryExecution().executedPlan().toString()
    assert "packed" not in plan and "c_totalprice" in plan


def test_profile_takes_all_held_out_queries(spark, monkeypatch):
    from packvec.plans import workloads

    monkeypatch.setattr(tables, "documents_vd", lambda spark, d, n: tables.embeddings(spark, d))
    d = "/root/testdata/sf0.1"
    base, queries = tables.base_and_queries(tables.embeddings(spark, d).select("vec_id", "embedding"))
    assert queries.count() == 200
    got = {r["name"]: r["lid"] for r in workloads.dataset_profile(spark, d).collect()}
    want = measures.lid(exact.knn(queries, base, 50)).first()["lid"]
    assert list(got.values()) == pytest.approx([want, want], abs=1e-4)


def test_profile_takes_all_documents(spark, tmp_path):
    """Also those without a token, and those whose tokens cancel."""
    from packvec.plans import workloads

    d, texts = str(tmp_path), [None, "", " .,;", "one", *(f"word{i % 7} word{i % 11} tail{i}" for i in range(96))]
    spark.createDataFrame([(i, t, "en", "web", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(3, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    tables.embeddings(spark, "/root/testdata/sf0.001").write.parquet(f"{d}/embeddings.parquet")
    rows = {r["vec_id"]: r for r in tables.documents_vd(spark, d, 16).collect()}
    assert sorted(rows) == list(range(100)) and rows[3]["quality"] == 1 and rows[0]["lang"] == "en"
    assert all(rows[i]["embedding"] == [0.0] * 16 for i in range(3))
    assert all(sum(x * x for x in rows[i]["embedding"]) == pytest.approx(1) or rows[i]["embedding"] == [0.0] * 16 for i in range(100))
    assert {r["name"]: r["n"] for r in workloads.dataset_profile(spark, d).collect()}["documents 64"] == 100


def test_recall_by_pruning_says_how_many_partitions_are_visited(spark, sf_dir):
    from packvec.plans import workloads

    rows = workloads.recall_by_pruning(spark, sf_dir).collect()
    assert rows[0].__fields__ == ["partitions", "hperc", "recall", "visited"] and len(rows) == 6
    base, queries = tables.base_and_queries(tables.embeddings(spark, sf_dir))
    found = index.build(base, [], index.Config(partitions=4, rounds=8))
    n = search.funnel(found, queries, 10, search.Plan(hperc=100)).agg(F.avg("n_visited")).first()[0]
    assert {r["visited"] for r in rows if r["partitions"] == 1} == {1.0}
    assert {r["visited"] for r in rows if r["partitions"] == 4} == {round(n, 6)} and 1 <= n <= 4


def test_append(small):
    base, queries, _ = small
    cfg = index.Config(partitions=2, rounds=3)
    some = index.build(base.where("vec_id % 3 <> 1"), ["totalprice", "priority", "status"], cfg)
    whole = index.append(some, base.where("vec_id % 3 = 1 OR vec_id = 2"))
    plan = search.Plan(hperc=100, policy="all", exact_stop=True)
    assert pairs(search.search(whole, queries.withColumn("pred", F.lit(PRED)), 5, plan)) == pairs(exact.knn(queries, base, 5, predicate=PRED))
    with pytest.raises(ValueError):
        index.append(some, base.withColumn("status", F.lit("new")))


def test_requests_are_keyed_once(spark, small, tmp_path):
    """What a cache's search runs on is read again, not hashed again in each of its jobs."""
    base, queries, _ = small
    seen = []

    def run(q):
        seen.append(q._jdf.queryExecution().toString())
        return exact.knn(q, base, 3)

    cache = reuse.ResultCache(spark, str(tmp_path / "results"))
    assert pairs(cache.search(queries.unionByName(queries.withColumn("query_id", F.col("query_id") + 1)), 3, run).where("query_id % 20 = 0")) == pairs(exact.knn(queries, base, 3))
    assert len(seen) == 1 and "sha2" not in seen[0] and cache.hits == cache.misses == queries.count()


def test_recall_measure_searches_once(spark, sf_dir):
    from packvec.queries import runs

    found = runs.recall_measure(spark, sf_dir)
    assert "MapInArrow" not in found._jdf.queryExecution().toString() and found.first()["recall"] == 0.5


def test_places_of_the_nearest_codes_and_least_bounds():
    rng = np.random.default_rng(3)
    for width in (1, 2):
        words, query = rng.integers(0, 4, (500, width)).astype(np.uint64), rng.integers(0, 4, width).astype(np.uint64)
        ham = np.bitwise_count(words ^ query).sum(1)
        for left in (1, 7, 250, 499):
            assert search.nearest_codes(words, query, left).tolist() == sorted(np.lexsort((np.arange(500), ham))[:left].tolist())
    bound = rng.integers(0, 9, 300) / 2
    for n in (1, 20, 299, 300, 400):
        assert search.least(bound, n).tolist() == np.lexsort((np.arange(300), bound))[:n].tolist()


def test_queries_of_one_chunk_are_split_over_tasks(spark, small):
    base, queries, _ = small
    one = index.build(base, [], index.Config(partitions=1, rounds=4))
    many = queries.crossJoin(spark.range(40).withColumnRenamed("id", "c")).select((F.col("query_id") * 40 + F.col("c")).alias("query_id"), "qvec")
    assert search.slices(many, 1) > 1 and search.slices(queries, 1) == 1
    plan = search.Plan(hperc=100, policy="all", exact_stop=True)
    got = search.search(one, many, 5, plan)
    assert "slice" in got._jdf.queryExecution().toString()
    assert pairs(got) == pairs(exact.knn(many, base, 5))
