"""Products of query groups and row batches against brute force, on odd inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from packvec.plans import baselines, exact, tiles
from packvec.queries import methods

ROWS = "vec_id long, embedding array<double>, label int"


def table(spark, n=300, d=5, seed=1):
    x = np.random.default_rng(seed).standard_normal((n, d)).round(2)
    x[n // 2 : n // 2 + 40] = x[0]  # copies: many ties
    rows = [(i, [float(c) for c in v], i % 3) for i, v in enumerate(x)]
    return spark.createDataFrame(rows, ROWS), x


def sides(df):
    return df.where("vec_id % 10 <> 0"), df.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))


@pytest.mark.parametrize("metric", ["l2", "dot", "cosine"])
def test_knn(spark, metric):
    df, x = table(spark)
    base, queries = sides(df)
    plan = exact.knn(queries, base, 7, metric)._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["dist"]) for r in exact.knn(queries, base, 7, metric).collect()}
    for q in range(0, 300, 10):
        f = {"l2": lambda a, b: np.sqrt(((a - b) ** 2).sum()), "dot": lambda a, b: -(a @ b), "cosine": lambda a, b: 1 - a @ b / np.sqrt((a @ a) * (b @ b))}[metric]
        want = sorted((round(float(f(x[q], x[i])), 9), i) for i in range(300) if i % 10)[:7]
        assert [got[q, r + 1][0] for r in range(7)] == [i for _, i in want]
        assert np.allclose([got[q, r + 1][1] for r in range(7)], [s for s, _ in want])


def test_null_and_odd_vectors_are_no_neighbours(spark):
    rows = [(0, [0.0, 0.0], 0), (1, None, 0), (2, [1.0, None], 0), (3, [float("nan"), 0.0], 0), (4, [1.0], 0), (5, [3.0, 4.0], 0), (6, [0.0, 1.0], 0), (10, None, 0)]
    base, queries = sides(spark.createDataFrame(rows, ROWS))
    assert [(r["query_id"], r["vec_id"], r["dist"]) for r in exact.knn(queries, base, 5).orderBy("rank").collect()] == [(0, 6, 1.0), (0, 5, 5.0)]
    assert exact.knn(queries, base.where("false"), 5).count() == 0 and exact.knn(queries.where("false"), base, 5).count() == 0


def test_by_and_other(spark):
    df, x = table(spark)
    every = df.select("label", F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    found = tiles.meet(every, df, tiles.nearest(2, other=True), tiles.FOUND, by="label").collect()
    for q in (0, 7, 151):
        dist = np.sqrt(((x - x[q]) ** 2).sum(1))
        want = sorted((round(float(dist[i]), 9), i) for i in range(300) if i % 3 == q % 3 and i != q)[:2]
        assert sorted((round(r["dist"], 9), r["vec_id"]) for r in found if r["query_id"] == q)[:2] == want
    assert all(r["query_id"] != r["vec_id"] and r["by"] == r["vec_id"] % 3 for r in found)


def test_radius(spark):
    df, x = table(spark)
    base, queries = sides(df)
    dist = {(q, i): np.sqrt(((x[q] - x[i]) ** 2).sum()) for q in range(0, 300, 10) for i in range(300) if i % 10}
    edge = dist[0, 1]  # a distance that occurs
    assert {(r["query_id"], r["vec_id"]) for r in tiles.meet(queries, base, tiles.within(float(edge), False), tiles.FOUND).collect()} == {p for p, s in dist.items() if s < edge}
    got = {r["query_id"]: r["n"] for r in tiles.meet(queries, base, tiles.counted(float(edge)), tiles.COUNTED).groupBy("query_id").agg(F.sum("n").alias("n")).collect()}
    assert got == {q: n for q in range(0, 300, 10) if (n := sum(s <= edge for (a, _), s in dist.items() if a == q))}


def test_bounds(spark, sf_dir):
    got = {(r["query_id"], r["vec_id"]): r["bound"] for r in methods.lb_direct(spark, sf_dir).collect()}
    short = methods.lb_shortlist(spark, sf_dir).where("query_id = 0").orderBy("rank").collect()
    assert [r["vec_id"] for r in short] == [i for _, i in sorted((b, i) for (q, i), b in got.items() if q == 0)[:20]]
    facts = methods.bound_tightness(spark, sf_dir).first()
    assert facts["pairs"] == len(got) and facts["violations"] == 0 and 0 < facts["tightness"] < 1
    for query in (methods.lb_direct, methods.lb_shortlist, methods.bound_tightness, methods.bound_correlation):
        plan = query(spark, sf_dir)._jdf.queryExecution().toString()
        assert "Join" not in plan and "Generate posexplode" not in plan


def test_full_shortlist_is_exact_and_lists_nothing(spark):
    df, _ = table(spark)
    base, queries = sides(df)
    found = baselines.product_search(base, queries, 3, m=2, bits=2, rerank=1000)
    assert found.exceptAll(exact.knn(queries, base, 3)).count() == 0 and found.count() == 90
    assert "adc" not in found._jdf.queryExecution().toString()


def test_whole_products(spark):
    from packvec.llm import topk_search

    df, x = table(spark)
    got = topk_search.search(df.where("vec_id % 50 = 0"), df, 5).collect()
    w = np.floor(256 * x).astype(int)
    for q in range(0, 300, 50):
        want = sorted((-int(w[q] @ w[i]), i) for i in range(300) if i != q)[:5]
        assert [(-r["score"], r["vec_id"]) for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == want
    assert "SortMergeJoin" not in topk_search.search(df, df, 5)._jdf.queryExecution().toString()
    with pytest.raises(Exception, match="not exact"):
        topk_search.search(*[spark.createDataFrame([(0, [1e7, 1e7], 0), (1, [1e7, 1e7], 0)], ROWS)] * 2).collect()


def test_best_sorts_only_the_queries_that_get_rows(monkeypatch):
    sorted_ = []
    real = np.lexsort
    monkeypatch.setattr(tiles.np, "lexsort", lambda keys: sorted_.append(len(keys[0])) or real(keys))
    best = tiles.Best(tiles.Side(0, np.arange(100), np.zeros((100, 2))), 3)
    best.add(np.repeat(np.arange(100), 4), np.tile([4.0, 3.0, 2.0, 1.0], 100), np.tile([4, 3, 2, 1], 100))
    best.add(np.array([51, 50, 50]), np.array([0.5, 2.5, 3.0]), np.array([9, 8, 0]))
    assert sorted_ == [400, 9]
    assert best.q.tolist() == np.repeat(np.arange(100), 3).tolist() and best.worst[[49, 50, 51, 52]].tolist() == [3, 2.5, 2, 3]
    assert best.ids.reshape(100, 3)[49:53].tolist() == [[1, 2, 3], [1, 2, 8], [9, 1, 2], [1, 2, 3]]


def by_codes(x, ids, books, queries, most, k):
    """Plainly: the k nearest of the most rows of least asymmetric distance, by query."""
    parts = np.array_split(np.arange(x.shape[1]), len(books))
    codes = [np.array([((v[p] - b) ** 2).sum(1).argmin() for v in x]) for p, b in zip(parts, books)]
    out = {}
    for q in queries:
        adc = np.zeros(len(ids))
        for p, b, c in zip(parts, books, codes):
            adc += ((x[q][p] - b) ** 2).sum(1)[c]
        some = [i for _, i in sorted((a, i) for a, i in zip(adc.round(12), ids) if i % 10)[:most]]
        out[q] = [i for _, i in sorted((round(float(np.sqrt(((x[q] - x[i]) ** 2).sum())), 9), i) for i in some)[:k]]
    return out


def got_lists(found):
    out = {}
    for r in found.orderBy("query_id", "rank").collect():
        out.setdefault(r["query_id"], []).append(r["vec_id"])
    return out


@pytest.mark.parametrize("most", [4, 200, 400, 900])
def test_product_search_takes_codes_and_shortlist_at_every_size(spark, monkeypatch, most):
    """Also where the shortlist holds the table or ends among rows that share a code."""
    x = np.random.default_rng(2).standard_normal((600, 5)).round(2)
    x[100:400] = np.repeat(x[:3], 100, axis=0) + np.random.default_rng(3).integers(0, 2, (300, 5)) / 1000  # near copies, few codes
    df = spark.createDataFrame([(i, [float(c) for c in v], 0) for i, v in enumerate(x)] + [(1001, None, 0), (1002, [float("nan")] * 5, 0)], ROWS)
    base, queries = sides(df)
    books, real = [], baselines.product_codebooks
    monkeypatch.setattr(baselines, "product_codebooks", lambda *a: books.append(real(*a)) or books[-1])
    got = got_lists(baselines.product_search(base, queries, 4, m=2, bits=2, rerank=most / 4))
    assert len(books) == 1 and got == by_codes(x, range(600), books[0], range(0, 600, 10), most, 4)


def test_product_search_without_rows(spark):
    df, _ = table(spark)
    base, queries = sides(df)
    assert baselines.product_search(base.where("false"), queries, 3).count() == 0
    assert baselines.product_search(base, queries.where("false"), 3).count() == 0


def test_shortlist_is_not_written_out(spark):
    """The tasks of the last pass give the k nearest, not rerank * k rows a query."""
    df, _ = table(spark)
    base, queries = sides(df)
    plan = baselines.product_search(base, queries, 3, m=2, bits=2, rerank=60)._jdf.queryExecution().toString()
    assert "adc" not in plan and "Join" not in plan


def test_cuts_end_where_the_nth_row_is(spark):
    rng = np.random.default_rng(5)
    x = np.repeat(rng.standard_normal((20, 4)), 60, axis=0)  # 60 rows a score
    df = spark.createDataFrame([(i * 7 - 3000, [float(c) for c in v], 0) for i, v in enumerate(x)], ROWS)
    queries = spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(rng.standard_normal((5, 4)))], "query_id long, qvec array<double>")
    scores = tiles.Scores([x[::60][:, :2], x[::60][:, 2:]], [np.arange(2), np.arange(2, 4)])
    for n in (1, 61, 700):
        cuts = tiles.cuts(queries, df, n, scores)
        for r in queries.collect():
            tables = scores.tables(np.array([r["qvec"]]))
            score = tiles.looked_up(tables, scores.codes(x))[:, 0].view(np.uint64)
            place = tiles.places(np.arange(1200) * 7 - 3000)
            at = cuts.at(np.array([r["query_id"]]))[0]
            up = (score < cuts.score[at]) | ((score == cuts.score[at]) & (place <= cuts.place[at]))
            assert up.sum() == n and np.flatnonzero(up).tolist() == sorted(np.lexsort((place, score))[:n].tolist())


def test_rounds_share_one_grid(spark, monkeypatch):
    """Queries and rows are dealt once for all rounds and once for the last pass, so disk does not grow with the rounds."""
    df, _ = table(spark)
    base, queries = sides(df)
    dealt, real = [], tiles.cells
    monkeypatch.setattr(tiles, "cells", lambda *a: dealt.append(real(*a)) or dealt[-1])
    assert baselines.product_search(base, queries, 3, m=2, bits=2, rerank=60).count() == 90
    assert len(dealt) == 2 and not any(d.is_cached for d in dealt)
