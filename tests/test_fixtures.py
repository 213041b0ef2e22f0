"""Worked examples, by hand."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from packvec.operators import attributes, bits, lowbit, lowerbound, predicates, quantizers, segments, select
from packvec.operators.predicates import P
from packvec.plans import cost, dispatch, measures
from packvec.plans.index import allocate_bits


def test_storage(spark):
    plan = spark.createDataFrame([(j, 4, 16) for j in range(128)], "dim int, bits int, cells long")
    r = bits.storage(plan, 8).first()
    assert (r["packed_words"], r["plain_words"], r["plain_waste"], r["packed_padding"]) == (64, 128, 512, 0)


def test_bits_by_hand(spark):
    got = {r["dim"]: r["bits"] for r in bits.allocate(spark.createDataFrame([(0, 16.0), (1, 4.0), (2, 1.0)], "dim int, variance double"), 4).collect()}
    assert got == {0: 3, 1: 1, 2: 0}


def greedy(variance, budget, most):
    left, out = list(variance), [0] * len(variance)
    for _ in range(budget):
        j = max((j for j in range(len(left)) if out[j] < most), key=lambda j: (left[j], -j), default=None)
        if j is None:
            break
        out[j] += 1
        left[j] /= 4.0
    return out


@given(st.lists(st.integers(0, 1 << 40), min_size=1, max_size=12), st.integers(0, 40))
def test_ranking_equals_greedy(variance, budget):
    assert allocate_bits(np.array(variance, float), budget, 4.0, 16).tolist() == greedy([float(v) for v in variance], budget, 16)


@pytest.mark.parametrize("plan,codes,words", [([3, 5, 8], [5, 22, 200], [0xB6, 0xC8]), ([5, 5, 6], [19, 13, 42], [0x9B, 0x6A]), ([9, 7], [300, 5], [0x96, 0x05]), ([0, 8], [0, 7], [0x07])])
def test_packing_by_hand(spark, plan, codes, words):
    df = spark.createDataFrame([(codes,)], "codes array<int>").select("codes", *segments.pack(F.col("codes"), plan, 8))
    assert [df.first()[f"seg_{g:03d}"] for g in range(len(words))] == words
    assert df.select(segments.unpack(plan, 8).alias("c")).first()["c"] == codes
    assert segments.pack_matrix(np.array([codes]), plan)[0].tolist() == words


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 17), min_size=1, max_size=20), st.integers(0, 2**32))
def test_pack_unpack(plan, seed):
    rng = np.random.default_rng(seed)
    codes = np.array([[rng.integers(0, 1 << b) if b else 0 for b in plan] for _ in range(5)])
    assert (segments.unpack_matrix(segments.pack_matrix(codes, plan, 8), plan) == codes).all()


def test_cells_of_a_predicate():
    a = attributes.Attribute("a", "numeric", [0.0, 10.0, 20.0, 30.0])
    assert predicates.cell_pass(P("a") < 15, a) == [1, 2, 0]
    assert predicates.cell_pass(P("a") < 10, a) == [1, 0, 0]
    assert predicates.cell_pass(P("a") <= 10, a) == [1, 2, 0]
    assert predicates.cell_pass(P("a") == 30, a) == [0, 0, 2]
    assert predicates.cell_pass(P("a").between(10, 20), a) == [0, 1, 2]


@given(st.lists(st.integers(-5, 5), min_size=2, max_size=6, unique=True), st.sampled_from(["<", "<=", "=", ">=", ">", "between"]), st.integers(-6, 6), st.integers(-6, 6), st.integers(-20, 20))
def test_cells_are_sound(edges, op, lo, hi, quarter):
    edges, x = sorted(map(float, edges)), quarter / 4
    a = attributes.Attribute("a", "numeric", edges)
    if not edges[0] <= x <= edges[-1]:
        return
    cell = min(max(i for i, e in enumerate(edges) if e <= x), len(edges) - 2)
    state = predicates.cell_pass(predicates.Condition("a", op, lo, hi), a)[cell]
    true = {"<": x < lo, "<=": x <= lo, "=": x == lo, ">=": x >= lo, ">": x > lo, "between": lo <= x <= hi}[op]
    assert state == 2 or state == int(true)


def test_parse():
    assert predicates.parse("") == ()
    p = predicates.parse("a < 3 and b = 'x y' or c between 1 and 2")
    assert p == ((predicates.Condition("a", "<", 3.0), predicates.Condition("b", "=", "x y")), (predicates.Condition("c", "between", 1.0, 2.0),))
    with pytest.raises(ValueError):
        predicates.parse("a ! 3")


def test_bounds():
    edges = [np.array([0.0, 1.0, 2.0, 3.0])]
    codes = np.array([[0], [1], [2]])
    q = np.array([2.5])
    for got in (lowerbound.direct(codes, q, edges), lowerbound.by_table(codes, lowerbound.table(q, edges)), lowerbound.fused(codes, q, edges, [2])):
        assert got.tolist() == [1.5, 0.5, 0.0]


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 2**32), st.integers(2, 60), st.integers(1, 9))
def test_bounds_hold(seed, n, d):
    rng = np.random.default_rng(seed)
    x, q = rng.normal(size=(n, d)), rng.normal(size=d)
    plan = rng.integers(0, 5, d).tolist()
    edges = [quantizers.lloyd_edges(x[:, j], 1 << plan[j]) for j in range(d)]
    codes = np.stack([np.clip(np.searchsorted(e, x[:, j], "right") - 1, 0, len(e) - 2) for j, e in enumerate(edges)], 1)
    bound = lowerbound.direct(codes, q, edges)
    assert (bound <= np.sqrt(((x - q) ** 2).sum(1)) + 1e-9).all()
    assert np.allclose(bound, lowerbound.by_table(codes, lowerbound.table(q, edges)))
    assert np.allclose(bound, lowerbound.fused(codes, q, edges, plan, 6))


@given(st.lists(st.floats(-1e3, 1e3), min_size=1, max_size=80), st.integers(1, 16))
def test_lloyd_edges(values, cells):
    e = quantizers.lloyd_edges(np.array(values), cells)
    assert (np.diff(e) >= 0).all() and e[0] == min(values) and e[-1] == max(values) and len(e) <= cells + 1 + (cells == 1)


def test_hamming():
    a, b = np.packbits([[1, 0, 1, 1, 0]], axis=1), np.packbits([[0, 0, 1, 1, 1]], axis=1)
    assert lowbit.matrix_distances(a, b[0]).tolist() == [2]


def test_selection(spark):
    ranked = spark.createDataFrame([(1, p, r, p + 1, r) for p, r in enumerate((1.0, 1.1, 1.3, 1.5))], "query_id long, part_id int, dist double, rank int, ratio double")
    counts = spark.createDataFrame([(1, 2), (2, 4), (3, 9)], "part_id int, n_pass long")
    assert [r["part_id"] for r in select.reach(ranked, counts, 1.2, 5).orderBy("rank").collect()] == [1, 2]


def test_selection_equals_loop(spark):
    rng = np.random.default_rng(1)
    rows, counts, want = [], [], []
    for q in range(60):
        ratios = np.r_[1.0, np.sort(1 + rng.random(6))]
        n = rng.integers(0, 4, 7)
        found = 0
        for p, (r, c) in enumerate(zip(ratios, n)):
            rows.append((q, p, float(r), p + 1, float(r)))
            counts.append((q, p, int(c)))
        for p, (r, c) in enumerate(zip(ratios, n)):
            if r > 1.4 and found >= 5:
                break
            if c:
                want.append((q, p))
                found += c
        assert found >= min(5, n.sum())
    got = select.reach(spark.createDataFrame(rows, "query_id long, part_id int, dist double, rank int, ratio double"), spark.createDataFrame(counts, "query_id long, part_id int, n_pass long"), 1.4, 5)
    assert sorted((r["query_id"], r["part_id"]) for r in got.collect()) == want


@pytest.mark.parametrize("fan,depth,n", [(10, 1, 10), (4, 2, 20), (4, 3, 84), (5, 3, 155), (6, 3, 258), (4, 4, 340), (1, 3, 3), (2, 5, 62)])
def test_trees(spark, fan, depth, n):
    rows = dispatch.tree(spark, fan, depth).collect()
    assert sorted(r["node_id"] for r in rows) == list(range(n)) == list(range(dispatch.size(fan, depth)))
    by = {r["node_id"]: r for r in rows}
    for r in rows:
        if r["parent_id"] is not None:
            p = by[r["parent_id"]]
            assert p["level"] == r["level"] - 1 and p["subtree_lo"] < r["subtree_lo"] and r["subtree_hi"] <= p["subtree_hi"]
    if (fan, depth) == (4, 3):
        assert [r["node_id"] for r in rows if r["level"] == 1] == [0, 21, 42, 63] and sorted(r["node_id"] for r in rows if r["parent_id"] == 0) == [1, 6, 11, 16]


def test_cost(spark):
    log = [(1, "allocator", i, 1000.0, 3.0, 0, 0) for i in range(2)] + [(1, "processor", i, 1000.0, 2.0, 1, 2) for i in range(4)] + [(1, "coordinator", 0, 500.0, 5.0, 2, 2)]
    r = cost.total(spark.createDataFrame(log, cost.RUNLOG), cost.Prices(1e-4, 1e-6, 1e-3, 1e-6), 256).first()
    assert [r[c] for c in ("invocations", "run", "object_store", "file_read", "total")] == pytest.approx([7e-4, 1.65e-2, 6e-3, 2.56e-3, 2.576e-2])


def test_recall(spark):
    truth = spark.createDataFrame([(1, i, float(i)) for i in range(1, 11)], "query_id long, vec_id long, dist double")
    hits = spark.createDataFrame([(1, i, float(i)) for i in [*range(1, 10), 42]], "query_id long, vec_id long, dist double")
    assert measures.recall(hits, truth, 10).first()["recall"] == 0.9
    few = truth.where("vec_id <= 4")
    assert measures.recall(hits, few, 10).first()["recall"] == 1.0 and measures.recall(hits, few, 10, literal=True).first()["recall"] == 0.4


def test_interleaving():
    assert dispatch.interleaved([1, 2, 3], lambda b: b * 10, lambda b: b + 1) == [11, 21, 31] and dispatch.interleaved([], None, None) == []
