"""Jaccard join and substring removal against brute force."""

import random

import pytest

from packvec.llm import jaccard_join, substring_dedup
from packvec.llm.components import components
from tests.llm import brute

SCHEMA = "doc_id long, text string, source string, key long, places string"


def corpus(seed, sizes, copies=6):
    rnd = random.Random(seed)
    pool = [f"{a}{b}" for a in "ab Cd é f-g h".split() for b in range(30)]
    base = [" ".join(rnd.choice(pool) for _ in range(rnd.choice(sizes))) for _ in range(25)]
    texts = list(base)
    for b in base:
        for _ in range(rnd.randrange(copies)):
            share = rnd.choice([0, 0.004, 0.01, 0.03])
            texts.append(" ".join(w if rnd.random() > share else f"new{rnd.randrange(10**6)}" for w in b.split()))
    texts += [None, "", " \n\t ", "one", "one", "One two", "a b c", "x y z w v u", base[0].replace(" ", "\n"), "w " * 300]
    passage = " ".join(rnd.choice(pool) for _ in range(60))
    texts += [f"{t} {passage} tail{i}" for i, t in enumerate(base[:12])]
    rnd.shuffle(texts)
    rows = [(i, t, "s", 1, "p") for i, t in enumerate(texts)]
    return rows + [rows[3], rows[5], (None, texts[7], "s", 1, "p")]


@pytest.mark.parametrize("n,num", [(4, 85), (5, 80)])
def test_jaccard_components(spark, n, num):
    rows = corpus(n, [3, 8, 9, 12, 15, 20, 40, 80, 200])
    got = jaccard_join.near_duplicates(spark.createDataFrame(rows, SCHEMA).repartition(5), n=n, num=num).collect()
    want = brute.components([(r[0], r[1]) for r in rows], n, num)
    assert sorted((str(r["id"]), r["n_shingles"], str(r["component"])) for r in got) == sorted((str(a), b, str(c)) for a, b, c in want)


def test_jaccard_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "BLOCK", 4)
    rows = corpus(9, [40, 80], 30)
    got = jaccard_join.near_duplicates(spark.createDataFrame(rows, SCHEMA), n=4, num=85).collect()
    want = brute.components([(r[0], r[1]) for r in rows], 4, 85)
    assert sorted((str(r["id"]), str(r["component"])) for r in got) == sorted((str(a), str(c)) for a, _, c in want)


def test_jaccard_empty(spark):
    assert jaccard_join.near_duplicates(spark.createDataFrame([], SCHEMA)).collect() == []


def test_components_chain(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, 103), (103, 101), (7, 7)]
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(61)}, 100: 100, 101: 100, 103: 100}


@pytest.mark.parametrize("held", [1, 7, 500_000])
def test_components_of_any_shape(spark, held):
    draw = random.Random(held)
    edges = [(draw.randrange(120), draw.randrange(120)) for _ in range(90)] + [(500, 500)] + [(1000, 1000 + i) for i in range(60)]
    up = {}
    for a, b in edges:
        while up.get(a, a) != a:
            a = up[a]
        while up.get(b, b) != b:
            b = up[b]
        up[max(a, b)] = min(a, b)
    want = {}
    for n in {x for a, b in edges for x in (a, b) if a != b}:
        r = n
        while up.get(r, r) != r:
            r = up[r]
        want[n] = r
    found = components(spark.createDataFrame(edges, "a long, b long").repartition(3), held=held).collect()
    assert len(found) == len(want) and {r["node"]: r["root"] for r in found} == want


@pytest.mark.parametrize("heavy", [2_000, 1])
def test_substring_removal(spark, heavy):
    rows = corpus(4, [10, 36, 60, 120, 400])
    got = substring_dedup.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5), heavy=heavy, whole=True).collect()
    want = brute.dedup([(r[0], r[1]) for r in rows], 35)
    assert sorted((str(r["doc_id"]), r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got) == sorted((str(a), b, c, d) for a, b, c, d in want)
    assert sum(c for _, _, c, _ in want) > 0


@pytest.mark.parametrize("heavy", [2_000, 1])
def test_substring_repeats_inside_one_place(spark, heavy):
    """Lines of up to 28 words in a row, whose windows all share a minimiser: one place, under LONGEST windows."""
    texts = []
    for period in (1, 2, 10, 27, 28):
        for n in (34, 35, period + 34, period + 35, 60, 290):
            line = [f"p{period}n{n}w{i}" for i in range(period)]
            texts.append(" ".join((line * (n // period + 1))[:n]))
            texts.append(" ".join([f"head{period}-{n}-{i}" for i in range(40)] + (line * (n // period + 1))[:n] + [f"tail{period}-{n}-{i}" for i in range(40)]))
    texts.append(" ".join(f"ten{i % 10}" for i in range(60)))
    rows = [(i, t, "s", 1, "p") for i, t in enumerate(texts)]
    got = substring_dedup.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5), heavy=heavy).collect()
    want = brute.dedup([(r[0], r[1]) for r in rows], 35)
    assert sorted(map(tuple, got)) == sorted(want)
    assert want[-1][2] == 60


def test_substring_empty(spark):
    assert substring_dedup.remove_repeats(spark.createDataFrame([], SCHEMA)).collect() == []


def test_twins_across_batches():
    import pyarrow as pa

    def rows(h, first):
        n = len(h)
        schema = pa.schema([pa.field(c, t, nullable=False) for c, t in (("mini", pa.int64()), ("key", pa.int64()), ("start", pa.int32()), ("n", pa.int32()))])
        return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(range(first, first + n), pa.int64()), pa.array([0] * n, pa.int32()), pa.array([1] * n, pa.int32())], schema=schema)

    h = [1, 2, 2, 3, 4, 4, 4, 4, 5, 6, 6, 7]
    for cut in range(1, 12):
        for size in (1, 2, 5):
            batches = [rows(h[:cut], 0)] + [rows(h[i : i + size], i) for i in range(cut, 12, size)]
            out = list(substring_dedup.twins(iter(batches)))
            assert len({b.schema for b in out}) == 1
            found = [k for b in out for k in b.column(1).to_pylist()]
            assert found == [1, 2, 4, 5, 6, 7, 9, 10]


def test_windows_whose_hashes_clash(monkeypatch):
    real = substring_dedup.K.gram_hashes
    monkeypatch.setattr(substring_dedup.K, "gram_hashes", lambda h, n: real(h, n) % substring_dedup.np.uint64(3))
    rnd = random.Random(5)
    lines = [[rnd.choice("abc") for _ in range(9)] for _ in range(40)]
    keys, starts, counts = (substring_dedup.np.array(x) for x in (range(40), [0] * 40, [6] * 40))
    got = substring_dedup.repeated_windows(keys, starts, counts, [" ".join(x).encode() for x in lines], 4)
    seen = {}
    for k, x in enumerate(lines):
        for i in range(6):
            seen.setdefault(tuple(x[i : i + 4]), []).append((k, i))
    assert sorted(zip(*map(list, got))) == sorted(p for v in seen.values() if len(v) > 1 for p in v)
