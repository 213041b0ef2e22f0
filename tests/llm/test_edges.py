"""Long texts, ties and cases that a classifier, a plain dictionary or one hash alone would get wrong."""

import math
import random
import time

import numpy as np

from packvec.llm import html_extract, jaccard_join, secret_scan, topk_search, url_filter
from tests.llm import brute


def test_signatures_lose_no_pair():
    """Pairs at the bound, of all sizes: both members share a signature."""
    rng = np.random.default_rng(11)
    for num in (80, 85):
        for size in [*range(4, 120, 3), 200, 333, 500, 900]:
            for larger in {size, size * 100 // num, (size + size * 100 // num) // 2}:
                common = -(-num * (size + larger) // (100 + num))
                if common > size or common == larger:
                    continue
                grams = rng.integers(1, 2**63, size + larger - common, dtype=np.uint64)
                one, two = np.sort(grams[:size]), np.sort(grams[size - common :])
                own, sig = jaccard_join.signatures(np.concatenate([one, two]), np.array([0, len(one), len(one) + len(two)]), num)
                assert set(sig[own == 0].tolist()) & set(sig[own == 1].tolist()), (num, size, larger)


def test_sets_without_grams_in_many_subsets():
    """Sets that lack a subset of more blocks than are spare give choices of these; linked ones still share a signature."""
    rng = np.random.default_rng(5)
    for num, size in ((80, 100), (85, 130), (80, 700)):
        family = next(i for i, (low, top, k) in enumerate(jaccard_join.families(num, size)) if low <= size <= top)
        low, _, k = jaccard_join.families(num, size)[family]
        blocks, parts, _, spare = jaccard_join.scheme(k, low)
        salt = np.uint64((family + 1) * 0x9E3779B97F4A7C15 % 2**64)
        pool = rng.integers(1, 2**63, 400_000, dtype=np.uint64)
        cell = (jaccard_join.K.mix(pool ^ salt) >> np.uint64(33)).astype(np.int64) % (blocks * parts)
        pool = pool[(cell // parts > spare + 1) | (cell % parts == parts - 1)]
        common = -(-num * 2 * size // (100 + num))
        one, two = np.sort(pool[:size]), np.sort(pool[size - common : 2 * size - common])
        own, sig = jaccard_join.signatures(np.concatenate([one, two]), np.array([0, size, 2 * size]), num)
        assert set(sig[own == 0].tolist()) & set(sig[own == 1].tolist())


def test_sketches_bound_the_difference():
    rng = np.random.default_rng(2)
    for size in (1, 40, 300, 1500):
        grams = rng.integers(1, 2**63, 2 * size, dtype=np.uint64)
        one, two = np.unique(grams[: size + size // 2]), np.unique(grams[size // 2 :])
        a, b = (jaccard_join._folded_list([x], 64)[0] for x in jaccard_join.sketches(np.concatenate([one, two]), np.array([0, len(one), len(one) + len(two)])))
        assert jaccard_join._apart(a, b) <= len(np.setxor1d(one, two))


DOCS = "doc_id long, text string"


def test_first_names_may_clash(spark, monkeypatch):
    """Different sets with one first name are told apart."""
    real = jaccard_join.first_names
    monkeypatch.setattr(jaccard_join, "first_names", lambda g, b, salt=0: real(g, b, salt) if salt else np.minimum(real(g, b), np.uint64(1)))
    rows = [(i, " ".join(f"w{i // 2}x{j}" for j in range(30 + i % 2))) for i in range(8)]
    names = [jaccard_join.set_names(*_grams(t), frozenset({1}))[0] for _, t in rows]
    assert len(set(names)) == 8


def _grams(text):
    data = np.frombuffer(text.encode(), np.uint8)
    s, e, firsts = jaccard_join.K.words(data, np.array([0, len(data)]))
    return jaccard_join.gram_sets(jaccard_join.K.word_hashes(data, s, e, True), firsts, 4)


def test_crowds(spark, monkeypatch):
    """Near copies around a common text, in crowds and blocks of a few sets, with a passage that strangers share, and many exact copies."""
    for name, value in (("BLOCK", 8), ("FEW", 3), ("SENT", 2), ("HELD", 200), ("GATHERED", 2_000)):
        monkeypatch.setattr(jaccard_join, name, value)
    rnd = random.Random(3)
    base = [f"b{i}" for i in range(60)]
    texts = []
    for i in range(40):
        own = list(base)
        for _ in range(rnd.randrange(1, 4)):
            own[rnd.randrange(60)] = f"n{rnd.randrange(10**6)}"
        texts.append(" ".join(own))
    passage = " ".join(f"p{i}" for i in range(50))
    texts += [f"{passage} " + " ".join(f"t{i}x{j}" for j in range(rnd.choice((3, 6, 60)))) for i in range(30)]
    texts += [texts[0]] * 300
    rows = list(enumerate(texts))
    got = jaccard_join.near_duplicates(spark.createDataFrame(rows, DOCS).repartition(6), n=4, num=85).select("id", "n_shingles", "component").collect()
    want = brute.components(rows[:70], 4, 85)
    assert sorted(map(tuple, got)) == sorted(want + [(i, *want[0][1:]) for i in range(70, 370)])


def plain_cost(value):
    """All ways to cut a value into segments, each at its least cost."""
    low, each = value.lower(), math.log10(secret_scan.alphabet(value))
    plain = low.translate(secret_scan.LEET)
    costs = {}

    def put(i, j, c):
        costs[i, j] = min(c, costs.get((i, j), math.inf))

    for i in range(len(value)):
        put(i, i + 1, each)
        for j in range(i + 1, len(value) + 1):
            part = value[i:j]
            rank = secret_scan.RANKS.get(low[i:j]) or secret_scan.RANKS.get(plain[i:j])
            if rank and j - i >= 3:
                put(i, j, 0.3 + math.log10(rank + 1) + 0.3 * sum(a != b for a, b in zip(part, plain[i:j])))
            for unit in range(1, min(8, len(part) // 2) + 1):
                times = len(part) // unit
                if part == part[:unit] * times and len(part) >= 3 and not (j + unit <= len(value) and value[j : j + unit] == part[:unit]):
                    put(i, j, 0.3 + unit * each + math.log10(times))
            if j - i >= 3 and all(a + b in secret_scan.NEXT for a, b in zip(low[i:j], low[i + 1 : j])) and not (j < len(value) and low[j - 1] + low[j] in secret_scan.NEXT):
                put(i, j, 0.3 + math.log10(len(secret_scan.ROWS) * 20 * (j - i)))
        if m := secret_scan.DATE.match(value, i):
            put(i, m.end(), 0.3 + math.log10(365 * 60))
    best = [0.0] + [math.inf] * len(value)
    for j in range(1, len(value) + 1):
        best[j] = min(best[i] + c for (i, k), c in costs.items() if k == j)
    return best[-1]


def test_guess_cost_against_all_cuts():
    rnd = random.Random(4)
    parts = ["password", "P4ss", "2019-12-24", "qwert", "aaaa", "abab", "xyzxyzxyz", "monkey", "Zq8#", "7", "k!", "lkjh"]
    for _ in range(300):
        value = "".join(rnd.choice(parts) for _ in range(rnd.randrange(1, 5)))
        assert abs(secret_scan.guess_cost(value) - plain_cost(value)) < 1e-9, value


def test_long_values_and_pages():
    start = time.time()
    assert secret_scan.guess_cost("a" * 50_000) < 8 and secret_scan.guess_cost("qw" * 25_000) < 8
    for page in ("<a " * 50_000, "<div>" * 10_000 + "x", "<div>x" * 10_000, "<!" * 50_000, "<div>" * 10_000 + "</p>" * 10_000):
        html_extract.main_text(page)
    assert secret_scan.spans_of("passphrase is " + "kqzvtwhxyjbn" * 1 + " then")[0][0] == "guess"
    assert time.time() - start < 30


def test_cut_corrects_the_classifier():
    """A short line and a row of signs between paragraphs look like boilerplate, and are kept for their neighbours' sake."""
    long = "<p>A long paragraph of the piece, which says a lot of things about it.</p>"
    page = f'<div><div><a href="/">Home</a></div><div><a href="/n">News</a></div></div><div>{long}<p>* * *</p>{long}</div><div><div><a href="/i">Imprint</a></div></div>'
    blocks = html_extract.Page(page).blocks
    alone = [g > 0 for g in html_extract.gains(blocks, html_extract.WEIGHTS)]
    kept = html_extract.minimum_cut(html_extract.gains(blocks, html_extract.WEIGHTS), html_extract.ties_of(blocks))
    assert [b.text for b, x, y in zip(blocks, alone, kept) if x != y] == ["* * *"]
    assert html_extract.main_text(page).count("\n") == 2 and "Imprint" not in html_extract.main_text(page)


def test_attributes_are_read_as_such():
    page = '<div class="overflow-hidden"><article><p>Words about <a href="/the/hidden/valley">the valley page</a> are here.</p><p data-state="not hidden">More words are here.</p><div class="article-header"><h1>The Title</h1></div><p hidden>no</p><p style="color:red; display: none">no</p><p aria-hidden="true">no</p></article></div>'
    assert html_extract.main_text(page) == "Words about the valley page are here.\nMore words are here.\nThe Title"


def test_ties_of_large_scores(spark):
    scores, ids = topk_search.best_of(np.full((2, 100), 2.0**50), np.arange(100)[::-1].copy(), 5)
    assert sorted(ids[0].tolist()) == [0, 1, 2, 3, 4] and scores.shape == (2, 5)


def test_empty_tables(spark):
    from packvec.llm import toxicity

    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert topk_search.search(vectors, vectors).collect() == []
    assert secret_scan.scan(spark.createDataFrame([], DOCS)).collect() == []
    assert html_extract.extract(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []
    assert url_filter.judge(spark.createDataFrame([], "page_id long, url string"), ()).collect() == []
    docs = spark.createDataFrame([], DOCS)
    assert toxicity.scored(docs, toxicity.learn(docs, spark.createDataFrame([], "doc_id long, toxic int"))).collect() == []
