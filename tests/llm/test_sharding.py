"""Shards by the hash tree: proportions, growth and gapless slots."""

import math
import zlib
from collections import Counter

import xxhash

from packvec.llm import sharding

SCHEMA = "doc_id long, text string, shard string, _k int"


def chained(node, key):
    """Spark's hash of a long and a string: the first one's hash seeds the second's."""
    return xxhash.xxh64_intdigest(key.encode(), xxhash.xxh64_intdigest(node.to_bytes(8, "little", signed=True), 42))


def brute(key, tree, added):
    def time(node, w):
        return -math.log(((chained(node, key) >> 11) + 0.5) * 2.0**-53) / w

    leaves = tree.leaves()
    racks, fan = max(map(len, leaves)), max(len(y) for x in leaves for y in x)
    t, r = min((time(i, sum(w for y in x for _, w in y)), i) for i, x in enumerate(leaves))
    late = min([(time(3 * sharding.LEVEL + i, w), i) for i, w in enumerate(added)], default=(math.inf, 0))
    if late[0] < t:
        return tree.base + late[1]
    _, k = min((time(sharding.LEVEL + r * racks + j, sum(w for _, w in y)), j) for j, y in enumerate(leaves[r]))
    return min((time(2 * sharding.LEVEL + (r * racks + k) * fan + n, w), s) for n, (s, w) in enumerate(leaves[r][k]))[1]


def test_tree(spark):
    tree = sharding.tree_of(40)
    rows = [(i, f"t{i}", "x", 1) for i in range(3000)] + [(5, "t5", "x", 1), (5, "t5", "x", 1), (None, None, None, None), (None, "a", "b", 2)]
    got = sharding.assign(spark.createDataFrame(rows, SCHEMA), tree, grown="grown").collect()
    assert len(got) == len(rows)
    for r in got[::7]:
        key = "" if r["doc_id"] is None else str(r["doc_id"])
        assert r["shard"] == brute(key, tree, ()) and r["grown"] == brute(key, tree, (1.0,))
    assert all(r["grown"] in (r["shard"], 40) for r in got) and any(r["grown"] == 40 for r in got)
    slots = {}
    for r in got:
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    sizes = Counter(r["shard"] for r in got)
    assert set(sizes) == set(range(40)) and max(sizes.values()) < 2 * 75


def test_weights_and_odd_trees(spark):
    for tree in (sharding.tree_of(7), sharding.HashTree(((1, 3), (2,)), {0: 4.0}, (2.0,)), sharding.tree_of(1)):
        got = Counter(r["s"] for r in sharding.with_shard(spark.range(4000), "id", tree, "s").collect())
        weights = [tree.shard_weights.get(s, 1.0) for s in range(tree.base)] + list(tree.added)
        for s, w in enumerate(weights):
            assert abs(got[s] - 4000 * w / sum(weights)) < 5 * math.sqrt(4000 * w / sum(weights)) + 1


def test_empty(spark):
    assert sharding.assign(spark.createDataFrame([], SCHEMA), sharding.tree_of(4)).collect() == []


def test_query(spark, sf_dir):
    from packvec.llm.queries import op1_hash_tree_sharding

    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    got = op1_hash_tree_sharding(spark, sf_dir).collect()
    assert len(got) == len(texts)
    for r in got:
        raw = texts[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["law"]) == (len(raw) + 16, zlib.crc32(raw), "key")
