"""Each stage of the pipeline on its own input, against plain versions."""

from collections import Counter

import corpus_pipeline
from packvec.llm import toxicity
from packvec.llm.common import table, written
from tests.llm import brute


def test_stages(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").withColumnRenamed("lang", "key").unionByName(spark.createDataFrame([(None, None, "en", None, None), (3, "", "en", "src0", 0)], "doc_id long, text string, key string, source string, n_chars long"))
    docs = written(docs.unionByName(docs.where("doc_id < 5")), "docs")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["toxicity", "near duplicates", "decontamination", "mixing", "sharding"]
    same = lambda df: Counter((r["doc_id"], r["text"]) for r in df.collect())

    kept = written(stages["toxicity"](spark, docs, sf_dir), "s1")
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    assert kept.columns == docs.columns and same(kept) == Counter({(r["doc_id"], r["text"]): n for r, n in Counter(docs.select("doc_id", "text").collect()).items() if model.score(r["text"]) < corpus_pipeline.TOXIC_FROM})

    own = [(r["doc_id"], r["text"]) for r in kept.collect()]
    once = written(stages["near duplicates"](spark, kept, sf_dir), "s2")
    found = brute.components(own, 5, 80)
    want = Counter((d, t) for (d, t), (_, n, c) in zip(own, found) if n == 0) + Counter({(d, t) for (d, t), (_, n, c) in zip(own, found) if n and d == c})
    assert once.columns == docs.columns and same(once) == want

    own = [(r["doc_id"], r["text"]) for r in once.collect()]
    clean = written(stages["decontamination"](spark, once, sf_dir), "s3")
    judged = brute.contamination(own, [(r["item_id"], r["text"]) for r in table(spark, sf_dir, "benchmark").collect()])
    assert same(clean) == Counter(x for x, j in zip(own, judged) if not j[-1])

    mixed = written(stages["mixing"](spark, clean, sf_dir), "s4")
    assert mixed.columns == docs.columns
    before, after = same(clean), same(mixed)
    assert set(after) <= set(before) and all(n <= 2 * before[x] for x, n in after.items())
    words = lambda c: sum(len(brute.words(t)) * n for (_, t), n in c.items())
    assert abs(words(after) - 1.5 * words(before)) < 0.1 * words(before)

    sharded = stages["sharding"](spark, mixed, sf_dir).collect()
    assert len(sharded) == sum(after.values()) and {r["shard"] for r in sharded} <= set(range(corpus_pipeline.SHARDS))
    slots: dict[int, list[int]] = {}
    for r in sharded:
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
