"""Dispatch, cost, reuse, measures, baselines and workloads as queries."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from packvec.functions import vectors as v
from packvec.plans import baselines, cost, dispatch, exact, index, measures, reuse, search, workloads
from packvec.plans.shared import ensure_checkpoint_dir, stored
from packvec.queries import QUERIES, SQL, query
from packvec.queries.methods import ALL, HAM, K, L2, PRED, PRED_SQL, SEARCH, E, bit_allocation, built, hamming_pairs, hybrid, knn_sql, pass_counts, ranked
from packvec.operators import select as sl
from packvec.sources import tables as tb

# Dispatch and cost


def tree_sql(fan: int, depth: int) -> str:
    below = [dispatch.size(fan, depth - level) + 1 for level in range(1, depth + 1)]
    return f"""WITH RECURSIVE b AS (SELECT {below!r} AS below), t AS (
SELECT i * {below[0]}::BIGINT AS node_id, NULL::BIGINT AS parent_id, 1 AS level FROM (SELECT unnest(range({fan})) AS i)
UNION ALL SELECT node_id + 1 + c * below[level + 1], node_id, level + 1 FROM t, b, (SELECT unnest(range({fan})) AS c) WHERE level < {depth})
SELECT node_id, parent_id, level, node_id AS subtree_lo, node_id + below[level] - 1 AS subtree_hi FROM t, b"""


def dealt_sql(fan: int, depth: int) -> str:
    """The tree with the number of orders that each node gets as queries, dealt by key."""
    n = f"SELECT o_orderkey % {dispatch.size(fan, depth)} AS node_id, count(*) AS n FROM orders GROUP BY 1"
    return f"SELECT node_id, parent_id, level, subtree_lo, subtree_hi, coalesce(n, 0)::BIGINT AS n_queries FROM ({tree_sql(fan, depth)}) LEFT JOIN ({n}) USING (node_id)"


def dealt_tree(spark, sf_dir, fan: int, depth: int):
    return dispatch.dealt(dispatch.tree(spark, fan, depth), tb.load(spark, sf_dir, "orders").select("o_orderkey"), dispatch.size(fan, depth))


def _tree(fan: int, depth: int):
    @query(dealt_sql(fan, depth), f"dispatch_tree_{fan}_{depth}")
    def run(spark, sf_dir):
        return dealt_tree(spark, sf_dir, fan, depth)


for _shape in ((10, 1), (4, 2), (4, 3), (5, 3), (6, 3), (4, 4), (1, 3)):
    _tree(*_shape)


@query("WITH a AS (SELECT ntile(84) OVER (ORDER BY o_orderkey) AS a FROM orders), n AS (SELECT count(*) AS n FROM a GROUP BY a) SELECT count(*) AS workers, min(n) AS least, max(n) AS most, round(avg(n), 4) AS mean FROM n")
def allocator_load(spark, sf_dir):
    queries = tb.load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("query_id"))
    return dispatch.load(dispatch.assign(queries, 84))


@query(f"""WITH t AS (SELECT * FROM ({dealt_sql(4, 3)}) WHERE n_queries > 0), r AS (SELECT coalesce(parent_id, -1) AS receiver, count(*) AS responses FROM t GROUP BY 1)
SELECT 'tree' AS mode, sum(responses)::BIGINT AS workers, max(responses) FILTER (receiver = -1) AS root_responses, max(responses) AS most_responses, (SELECT max(level) FROM t) AS depth FROM r
UNION ALL SELECT 'flat', count(*), count(*), count(*), 1 FROM t""")
def fan_in_report(spark, sf_dir):
    """Of the workers that get orders as queries."""
    return dispatch.fan_in_report(dealt_tree(spark, sf_dir, 4, 3).where("n_queries > 0"))


@query()
def role_assignment(spark, sf_dir):
    reached = sl.reach(ranked(spark, sf_dir), pass_counts(spark, sf_dir), 1.03, K)
    return dispatch.roles(reached, dispatch.assign(reached.select("query_id").distinct(), 10))


RUNLOG_SQL = """l AS (SELECT o_custkey AS run_id, 512.0::DOUBLE AS mem_mb, (o_orderkey % 7)::DOUBLE AS seconds, o_orderkey % 3 AS gets, o_orderkey % 11 AS full_reads FROM orders)"""


def runlog(spark, sf_dir):
    key = F.col("o_orderkey")
    return tb.load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("run_id"), F.lit("processor").alias("role"), key.alias("worker_id"), F.lit(512.0).alias("mem_mb"), (key % 7).cast("double").alias("seconds"), (key % 3).alias("gets"), (key % 11).alias("full_reads"))


@query(f"""WITH {RUNLOG_SQL}, s AS (SELECT run_id, round(count(*) * 2e-7::DOUBLE, 12) AS invocations, round(sum(mem_mb * seconds) * 1.6e-8::DOUBLE, 12) AS run, round(sum(gets)::DOUBLE * 4e-7::DOUBLE, 12) AS object_store, round(sum(full_reads)::DOUBLE * 256 * 3e-11::DOUBLE, 12) AS file_read FROM l GROUP BY run_id)
SELECT *, round(invocations + run + object_store + file_read, 12) AS total FROM s""")
def cost_model(spark, sf_dir):
    return cost.total(runlog(spark, sf_dir), cost.Prices(), 256)


VOLUMES_SQL = "v AS (SELECT date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS day, count(*) AS volume FROM orders GROUP BY 1)"


def volumes(spark, sf_dir):
    """Orders a day, as queries a day."""
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date"))
    return tb.load(spark, sf_dir, "orders").groupBy(day.alias("day")).agg(F.count(F.lit(1)).alias("volume"))


@query(f"""WITH {VOLUMES_SQL}
SELECT day, volume, 'packed' AS solution, round(volume * 1e-5::DOUBLE, 6) AS cost FROM v UNION ALL SELECT day, volume, 'managed service', round(volume * 4e-5::DOUBLE, 6) FROM v
UNION ALL SELECT day, volume, 'server small', 38.4::DOUBLE FROM v UNION ALL SELECT day, volume, 'server large', 144.0::DOUBLE FROM v""")
def daily_cost_curve(spark, sf_dir):
    return cost.daily(volumes(spark, sf_dir), {"packed": 1e-5, "managed service": 4e-5}, {"server small": 0.8, "server large": 3.0})


@query(f"""WITH {VOLUMES_SQL}, b AS (SELECT 'small' AS server, ceil(0.8::DOUBLE * 24 * 2 / 1e-5::DOUBLE)::BIGINT AS volume UNION ALL SELECT 'large', ceil(3.0::DOUBLE * 24 * 2 / 1e-5::DOUBLE)::BIGINT)
SELECT server, b.volume, count(*) AS days, count(*) FILTER (v.volume >= b.volume) AS days_above FROM b, v GROUP BY ALL""")
def break_even(spark, sf_dir):
    """The volume from which a server costs less, and on how many days the orders reach it."""
    each = volumes(spark, sf_dir).select(F.col("volume").alias("own")).crossJoin(F.broadcast(cost.break_even(spark, 1e-5, {"small": 0.8, "large": 3.0})))
    return each.groupBy("server", "volume").agg(F.count(F.lit(1)).alias("days"), F.count_if(F.col("own") >= F.col("volume")).alias("days_above"))


# Reuse


def _folder(spark, name: str) -> str:
    return f"{ensure_checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"


@query("SELECT 1::INT AS loads, 2::INT AS reuses")
def retention_report(spark, sf_dir):
    found, queries = built(spark, sf_dir, [])
    path, keep = _folder(spark, "index"), reuse.Retainer(spark)
    found.save(path)
    for _ in range(3):
        search.search(keep.get(path), queries, K).count()
    keep.release()
    return keep.report()


@query(knn_sql(L2))
def cached_search(spark, sf_dir):
    """Answers that are kept equal answers that are searched for."""
    found, queries = built(spark, sf_dir, [], index.Config(partitions=1, rounds=4))
    cache = reuse.ResultCache(spark, _folder(spark, "results"))
    run = lambda q: search.search(found, q, K, ALL)
    cache.search(queries.where("query_id % 20 = 0"), K, run)
    return cache.search(queries, K, run)


@query("WITH n AS (SELECT count(*) FILTER (vec_id % 10 = 0) AS q FROM embeddings) SELECT 4 * q AS requests, q AS searched, 3 * q AS kept FROM n")
def cache_duplication(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    cache = reuse.ResultCache(spark, _folder(spark, "results"))
    four = queries.select(F.col("query_id"), "qvec", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("c")).select((F.col("query_id") * 4 + F.col("c")).alias("query_id"), "qvec")
    cache.search(four, K, lambda q: exact.knn(q, base, K))
    return spark.createDataFrame([(cache.hits + cache.misses, cache.misses, cache.hits)], "requests long, searched long, kept long")


FACTORS = (1, 2, 4, 8, 10)


def duplicated(queries, factor: int):
    """Each query so many times, with ids of its own."""
    copies = queries.select("query_id", "qvec", F.explode(F.sequence(F.lit(0), F.lit(factor - 1))).alias("c"))
    return copies.select((F.col("query_id") * factor + F.col("c")).alias("query_id"), "qvec")


@query(f"WITH n AS (SELECT count(*) FILTER (vec_id % 10 = 0) AS q FROM embeddings), f AS (SELECT unnest({list(FACTORS)!r})::INT AS factor) SELECT factor, factor * q AS requests, q AS searched, (factor - 1) * q AS kept FROM f, n")
def cache_duplication_sweep(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    base, rows = stored(base.select("vec_id", "embedding"), "base"), []
    for factor in FACTORS:
        cache = reuse.ResultCache(spark, _folder(spark, "results"))
        cache.search(duplicated(queries, factor), K, lambda q: exact.knn(q, base, K))
        rows.append((factor, cache.hits + cache.misses, cache.misses, cache.hits))
    return spark.createDataFrame(rows, "factor int, requests long, searched long, kept long")


@query()
def cache_ratio(spark, sf_dir):
    """Seconds of an unfiltered scan with kept results by duplication, and the least one that beats the packed search's throughput."""
    found, queries = built(spark, sf_dir, [])
    base = stored(hybrid(spark, sf_dir)[0].select("vec_id", "embedding"), "base")
    n = queries.count()
    qps = n / measures.timed(lambda: search.search(found, queries, K), 1)
    run = lambda f: reuse.ResultCache(spark, _folder(spark, "results")).search(duplicated(queries, f), K, lambda q: exact.knn(q, base, K))
    seconds = {f: measures.timed(lambda: run(f), 1) for f in FACTORS}
    least = min((f for f in FACTORS if measures.cache_ratio_to_beat({f: seconds[f]}, n * f, qps)), default=None)
    return spark.createDataFrame([(f, n * f, s, n * f / s, qps, least) for f, s in seconds.items()], "factor int, requests long, seconds double, qps double, packed_qps double, least_factor int")


# Baselines


@query(knn_sql(L2, PRED_SQL))
def managed_service(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    service = baselines.ManagedService()
    records = service.to_records(base, ["totalprice", "priority", "status"])
    service.upsert(records.where("id % 3 = 0"))
    service.upsert(records)
    return service.query(queries, K, "totalprice double, priority string, status string", "totalprice BETWEEN 100000 AND 400000 AND priority <= '2-HIGH' AND status <> 'P'")


@query(knn_sql(L2))
def variable_bits_file(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    return baselines.variable_bits_file(base, queries, K)


@query(knn_sql(L2, PRED_SQL))
def pre_filter(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    return baselines.pre_filter(base, queries, K, "totalprice BETWEEN 100000 AND 400000 AND priority <= '2-HIGH' AND status <> 'P'")


@query(knn_sql(L2, PRED_SQL))
def post_filter(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    hits, _ = baselines.post_filter(base, queries, K, "totalprice BETWEEN 100000 AND 400000 AND priority <= '2-HIGH' AND status <> 'P'", lambda q, n: exact.knn(q, base, n), growth=4)
    return hits


@query()
def uniform_cells(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    return baselines.uniform_cells(base, queries, K)


@query()
def product_quantization(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    return baselines.product_search(base, queries, K, rerank=10)


@query(knn_sql(L2))
def product_quantization_full_rerank(spark, sf_dir):
    """With a shortlist of all rows the exact answer comes out."""
    base, queries = hybrid(spark, sf_dir)
    return baselines.product_search(base, queries, K, rerank=10_000)


def _graph(name: str, **how):
    @query(name=name)
    def run(spark, sf_dir):
        base, queries = hybrid(spark, sf_dir)
        return baselines.graph(base, queries, K, **how)


_graph("graph_search")
_graph("graph_filter_after", predicate="totalprice > 100000", filter="post")
_graph("graph_filter_during", predicate="totalprice > 100000", filter="during", expand=1.5)
_graph("graph_scalar_codes", codes="sq")
_graph("graph_product_codes", codes="pq")
_graph("graph_by_range", predicate="totalprice BETWEEN 100000 AND 200000", filter="during", range_attr="totalprice")


@query()
def cached_unfiltered(spark, sf_dir):
    found, queries = built(spark, sf_dir, [], SEARCH)
    return baselines.cached_unfiltered(found, queries, K, _folder(spark, "results"))


@query()
def single_node(spark, sf_dir):
    found, queries = built(spark, sf_dir)
    return baselines.single_node(found, queries.withColumn("pred", F.lit(PRED)), K, 4)


@query(knn_sql(L2))
def via_storage(spark, sf_dir):
    found, queries = built(spark, sf_dir, [], index.Config(partitions=2, rounds=4))
    return baselines.via_storage(found, queries, K, search.Plan(hperc=100, policy="all", rerank=50))


# Measures and workloads


@query(f"WITH {E}, t AS (SELECT q.vec_id AS query_id, b.vec_id, round({L2}, 9) AS dist FROM e q, e b WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 <> 0), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS rank FROM t), k AS (SELECT * FROM r WHERE rank <= 20 AND dist > 0), m AS (SELECT query_id, avg(ln(dist / far)) AS m FROM (SELECT *, max(dist) OVER (PARTITION BY query_id) AS far FROM k) GROUP BY query_id) SELECT round(avg(-1 / m), 4) AS lid FROM m WHERE m < 0")
def intrinsic_dimension(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    return measures.lid(exact.knn(queries, base, 20))


@query("SELECT 0.5::DOUBLE AS recall")
def recall_measure(spark, sf_dir):
    """Half of each query's neighbours are found by a search that leaves every second rank out."""
    base, queries = hybrid(spark, sf_dir)
    truth = stored(exact.knn(queries, base, K), "truth")
    return measures.recall(truth.where("rank % 2 = 0"), truth, K)


@query("WITH n AS (SELECT count(*) AS n FROM embeddings GROUP BY label) SELECT count(*) AS groups, round(avg(n), 4) AS mean, round(max(n) / avg(n), 6) AS most_over_mean, round(min(n) / avg(n), 6) AS least_over_mean FROM n")
def partition_balance(spark, sf_dir):
    return measures.balance(tb.embeddings(spark, sf_dir), "label")


@query()
def suitability_report(spark, sf_dir):
    return workloads.suitability(spark, sf_dir)


@query()
def recall_by_pruning(spark, sf_dir):
    return workloads.recall_by_pruning(spark, sf_dir)


@query()
def calibration(spark, sf_dir):
    base, queries = hybrid(spark, sf_dir)
    found = index.build(base, [], index.Config(partitions=1))
    return workloads.calibrate(found, queries, exact.knn(queries, base, K), K, 0.97)


@query()
def selectivity_sweep(spark, sf_dir):
    return workloads.selectivity_sweep(spark, sf_dir)


@query("""WITH u AS (SELECT vec_id, unnest(range(4)) AS j FROM embeddings), x AS (SELECT vec_id, j, (('0x' || substring(md5(vec_id || '-' || j), 1, 7))::BIGINT % 10000) / 10000.0 AS u FROM u),
p AS (SELECT vec_id, bool_and(u < 0.532) AS ok FROM x GROUP BY vec_id) SELECT count(*) FILTER (ok) AS n_pass, count(*) AS n_rows, round(count(*) FILTER (ok) / count(*), 6) AS share FROM p""")
def uniform_attributes(spark, sf_dir):
    df = tb.uniform_attributes(tb.embeddings(spark, sf_dir))
    return measures.selectivity(df, F.expr(" AND ".join(f"u{j} < 0.532" for j in range(4))))


@query("""WITH t AS (SELECT doc_id AS vec_id, unnest(list_filter(regexp_split_to_array(lower(text), '[\\s.,;:!?]+'), lambda w: w <> '')) AS w FROM documents),
h AS (SELECT vec_id, ('0x' || substring(md5(w), 1, 7))::BIGINT % 64 AS b, CASE WHEN ('0x' || substring(md5(w), 8, 1))::INT % 2 = 0 THEN 1 ELSE -1 END AS s FROM t),
c AS (SELECT vec_id, b, sum(s)::DOUBLE AS n FROM h GROUP BY ALL), z AS (SELECT vec_id, sqrt(sum(n * n)) AS z FROM c GROUP BY vec_id)
SELECT vec_id, b::INT AS dim, round(n / z, 9) AS x FROM c JOIN z USING (vec_id) WHERE n <> 0""")
def document_vectors(spark, sf_dir):
    docs = v.text_vectors(tb.load(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text"), "vec_id", "text", 64, "e")
    return docs.select("vec_id", F.posexplode("e").alias("dim", "x")).where("x <> 0").withColumn("x", F.round("x", 9))


@query()
def line_search(spark, sf_dir):
    """Bounds-only search of six-dimensional lines: the size test."""
    rows = stored(tb.lineitem_vl(spark, sf_dir), "lines")  # the build reads them many times
    queries = rows.where("vec_id % 997 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    found = index.build(rows.where("vec_id % 997 <> 0"), ["l_returnflag", "l_quantity"], index.Config(partitions=4, bits=6, balanced=False))
    return search.search(found, queries.withColumn("pred", F.lit("l_returnflag = 'A' AND l_quantity < 25")), K)


@query()
def allocator_sweep(spark, sf_dir):
    return workloads.allocator_sweep(spark, sl.reach(ranked(spark, sf_dir), pass_counts(spark, sf_dir), 1.03, K))


@query()
def dataset_profile(spark, sf_dir):
    return workloads.dataset_profile(spark, sf_dir)


def _ablation(name: str):
    @query(name=f"without_{name.replace(' ', '_').replace('-', '_')}")
    def run(spark, sf_dir):
        base, queries = hybrid(spark, sf_dir)
        return baselines.ablated(base, queries, K, name, index.Config(partitions=2, rounds=4))


for _name in baselines.ABLATIONS:
    if _name != "none":
        _ablation(_name)


@query(knn_sql(L2, PRED_SQL))
def appended_index(spark, sf_dir):
    """An index that got half of its rows later answers exactly too."""
    base, queries = hybrid(spark, sf_dir)
    half = index.build(base.where("vec_id % 2 = 1"), ["totalprice", "priority", "status"], index.Config(partitions=2, rounds=4))
    whole = index.append(half, base.where("vec_id % 2 = 0"))
    return search.search(whole, queries.withColumn("pred", F.lit(PRED)), K, ALL)


RANKS = "rank() OVER (PARTITION BY query_id ORDER BY {0}) + (count(*) OVER (PARTITION BY query_id, {0}) - 1) / 2.0"


@query(f"""WITH {HAM}, d AS (SELECT q.vec_id AS query_id, b.vec_id, {L2} AS dist FROM e q, e b WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 <> 0),
r AS (SELECT query_id, ham, dist, {RANKS.format('ham')} AS rh, {RANKS.format('dist')} AS rd FROM ham JOIN d USING (query_id, vec_id))
SELECT query_id, round(corr(ham, dist), 4) AS pearson, round(corr(rh, rd), 4) AS spearman FROM r GROUP BY query_id""")
def hamming_correlation(spark, sf_dir):
    """How well distances of one-bit codes rank a query's rows by Euclidean distance."""
    rows = tb.embeddings(spark, sf_dir)
    ham = hamming_pairs(spark, sf_dir).join(rows.select("vec_id", "embedding"), "vec_id").join(rows.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec")), "query_id")
    pairs = ham.select("query_id", "ham", v.l2(F.col("qvec"), F.col("embedding")).alias("dist"))
    return measures.rank_correlation(pairs, "ham", "dist").select("query_id", F.round("pearson", 4).alias("pearson"), F.round("spearman", 4).alias("spearman"))


@query(f"""WITH a AS ({SQL['bit_allocation']}), n AS (SELECT count(*) * 1000 AS direct, (sum(cells) - 1)::BIGINT AS "table" FROM a) SELECT direct, "table", round(direct / "table", 6) AS ratio FROM n""")
def lookup_savings(spark, sf_dir):
    return measures.lookup_savings(bit_allocation(spark, sf_dir), 1000)


@query(f"WITH {RUNLOG_SQL} SELECT run_id, sum(gets)::BIGINT AS gets, count(*) FILTER (gets = 0) AS loads_avoided, sum(full_reads)::BIGINT AS full_reads, (sum(full_reads) * 256)::BIGINT AS full_bytes FROM l GROUP BY run_id")
def io_measure(spark, sf_dir):
    return measures.io(runlog(spark, sf_dir), 256)


@query(f"WITH s AS ({SQL['reach_threshold']}), n AS (SELECT query_id, count(*) AS n FROM s GROUP BY query_id) SELECT count(*) AS queries, round(avg(n), 6) AS mean_partitions, max(n) AS most_partitions FROM n")
def partitions_visited(spark, sf_dir):
    return measures.visited(QUERIES["reach_threshold"](spark, sf_dir))


def _partitions(n: int):
    @query(knn_sql(L2, PRED_SQL), f"search_{n}_partitions")
    def run(spark, sf_dir):
        found, queries = built(spark, sf_dir, ["totalprice", "priority", "status"], index.Config(partitions=n, rounds=4, balanced=False))
        return search.search(found, queries.withColumn("pred", F.lit(PRED)), K, ALL)


for _n in (10, 20):
    _partitions(_n)


@query(knn_sql(L2))
def interleaved_search(spark, sf_dir):
    """Two batches: the second is prepared while the first is searched; the answers are those of one batch."""
    found, queries = built(spark, sf_dir, [], index.Config(partitions=2, rounds=4))
    half = F.pmod(F.xxhash64("query_id"), F.lit(2))
    answers = dispatch.interleaved([0, 1], lambda i: stored(queries.where(half == i), "batch"), lambda q: search.search(found, q, K, ALL))
    return answers[0].unionByName(answers[1])


@query()
def throughput_by_solution(spark, sf_dir):
    """All queries in one batch, mean of three runs, by solution: seconds, queries a second and recall."""
    found, queries = built(spark, sf_dir, [])
    base, _ = hybrid(spark, sf_dir)
    service = baselines.ManagedService()
    service.upsert(service.to_records(base, ["label"]))
    truth = stored(exact.knn(queries, base, K), "truth")
    solutions = {
        "packed": lambda: search.search(found, queries, K),
        "packed, no pruning": lambda: search.search(found, queries, K, search.Plan(hperc=100, policy="all")),
        "one machine": lambda: baselines.single_node(found, queries, K, 4),
        "managed service": lambda: service.query(queries, K, "label string"),
        "product codes": lambda: baselines.product_search(base, queries, K, rerank=10),
        "exact scan": lambda: exact.knn(queries, base, K),
    }
    n, rows = queries.count(), []
    for name, run in solutions.items():
        seconds = measures.timed(run)
        rows.append((name, n, seconds, n / seconds, measures.recall(run(), truth, K).first()["recall"]))
    return spark.createDataFrame(rows, "solution string, queries long, seconds double, qps double, recall double")
