"""Surrounding operators: scans, joins, aggregates, windows, sets, functions and batch twins of the streams."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from packvec.functions import vectors as v
from packvec.plans import tiles
from packvec.plans.shared import ensure_checkpoint_dir
from packvec.queries import query
from packvec.sources.tables import base_and_queries, load


def scratch(spark, name: str) -> str:
    return f"{ensure_checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"


# Scans and projections


@query("SELECT vec_id, label FROM embeddings WHERE label >= 5")
def scan_parquet(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").where("label >= 5").select("vec_id", "label")


def _round_trip(kind: str):
    @query("SELECT o_orderkey, o_orderstatus, o_orderpriority FROM orders", f"scan_{kind}")
    def run(spark, sf_dir):
        df = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority")
        path = scratch(spark, kind)
        df.write.format(kind).save(path)
        return spark.read.format(kind).schema(df.schema).load(path)


for _kind in ("csv", "json", "orc"):
    _round_trip(_kind)


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 9) AS n FROM embeddings")
def project_vector_norm(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(v.norm(F.col("embedding")), 9).alias("n"))


@query("SELECT o_orderkey FROM orders WHERE (o_totalprice > 300000 OR o_orderstatus = 'F') AND NOT o_orderpriority = '5-LOW'")
def filter_and_or_not(spark, sf_dir):
    return load(spark, sf_dir, "orders").where("(o_totalprice > 300000 OR o_orderstatus = 'F') AND NOT o_orderpriority = '5-LOW'").select("o_orderkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '3-MEDIUM')")
def filter_in(spark, sf_dir):
    return load(spark, sf_dir, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "3-MEDIUM")).select("o_orderkey")


@query("SELECT p_partkey, p_type FROM part WHERE p_name LIKE '%1%'")
def filter_like(spark, sf_dir):
    return load(spark, sf_dir, "part").where(F.col("p_name").like("%1%")).select("p_partkey", "p_type")


@query("SELECT doc_id FROM documents LEFT JOIN labels USING (doc_id) WHERE quality IS NULL")
def filter_null(spark, sf_dir):
    return load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id", "left").where(F.col("quality").isNull()).select("doc_id")


@query("SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1996-06-30'")
def filter_between_dates(spark, sf_dir):
    return load(spark, sf_dir, "orders").where("o_orderdate BETWEEN timestamp_ntz '1995-01-01' AND timestamp_ntz '1996-06-30'").select("o_orderkey")


@query("SELECT CASE WHEN o_totalprice < 100000 THEN 'low' WHEN o_totalprice < 300000 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM orders GROUP BY 1")
def case_when(spark, sf_dir):
    p = F.col("o_totalprice")
    band = F.when(p < 100000, "low").when(p < 300000, "mid").otherwise("high")
    return load(spark, sf_dir, "orders").groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("n"))


# Joins


@query("SELECT vec_id, o_orderstatus FROM embeddings JOIN orders ON o_orderkey = vec_id")
def join_attrs(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").join(load(spark, sf_dir, "orders"), F.col("vec_id") == F.col("o_orderkey")).select("vec_id", "o_orderstatus")


@query("SELECT d.doc_id, quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def join_labels_left(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left")


@query("SELECT coalesce(e.vec_id, 100 * p.page_id) AS id, e.vec_id IS NULL AS only_page FROM embeddings e FULL JOIN pages p ON e.vec_id = p.page_id * 3")
def join_full(spark, sf_dir):
    e, p = load(spark, sf_dir, "embeddings"), load(spark, sf_dir, "pages")
    return e.join(p, F.col("vec_id") == F.col("page_id") * 3, "full").select(F.coalesce("vec_id", F.col("page_id") * 100).alias("id"), F.col("vec_id").isNull().alias("only_page"))


@query("SELECT vec_id FROM embeddings WHERE vec_id IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def join_semi_hits(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").join(load(spark, sf_dir, "lineitem").where("l_quantity > 45"), F.col("vec_id") == F.col("l_orderkey"), "left_semi").select("vec_id")


@query("SELECT vec_id FROM embeddings WHERE vec_id NOT IN (SELECT l_orderkey FROM lineitem)")
def join_anti_cache(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").join(load(spark, sf_dir, "lineitem"), F.col("vec_id") == F.col("l_orderkey"), "left_anti").select("vec_id")


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast_nation(spark, sf_dir):
    nation = load(spark, sf_dir, "nation")  # 25 rows by definition
    return load(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


def _hinted(kind: str):
    @query("SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 4) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey", f"join_{kind}_orders")
    def run(spark, sf_dir):
        joined = load(spark, sf_dir, "orders").join(load(spark, sf_dir, "lineitem").hint(kind), F.col("o_orderkey") == F.col("l_orderkey"))
        return joined.groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"))


for _kind in ("merge", "shuffle_hash"):
    _hinted(_kind)


@query("SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON a.vec_id % 10 = 0 AND b.vec_id % 10 <> 0 AND sqrt(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: (p[1]::DOUBLE - p[2]) * (p[1]::DOUBLE - p[2])))) < 1.3")
def join_distance_radius(spark, sf_dir):
    """The held-out queries against all rows."""
    base, queries = base_and_queries(load(spark, sf_dir, "embeddings"))
    return tiles.meet(queries, base, tiles.within(1.3, inclusive=False), tiles.FOUND).select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"))


@query("WITH c AS (SELECT unnest(range(10)) AS cell) SELECT cell::INT AS cell, count(*) AS n FROM orders JOIN c ON o_totalprice >= cell * 50000 AND o_totalprice < (cell + 1) * 50000 GROUP BY cell")
def join_cell_range(spark, sf_dir):
    """A value's cell is its bucket, so the range join is an equi-join."""
    cells = spark.range(10).select(F.col("id").cast("int").alias("cell"))
    own = load(spark, sf_dir, "orders").select(F.floor(F.col("o_totalprice") / 50000).cast("int").alias("cell"))
    return own.join(cells, "cell").groupBy("cell").agg(F.count(F.lit(1)).alias("n"))


@query("""WITH o AS (SELECT o_orderkey, o_custkey, o_orderdate FROM orders)
SELECT a.o_orderkey, max(b.o_orderdate) AS previous FROM o a LEFT JOIN o b ON a.o_custkey = b.o_custkey AND b.o_orderdate < a.o_orderdate GROUP BY a.o_orderkey""")
def join_asof(spark, sf_dir):
    """The last earlier date of the same key, by one window over the distinct dates."""
    own = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    dates = own.select("o_custkey", "o_orderdate").distinct().withColumn("previous", F.lag("o_orderdate").over(Window.partitionBy("o_custkey").orderBy("o_orderdate")))
    return own.join(dates, ["o_custkey", "o_orderdate"]).select("o_orderkey", "previous")


@query("""WITH e AS (SELECT user_id, ts, value, event_id FROM events), r AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM e)
SELECT c_custkey, event_id FROM customer JOIN r ON user_id = c_custkey WHERE r <= 2""")
def join_lateral_topk(spark, sf_dir):
    ranked = load(spark, sf_dir, "events").withColumn("r", F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))).where("r <= 2")
    return load(spark, sf_dir, "customer").join(ranked, F.col("user_id") == F.col("c_custkey")).select("c_custkey", "event_id")


@query("""WITH d AS (SELECT a.vec_id AS a, b.vec_id AS b, round(sqrt(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: (p[1]::DOUBLE - p[2]) * (p[1]::DOUBLE - p[2])))), 9) AS dist FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND a.label = b.label),
r AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY dist, b) AS r FROM d) SELECT a, b, dist FROM r WHERE r <= 3""")
def knn_self_join(spark, sf_dir):
    df = load(spark, sf_dir, "embeddings")
    every = df.select("label", F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    found = tiles.meet(every, df, tiles.nearest(3, other=True), tiles.FOUND, by="label").select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"), F.round("dist", 9).alias("dist"))
    return found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("dist", "b"))).where("r <= 3").drop("r")


# Aggregates


@query("SELECT label, count(*) AS n, min(vec_id) AS first_id, max(vec_id) AS last_id FROM embeddings GROUP BY label")
def agg_by_label(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.min("vec_id").alias("first_id"), F.max("vec_id").alias("last_id"))


@query("SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderpriority")
def agg_count_distinct(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("customers"))


@query()
def agg_approx_distinct(spark, sf_dir):
    return load(spark, sf_dir, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("customers"))


def _cubed(name: str, sql: str, how):
    @query(f"SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {sql}", name)
    def run(spark, sf_dir):
        return how(load(spark, sf_dir, "orders")).agg(F.count(F.lit(1)).alias("n"))


_cubed("rollup_attrs", "ROLLUP (o_orderstatus, o_orderpriority)", lambda d: d.rollup("o_orderstatus", "o_orderpriority"))
_cubed("cube_attrs", "CUBE (o_orderstatus, o_orderpriority)", lambda d: d.cube("o_orderstatus", "o_orderpriority"))
_cubed("grouping_sets_attrs", "GROUPING SETS ((o_orderstatus), (o_orderpriority))", lambda d: d.groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")]], F.col("o_orderstatus"), F.col("o_orderpriority")))


@query("SELECT dim::INT AS dim, round(avg(x), 9) AS mean, round(var_pop(x), 9) AS variance, round(max(x), 9) AS top FROM (SELECT generate_subscripts(embedding, 1) - 1 AS dim, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY dim")
def agg_dim_stats(spark, sf_dir):
    values = load(spark, sf_dir, "embeddings").select(F.posexplode(F.col("embedding").cast("array<double>")).alias("dim", "x"))
    return values.groupBy("dim").agg(F.round(F.avg("x"), 9).alias("mean"), F.round(F.var_pop("x"), 9).alias("variance"), F.round(F.max("x"), 9).alias("top"))


@query("SELECT label, dim::INT AS dim, round(avg(x), 9) AS m FROM (SELECT label, generate_subscripts(embedding, 1) - 1 AS dim, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY ALL")
def agg_centroid(spark, sf_dir):
    from packvec.sources.tables import embeddings, label_centroids

    return label_centroids(embeddings(spark, sf_dir)).select(F.col("part_id").alias("label"), F.posexplode("centroid").alias("dim", "m")).withColumn("m", F.round("m", 9))


@query("SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 6) AS median, round(quantile_cont(o_totalprice, 0.9), 6) AS p90 FROM orders GROUP BY o_orderstatus")
def agg_percentile(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("o_totalprice", F.lit(0.9)), 6).alias("p90"))


@query("SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS c, round(covar_pop(l_discount, l_tax), 9) AS v FROM lineitem GROUP BY l_returnflag")
def agg_correlation(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"), F.round(F.covar_pop("l_discount", "l_tax"), 9).alias("v"))


@query("SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def agg_bitmap(spark, sf_dir):
    at = F.col("vec_id") + 1
    maps = load(spark, sf_dir, "embeddings").groupBy("label", F.bitmap_bucket_number(at).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("m"))
    return maps.groupBy("label").agg(F.sum(F.bitmap_count("m")).alias("n"))


@query("WITH d AS (SELECT label, vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: (x::DOUBLE - 0.1) * (x::DOUBLE - 0.1)))), 9) AS dist FROM embeddings) SELECT label, min_by(vec_id, {'d': dist, 'i': vec_id}) AS nearest FROM d GROUP BY label")
def agg_nearest_by_label(spark, sf_dir):
    point = F.array_repeat(F.lit(0.1), 64)
    d = load(spark, sf_dir, "embeddings").select("label", "vec_id", F.round(v.l2(F.col("embedding"), point), 9).alias("dist"))
    return d.groupBy("label").agg(F.min_by("vec_id", F.struct("dist", "vec_id")).alias("nearest"))


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '5-LOW') AS low FROM orders GROUP BY o_orderstatus")
def agg_pivot(spark, sf_dir):
    p = load(spark, sf_dir, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count()
    return p.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


KNN = """WITH d AS (SELECT q.vec_id AS query_id, q.label AS truth, b.label, b.vec_id, round(sqrt(list_sum(list_transform(list_zip(q.embedding, b.embedding), lambda p: (p[1]::DOUBLE - p[2]) * (p[1]::DOUBLE - p[2])))), 9) AS dist FROM embeddings q, embeddings b WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 <> 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS r FROM d), n AS (SELECT query_id, label, count(*) AS n FROM r WHERE r <= 10 GROUP BY ALL)"""


@query(f"{KNN} SELECT query_id, min_by(label, {{'n': -n, 'l': label}}) AS label FROM n GROUP BY query_id")
def knn_classify(spark, sf_dir):
    from packvec.plans import exact
    from packvec.sources.tables import base_and_queries, embeddings

    df = embeddings(spark, sf_dir)
    base, queries = base_and_queries(df)
    votes = exact.knn(queries, base, 10).join(df.select("vec_id", "label"), "vec_id").groupBy("query_id", "label").agg(F.count(F.lit(1)).alias("n"))
    return votes.groupBy("query_id").agg(F.min_by("label", F.struct(-F.col("n"), F.col("label"))).alias("label"))


# Windows, sorts, sets


@query("SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_event(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS n_before FROM orders")
def win_running_candidates(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, -1)
    return load(spark, sf_dir, "orders").select("o_orderkey", F.count(F.lit(1)).over(w).alias("n_before"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_totalprice RANGE BETWEEN 10000 PRECEDING AND 10000 FOLLOWING) AS near FROM orders")
def win_range_frame(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice").rangeBetween(-10000, 10000)
    return load(spark, sf_dir, "orders").select("o_orderkey", F.count(F.lit(1)).over(w).alias("near"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25 OFFSET 5")
def topk_global(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(25)


@query("WITH r AS (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) SELECT o_custkey, o_orderkey FROM r WHERE r <= 2")
def topk_per_query(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


def _sets(name: str, op: str, how):
    @query(f"SELECT label, vec_id % 7 AS m FROM embeddings WHERE vec_id < 300 {op} SELECT label, vec_id % 7 AS m FROM embeddings WHERE vec_id >= 200", name)
    def run(spark, sf_dir):
        e = load(spark, sf_dir, "embeddings").select("label", (F.col("vec_id") % 7).alias("m"), "vec_id")
        return how(e.where("vec_id < 300").drop("vec_id"), e.where("vec_id >= 200").drop("vec_id"))


_sets("hits_union", "UNION ALL", lambda a, b: a.unionByName(b))
_sets("hits_union_distinct", "UNION", lambda a, b: a.unionByName(b).distinct())
_sets("hits_intersect", "INTERSECT", lambda a, b: a.intersect(b))
_sets("hits_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_sets("hits_except", "EXCEPT", lambda a, b: a.subtract(b))
_sets("hits_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))


# Functions


@query("SELECT vec_id, round(sqrt(vec_id), 9) AS a, round(ln(vec_id + 1), 9) AS b, round(pow(vec_id, 1.5), 4) AS c, greatest(vec_id, 100) AS d, vec_id % 7 AS e FROM embeddings")
def fn_math(spark, sf_dir):
    i = F.col("vec_id")
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.sqrt(i), 9).alias("a"), F.round(F.ln(i + 1), 9).alias("b"), F.round(F.pow(i, F.lit(1.5)), 4).alias("c"), F.greatest(i, F.lit(100)).alias("d"), (i % 7).alias("e"))


@query("SELECT vec_id, vec_id << 3 AS l, vec_id >> 2 AS r, vec_id & 12 AS a, vec_id | 5 AS o, xor(vec_id, 9) AS x, bit_count(vec_id)::INT AS n FROM embeddings")
def fn_bits(spark, sf_dir):
    i = F.col("vec_id")
    return load(spark, sf_dir, "embeddings").select("vec_id", F.shiftleft(i, 3).alias("l"), F.shiftright(i, 2).alias("r"), i.bitwiseAND(12).alias("a"), i.bitwiseOR(5).alias("o"), i.bitwiseXOR(9).alias("x"), F.bit_count(i).alias("n"))


@query("SELECT vec_id, list_filter(list_transform(embedding, lambda x: floor(x::DOUBLE * 100)::INT), lambda x: x > 20) AS big, embedding[1:2] AS head FROM embeddings".replace("embedding[1:2] AS head", "round(embedding[1]::DOUBLE + embedding[2]::DOUBLE, 9) AS head"))
def fn_arrays(spark, sf_dir):
    e = F.col("embedding")
    big = F.filter(F.transform(e, lambda x: F.floor(x.cast("double") * 100).cast("int")), lambda x: x > 20)
    return load(spark, sf_dir, "embeddings").select("vec_id", big.alias("big"), F.round(F.aggregate(F.slice(e, 1, 2), F.lit(0.0), lambda s, x: s + x.cast("double")), 9).alias("head"))


@query("SELECT doc_id, md5(text) AS m, length(text) AS n, lower(lang) AS l, substring(text, 1, 5) AS s, len(string_split(text, ' '))::INT AS w FROM documents")
def fn_strings(spark, sf_dir):
    t = F.col("text")
    return load(spark, sf_dir, "documents").select("doc_id", F.md5(t).alias("m"), F.length(t).cast("long").alias("n"), F.lower("lang").alias("l"), F.substring(t, 1, 5).alias("s"), F.size(F.split(t, " ")).alias("w"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS d, year(o_orderdate)::INT AS y FROM orders")
def fn_dates(spark, sf_dir):
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.date_trunc("month", d).cast("timestamp_ntz").alias("m"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("d"), F.year(d).alias("y"))


@query("SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def fn_json(spark, sf_dir):
    return load(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE - 0.05))), 7) AS l1, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * 0.05)), 7) AS dot FROM embeddings")
def fn_vectors(spark, sf_dir):
    point = F.array_repeat(F.lit(0.05), 64)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(v.l1(F.col("embedding"), point), 7).alias("l1"), F.round(v.inner_product(F.col("embedding"), point), 7).alias("dot"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 7) AS n FROM embeddings")
def fn_sql_registered(spark, sf_dir):
    v.register(spark)
    zero = F.array_repeat(F.lit(0.0), 64)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.call_function("pv_l2", F.col("embedding").cast("array<double>"), zero), 7).alias("n"))


# Batch twins of the streams


@query("SELECT date_trunc('hour', ts)::TIMESTAMP AS w, event_type, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY ALL")
def win_tumbling(spark, sf_dir):
    w = F.window(F.col("ts").cast("timestamp"), "1 hour")
    return load(spark, sf_dir, "events").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("v")).select(F.col("w.start").cast("timestamp_ntz").alias("w"), "event_type", "n", "v")


@query("SELECT w, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) + INTERVAL (CASE WHEN minute(ts) >= 30 THEN 30 ELSE -30 END) MINUTE])::TIMESTAMP AS w FROM events) GROUP BY w")
def win_sliding(spark, sf_dir):
    w = F.window(F.col("ts").cast("timestamp"), "1 hour", "30 minutes")
    return load(spark, sf_dir, "events").groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("w"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, new DESC ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM s GROUP BY user_id, s""")
def win_session(spark, sf_dir):
    w = F.session_window(F.col("ts").cast("timestamp"), "6 hours")
    return load(spark, sf_dir, "events").groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
