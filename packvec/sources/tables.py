"""The given tables and the vector sets of the experiments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from packvec.functions.vectors import text_vectors
from packvec.plans.shared import stored

#: The experiments' conjunctive predicate of about 8 %.
EIGHT_PERCENT = "totalprice BETWEEN 100000 AND 400000 AND orderdate < timestamp_ntz '1998-07-01' AND priority <= '2-HIGH' AND (status < 'P' OR status > 'P')"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def valid(vector: str, d: int | None = None) -> Column:
    """True for vectors without null or non-finite components and, if given, of length d."""
    bad = F.exists(F.col(vector), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    ok = F.col(vector).isNotNull() & (F.size(vector) > 0) & ~bad
    return ok & (F.size(vector) == d) if d else ok


def split_valid(df: DataFrame, vector: str = "embedding", d: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(usable rows, quarantined rows)."""
    ok = F.coalesce(valid(vector, d), F.lit(False))
    return df.where(ok), df.where(~ok)


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """VE: vec_id, embedding (double), label."""
    return load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"), "label")


def hybrid_ve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """VE with the attributes of orders bound by o_orderkey = vec_id."""
    orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vec_id"), F.col("o_totalprice").alias("totalprice"), F.col("o_orderdate").alias("orderdate"), F.col("o_orderpriority").alias("priority"), F.col("o_orderstatus").alias("status"))
    return embeddings(spark, sf_dir).join(orders, "vec_id")


def uniform_attributes(df: DataFrame, n: int = 4) -> DataFrame:
    """Adds u0 .. u(n-1), uniform in [0, 1), from md5 of the id."""
    digits = lambda j: F.conv(F.substring(F.md5(F.concat(F.col("vec_id").cast("string"), F.lit(f"-{j}"))), 1, 7), 16, 10).cast("long")
    return df.withColumns({f"u{j}": (digits(j) % 10000) / F.lit(10000.0) for j in range(n)})


def documents_vd(spark: SparkSession, sf_dir: str, d: int = 64) -> DataFrame:
    """VD: the hashed vector of every document with lang, source, n_chars and, where labelled, quality and toxic.

    Documents without tokens, or whose signed counts are all zero, have the zero vector.
    """
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text", "lang", "source", "n_chars")
    vectors = text_vectors(docs.select(F.col("vec_id").alias("_id"), "text"), "_id", "text", d, "embedding")
    vector = F.coalesce("embedding", F.array_repeat(F.lit(0.0), d)).alias("embedding")
    found = docs.drop("text").join(vectors, F.col("vec_id") == F.col("_id"), "left").select("vec_id", vector, "lang", "source", "n_chars")
    return found.join(load(spark, sf_dir, "labels"), F.col("vec_id") == F.col("doc_id"), "left").drop("doc_id")


def numbered(df: DataFrame, out: str, *by: str) -> DataFrame:
    """df with out, a long from 0 on that numbers the rows in the order of by: each range of the order numbers its own rows.

    by must tell all rows apart but those that are equal in all columns, as the order is made and its ranges are counted in
    separate jobs. The ranges are kept in the shared folder.
    """
    ranged = df.repartitionByRange(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *by).sortWithinPartitions(*by)
    kept = stored(ranged.withColumn("_at", F.monotonically_increasing_id()), "ranges")  # 31 bits for the range, 33 for the place in it
    kept = kept.withColumns({"_range": F.shiftright("_at", 33), "_place": F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))})
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    sizes = kept.groupBy("_range").agg(F.count(F.lit(1)).alias("n")).select("_range", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_before"))
    return kept.join(F.broadcast(sizes), "_range").withColumn(out, F.col("_before") + F.col("_place")).drop("_at", "_range", "_place", "_before")


def lineitem_vl(spark: SparkSession, sf_dir: str) -> DataFrame:
    """VL: six standardised numbers of each line; the id numbers the rows in the order of all columns."""
    line = load(spark, sf_dir, "lineitem")
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("double")
    raw = {"q": F.col("l_quantity"), "p": F.col("l_extendedprice"), "s": F.col("l_discount"), "t": F.col("l_tax"), "d": day, "l": F.col("l_linenumber").cast("double")}
    stats = line.agg(*[f(x).alias(f"{n}_{c}") for c, x in raw.items() for n, f in (("m", F.avg), ("v", F.stddev_pop))]).first()
    vector = F.array(*[(x - F.lit(stats[f"m_{c}"])) / F.lit(stats[f"v_{c}"] or 1.0) for c, x in raw.items()])
    return numbered(line, "vec_id", *sorted(line.columns)).select("vec_id", vector.alias("embedding"), "l_returnflag", "l_linestatus", "l_shipdate", "l_quantity")


def base_and_queries(df: DataFrame, every: int = 10) -> tuple[DataFrame, DataFrame]:
    """Rows to search, and the held-out rows (vec_id % every = 0) as query_id, qvec."""
    return df.where(F.col("vec_id") % every != 0), df.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))


def label_centroids(df: DataFrame) -> DataFrame:
    """Mean vector of each label: part_id, centroid."""
    means = df.select("label", F.posexplode("embedding").alias("dim", "x")).groupBy("label", "dim").agg(F.avg("x").alias("m"))
    return means.groupBy(F.col("label").alias("part_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "m"))), lambda s: s["m"]).alias("centroid"))
