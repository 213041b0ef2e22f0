"""Vector arithmetic as built-in column expressions; the kernels of the search have array twins of these."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _fold(a: Column, b: Column, f) -> Column:
    return F.aggregate(F.zip_with(a, b, f), F.lit(0.0), lambda s, x: s + x)


def l2sq(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def l1(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: F.abs(x.cast("double") - y.cast("double")))


def inner_product(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: x.cast("double") * y.cast("double"))


def norm(a: Column) -> Column:
    return F.sqrt(inner_product(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine similarity; null for a zero vector."""
    return F.try_divide(inner_product(a, b), norm(a) * norm(b))


def normalize(a: Column) -> Column:
    n = norm(a)
    return F.when(n > 0, F.transform(a, lambda x: x.cast("double") / n))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x.cast("double") + y.cast("double"))


def vec_scale(a: Column, s: float) -> Column:
    return F.transform(a, lambda x: x.cast("double") * F.lit(float(s)))


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two arrays of 64-bit words."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def text_vectors(df: DataFrame, id: str, text: str, d: int, out: str) -> DataFrame:
    """id (unique) and signed counts of its text's tokens in d buckets by md5, scaled to unit length; none without tokens.

    Tokens are summed by (id, bucket) before a vector is put together, so a long text is not one task's work. The length is
    a sum of its own: inside transform it would be taken anew for each component.
    """
    tokens = df.select(id, F.explode(F.filter(F.split(F.lower(F.col(text)), r"[\s.,;:!?]+"), lambda t: t != "")).alias("t"))
    h = F.md5("t")
    bucket = F.pmod(F.conv(F.substring(h, 1, 7), 16, 10).cast("long"), F.lit(d)).cast("int").alias("b")
    sign = F.when(F.conv(F.substring(h, 8, 1), 16, 10).cast("int") % 2 == 0, 1.0).otherwise(-1.0).alias("s")
    sums = tokens.select(id, bucket, sign).groupBy(id, "b").agg(F.sum("s").alias("s"))
    each = sums.groupBy(id).agg(F.map_from_entries(F.collect_list(F.struct("b", "s"))).alias("m"), F.sqrt(F.sum(F.col("s") * F.col("s"))).alias("n"))
    unit = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at(F.col("m"), i), F.lit(0.0)) / F.col("n"))
    return each.select(id, F.when(F.col("n") > 0, unit).alias(out))


def register(spark: SparkSession) -> None:
    """SQL functions of these names, as macros over built-in functions (no Python runs)."""
    for name, body in {
        "pv_l2sq": "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
        "pv_l2": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
        "pv_dot": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        "pv_l1": "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x)",
    }.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
