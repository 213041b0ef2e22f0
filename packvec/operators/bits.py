"""Bit allocation over dimensions (M01, M02) and storage accounting."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def dims(df: DataFrame, vector: str = "embedding", *keep: str) -> DataFrame:
    """One row a component: keep, dim, x."""
    return df.select(*keep, F.posexplode(vector).alias("dim", "x"))


def variances(df: DataFrame, vector: str = "embedding", *by: str) -> DataFrame:
    """by, dim, variance; rounded to 12 decimals so that the order of summation cannot change an allocation."""
    return dims(df, vector, *by).groupBy(*by, "dim").agg(F.round(F.var_pop("x"), 12).alias("variance"))


def allocate(variances: DataFrame, budget: int, *by: str, decay: float = 4.0, max_bits: int | None = None) -> DataFrame:
    """by, dim, bits, cells: each bit goes to the largest variance left, which a bit divides by decay.

    That is the budget's largest of all variance / decay ** t, so one ranking does it. max_bits caps a dimension (M02).
    """
    steps = variances.select("*", F.explode(F.sequence(F.lit(0), F.lit((max_bits or budget) - 1))).alias("t"))
    best = Window.partitionBy(*by).orderBy(F.desc(F.col("variance") / F.pow(F.lit(decay), "t")), "dim", "t")
    given = steps.withColumn("r", F.row_number().over(best)).groupBy(*by, "dim").agg(F.count_if(F.col("r") <= budget).cast("int").alias("bits"))
    return given.withColumn("cells", F.expr("shiftleft(1L, bits)"))


def allocate_uniform(variances: DataFrame, budget: int, *by: str) -> DataFrame:
    """Equal bits for all dimensions, the remainder to the first ones."""
    n = F.count(F.lit(1)).over(Window.partitionBy(*by))
    rank = F.row_number().over(Window.partitionBy(*by).orderBy("dim"))
    out = variances.withColumns({"n": n, "r": rank}).withColumn("bits", (F.floor(F.lit(budget) / F.col("n")) + F.when(F.col("r") <= F.lit(budget) % F.col("n"), 1).otherwise(0)).cast("int"))
    return out.select(*by, "dim", "bits").withColumn("cells", F.expr("shiftleft(1L, bits)"))


def placed(bits: DataFrame, seg_bits: int, *by: str) -> DataFrame:
    """bits with bit_offset (from the first bit of the vector) and the first and last segment of each dimension."""
    before = F.sum("bits").over(Window.partitionBy(*by).orderBy("dim")) - F.col("bits")
    out = bits.withColumn("bit_offset", before.cast("int"))
    return out.withColumns({"seg_first": F.floor(F.col("bit_offset") / seg_bits).cast("int"), "seg_last": F.floor((F.col("bit_offset") + F.greatest(F.col("bits"), F.lit(1)) - 1) / seg_bits).cast("int")})


def storage(bits: DataFrame, seg_bits: int, *by: str) -> DataFrame:
    """Words, wasted bits, mean segment delta, padding and compression against one word a dimension."""
    s = F.lit(seg_bits)
    total = F.sum("bits")
    packed, plain = F.ceil(total / s), F.count(F.lit(1)) * F.greatest(F.ceil(F.max("bits") / s), F.lit(1))
    return bits.groupBy(*by).agg(
        packed.cast("long").alias("packed_words"), plain.cast("long").alias("plain_words"), (plain * s - total).cast("long").alias("plain_waste"),
        (packed * s - total).cast("long").alias("packed_padding"), F.round(F.avg(s - F.col("bits")), 6).alias("mean_delta"), F.round(plain / packed, 6).alias("compression"),
    )
