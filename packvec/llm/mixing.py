"""Operator 8: sources mixed to target weights by capped water-filling, with seeded whole and fractional repetitions.

A source's target is its weight times a common level, or its cap if that is less; the level is what makes the targets
sum to the wanted total. Raising it from 0 clamps sources at their caps one round after another, each round one
aggregate over the sources. A source whose target is e times its size has all documents floor(e) times and, for the
rest, those that come first in a seeded order of all its documents, up to the one whose middle passes the target.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from packvec.llm.common import word_count, written

#: Groups that a source's documents are ordered in: the first three hexadecimal digits of their places in the order.
GROUP_DIGITS = 3
MAX_BROADCAST_SOURCES = 100_000


def source_key(source: Column) -> Column:
    """A string that is never null and tells null from the empty string."""
    return F.coalesce(F.concat(F.lit("="), source), F.lit(""))


def place(df: DataFrame, id: str, text: str, seed: int) -> Column:
    """A document's place in the seeded order; equal for repeated rows only."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id).cast("string"), F.lit("")), F.lit(":"), F.coalesce(F.col(text), F.lit(""))))


def targets(stats: DataFrame, weights: Sequence[float], total_share: float, most: float) -> DataFrame:
    """stats (_s, source, source_size; a written table of one row a source) with the target of each source.

    Weights repeat over the sources by code point, null last.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    which = (F.row_number().over(order) - 1) % len(weights)
    weighed = written(stats.withColumn("w", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), which + 1)).withColumn("cap", F.col("source_size") * F.lit(float(most))), "weighed")
    whole = weighed.agg(F.sum("source_size")).first()[0] or 0
    wanted, level = total_share * whole, 0.0
    while True:
        clamped = F.col("cap") <= F.lit(level) * F.col("w")
        full, weight = weighed.agg(F.sum(F.when(clamped, F.col("cap")).otherwise(0.0)), F.sum(F.when(clamped, 0.0).otherwise(F.col("w")))).first()
        above = (wanted - (full or 0.0)) / weight if weight else level
        if above <= level:
            break
        level = above
    return weighed.withColumn("target", F.least(F.col("cap"), F.lit(level) * F.col("w")))


def mix(df: DataFrame, weights: Sequence[float] = (5, 2, 1), total_share: float = 1.5, most: float = 2.0, seed: int = 7, id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """df with _size, _source_size, _target (of its source) and _copies (times that the mix takes the document).

    Texts are not shuffled: places in the order and sizes are, and each source then has one last place, which decides
    for its documents as they are read. Edge cases: null source is a source of its own; null and empty texts have
    size 0 and are taken floor(e) times or by place; repeated rows share a place and are taken alike; a source of size
    0 has target 0; an empty table gives an empty result; other columns pass through.
    """
    own = df.withColumns({"_pv_s": source_key(F.col(source)), "_pv_size": word_count(F.col(text)), "_pv_place": place(df, id, text, seed)})
    sized = written(own.select("_pv_s", F.col(source).alias("source"), F.col("_pv_size").alias("_size"), "_pv_place"), "sizes")
    stats = sized.groupBy("_pv_s", "source").agg(F.sum("_size").alias("source_size"))
    wanted = targets(stats, weights, total_share, most).select("_pv_s", "source_size", "target")
    times = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    wanted = written(wanted.withColumn("times", F.floor(times)).withColumn("rest", F.col("target") - F.col("times") * F.col("source_size")), "targets")

    units = sized.groupBy("_pv_s", "_pv_place").agg(F.sum("_size").alias("n")).withColumn("_pv_g", F.substring("_pv_place", 1, GROUP_DIGITS))
    groups = units.groupBy("_pv_s", "_pv_g").agg(F.sum("n").alias("all"))
    before = groups.select("_pv_s", "_pv_g", (F.sum("all").over(Window.partitionBy("_pv_s").orderBy("_pv_g")) - F.col("all")).alias("before"))
    middle = F.col("before") + F.sum("n").over(Window.partitionBy("_pv_s", "_pv_g").orderBy("_pv_place")) - F.col("n") / 2
    reached = units.join(before, ["_pv_s", "_pv_g"]).withColumn("middle", middle).join(wanted, "_pv_s").where(F.col("middle") <= F.col("rest"))
    last = wanted.join(reached.groupBy("_pv_s").agg(F.max("_pv_place").alias("last")), "_pv_s", "left").select(F.col("_pv_s").alias("_pv_t"), F.col("source_size").alias("_pv_ss"), F.col("target").alias("_pv_target"), F.col("times").alias("_pv_times"), F.when(F.col("rest") > 0, F.col("last")).alias("_pv_last"))
    last = written(last, "last")
    if last.count() <= MAX_BROADCAST_SOURCES:
        last = F.broadcast(last)
    out = own.join(last, F.col("_pv_s") == F.col("_pv_t"))
    copies = F.col("_pv_times") + F.when(F.col("_pv_place") <= F.col("_pv_last"), 1).otherwise(0)
    kept = [c for c in df.columns if c not in ("_size", "_source_size", "_target", "_copies")]
    return out.select(*kept, F.col("_pv_size").alias("_size"), F.col("_pv_ss").cast("long").alias("_source_size"), F.col("_pv_target").alias("_target"), copies.cast("long").alias("_copies"))


def repeated(mixed: DataFrame, columns: Sequence[str]) -> DataFrame:
    """The mix itself: columns of each document as many times as it is taken."""
    return mixed.where(F.col("_copies") > 0).select(*columns, F.explode(F.sequence(F.lit(1).cast("long"), F.col("_copies"))).alias("_again")).drop("_again")
