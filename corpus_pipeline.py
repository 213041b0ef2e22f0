"""A corpus pipeline of five stages; each stage's result is written as Parquet and read again as the next one's input."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from packvec.llm import decontaminate, jaccard_join, mixing, sharding, toxicity
from packvec.llm.common import shared_folder, table

TOXIC_FROM, SHARDS = 0.3, 40


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below TOXIC_FROM. The model is learnt from the labelled documents given."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    judged = toxicity.scored(docs, model, score="_pv_toxic")
    return judged.where(F.col("_pv_toxic") < TOXIC_FROM).select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by a Jaccard similarity of 0.8 on five-word shingles: that with the least id.

    Of a group without ids the one with the least hash of its text stays. Documents without words are linked with
    nothing and all stay. Of rows that share an id and a text, one stays.
    """
    found = jaccard_join.near_duplicates(docs, n=5, num=80)
    worded = found.where(F.col("name") != 0).groupBy("group").agg(F.min(F.struct(F.col("id").isNull().alias("no"), "id", "key")).alias("m"))
    row = F.xxhash64(F.col("id").cast("string"), F.col("key"))
    keep = worded.select("m.id", "m.key").select(row.alias("_pv_row"), F.lit(False).alias("_pv_blank")).unionByName(found.where(F.col("name") == 0).select(row.alias("_pv_row"), F.lit(True).alias("_pv_blank")).distinct())
    own = docs.withColumn("_pv_own", F.xxhash64(F.col("doc_id").cast("long").cast("string"), F.xxhash64(F.coalesce("text", F.lit("")))))
    met = own.join(keep, F.col("_pv_own") == F.col("_pv_row"))
    first = F.row_number().over(Window.partitionBy("_pv_own").orderBy("_pv_own"))
    return met.withColumn("_pv_first", first).where(F.col("_pv_blank") | (F.col("_pv_first") == 1)).select(*docs.columns)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not contaminated by benchmark passages."""
    judged = decontaminate.contamination(docs, table(spark, sf_dir, "benchmark"))
    bad = judged.where("contaminated").select(F.col("_id").alias("_pv_bad"), F.col("_key").alias("_pv_bad_key")).distinct()
    own = docs.withColumn("_pv_own", F.xxhash64(F.col("doc_id").cast("string"), F.col("text")))
    return own.join(bad, F.col("doc_id").eqNullSafe(F.col("_pv_bad")) & (F.col("_pv_own") == F.col("_pv_bad_key")), "left_anti").select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of all sources to their target weights; a document stands in it as often as it is taken."""
    return mixing.repeated(mixing.mix(docs), docs.columns)


def sharding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows with their shard and their number in it."""
    return sharding.assign(docs, sharding.tree_of(SHARDS))


STAGES = [
    ("toxicity", toxicity_stage),
    ("near duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
    ("sharding", sharding_stage),
]

#: Scores of a trained model decide in the first stage, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{shared_folder(spark)}/pipeline-{name.replace(' ', '-')}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
