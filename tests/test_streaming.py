"""Streams replayed from files."""

from pyspark.sql import functions as F

from packvec.plans import index, search
from packvec.plans.shared import stored
from packvec.sources import tables
from packvec.streaming import streams


def test_query_stream(spark, sf_dir, tmp_path):
    df = stored(tables.embeddings(spark, sf_dir).where("vec_id < 100"), "stream")
    base, queries = tables.base_and_queries(df)
    found = index.build(base, [], index.Config(partitions=1, rounds=2))
    source = queries.withColumn("pred", F.lit(""))
    source.repartition(2).write.parquet(str(tmp_path / "in"))
    stream = streams.replay(spark, str(tmp_path / "in"), source.schema)
    streams.stream_search(found, stream, str(tmp_path / "out"), str(tmp_path / "check"), 5).awaitTermination()
    got = {(r["query_id"], r["rank"], r["vec_id"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {(r["query_id"], r["rank"], r["vec_id"]) for r in search.search(found, queries, 5).collect()}


def test_rates_and_repeats(spark, tmp_path):
    rows = [(i, f"2024-01-01 00:{i:02d}:00", [float(i % 3)], "") for i in range(30)]
    df = spark.createDataFrame(rows, "query_id long, t string, qvec array<double>, pred string").withColumn("ts", F.col("t").cast("timestamp")).drop("t")
    df.coalesce(1).write.parquet(str(tmp_path / "in"))
    for name, f in (("rates", lambda s: streams.rates(s, "10 minutes", late="0 minutes")), ("first", lambda s: streams.first_only(s, "2 hours"))):
        stream = f(streams.replay(spark, str(tmp_path / "in"), df.schema))
        stream.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start().awaitTermination()
    assert {r["n"] for r in spark.table("rates").collect()} == {10}
    assert spark.table("first").count() == 3
