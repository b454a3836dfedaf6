from seqvault.index import IndexParams, build_index
from seqvault.operators.barrier import scratch_path
from seqvault.streaming import delta

KEY = bytes(range(64))


def test_feed_appends_once_and_equals_batch(spark):
    rows = [(i, "ACGTTGCAACGT"[i % 5 :] * (i % 4 + 1)) for i in range(12)]
    path, schema = scratch_path(spark, "feed"), "item_no long, seq string"
    for i in range(3):
        spark.createDataFrame(rows[4 * i : 4 * i + 4], schema).coalesce(1).write.mode("append").parquet(path)
    first = build_index(spark.createDataFrame([(100, "ACGT")], schema), IndexParams(k=2, bs=16), KEY, scratch_path(spark, "fed"))
    feed = delta.IndexFeed(first)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)
    feed.start(stream, scratch_path(spark, "state")).awaitTermination()
    assert sorted(map(tuple, feed.index.restore().collect())) == sorted([*rows, (100, "ACGT")])
    assert feed.index.shards().count() == 4
    feed.take(spark.createDataFrame(rows[:4], schema), 0)  # a replayed batch
    assert feed.index.table("items").count() == 13


def test_patterns_stream_against_an_index(spark):
    index = build_index(spark.createDataFrame([(1, "ACGTACGT")], "item_no long, seq string"), IndexParams(k=2, bs=16), KEY, scratch_path(spark, "fixed"))
    path, out = scratch_path(spark, "asked"), scratch_path(spark, "hits")
    spark.createDataFrame([(7, "CGT")], "pattern_id long, pattern string").coalesce(1).write.parquet(path)
    stream = spark.readStream.schema("pattern_id long, pattern string").parquet(path)
    delta.locate_stream(stream, index, out, scratch_path(spark, "state")).awaitTermination()
    assert sorted(tuple(r)[:3] for r in spark.read.parquet(out).collect()) == [(7, 1, 1), (7, 1, 5)]
