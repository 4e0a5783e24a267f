"""Saving and loading, guarded lookups over files, and updates from a stream."""

from pyspark.sql import functions as F

from rangesieve.operators.base import BaseFilter
from rangesieve.operators.dynamic import DynamicFilter
from rangesieve.plans import prune, store
from rangesieve.sources import keysets as k
from rangesieve.streaming import updates

D = "/root/testdata/sf0.001"


def test_saved_filter_answers_alike(spark, tmp_path):
    keys, asked = k.range_queries(k.integer_keys(spark, D, "skewed"), "mixed", 1 << 10)
    f = BaseFilter.build(keys, t=64, eps=2 / 256)
    store.save_base(f, str(tmp_path))
    again = store.load_base(spark, str(tmp_path))
    assert sorted(f.probe(asked).collect()) == sorted(again.probe(asked).collect())


def test_guarded_lookup(spark, tmp_path):
    keys = k.integer_keys(spark, D, "uniform")
    keys.withColumn("v", F.lit(1)).repartition(6).write.parquet(f"{tmp_path}/t")
    filters = prune.file_filters(spark, f"{tmp_path}/t", "key").cache()
    some = [r["key"] for r in keys.orderBy("key").limit(3).collect()]
    asked = spark.createDataFrame([(i, x, x + 5) for i, x in enumerate(some)], "query_id long, lo long, hi long")
    assert prune.guarded_lookup(spark, f"{tmp_path}/t", "key", asked, filters).count() == 3
    empty = spark.createDataFrame([(9, some[0] + 1, some[0] + 9)], "query_id long, lo long, hi long")
    assert prune.guarded_lookup(spark, f"{tmp_path}/t", "key", empty, filters).count() == 0
    assert prune.predicate_range("<", 5) == (0, 4) and prune.prefix_range(b"ab", 3) == (b"ab", b"ab\xff")


def test_stream_of_updates(spark, tmp_path):
    events = spark.read.parquet(f"{D}/events.parquet").select("ts", "event_type").limit(60)
    events.repartition(2).write.parquet(f"{tmp_path}/events")
    start = spark.createDataFrame([(1,)], "key long")
    f = DynamicFilter.build(start, t=16, r=8, bounds=[1 << 50])
    stream, held = updates.apply_stream(updates.read_ops(spark, f"{tmp_path}/events", events.schema), f, f"{tmp_path}/filter", f"{tmp_path}/checkpoint")
    stream.awaitTermination(120)
    inserted = {r["key"] for r in events.where("event_type <> 'error'").select(F.unix_micros(F.col("ts").cast("timestamp")).alias("key")).collect()}
    deleted = {r["key"] for r in events.where("event_type = 'error'").select(F.unix_micros(F.col("ts").cast("timestamp")).alias("key")).collect()}
    points = spark.createDataFrame([(i, x, x) for i, x in enumerate(sorted(inserted - deleted))], "query_id long, lo long, hi long")
    assert held["filter"].probe(points).where("not positive").count() == 0


def test_filters_of_windows(spark, tmp_path):
    events = spark.read.parquet(f"{D}/events.parquet").select("event_id", "ts", "event_type").orderBy("event_id").limit(80)
    events.repartition(2).write.parquet(f"{tmp_path}/events")
    stream = updates.window_filters(spark, spark.readStream.schema(events.schema).parquet(f"{tmp_path}/events"), f"{tmp_path}/windows", f"{tmp_path}/checkpoint", t=16)
    stream.awaitTermination(300)
    keys = [r["key"] for r in updates.window_keys(events).select("key").distinct().collect()]
    asked = spark.createDataFrame([(i, x, x) for i, x in enumerate(keys)] + [(900, 5, 9)], "query_id long, lo long, hi long")
    found = {r["query_id"]: r["positive"] for r in updates.probe_windows(spark, asked, f"{tmp_path}/windows", t=16).collect()}
    assert all(found[i] for i in range(len(keys))) and not found[900]


def test_saved_string_filter_answers_alike(spark, tmp_path):
    words = spark.createDataFrame([(f"w{i * 37 % 1000:04d}",) for i in range(500)], "key string")
    f = BaseFilter.build(words, t=32, eps=2 / 256)
    store.save_base(f, str(tmp_path))
    again = store.load_base(spark, str(tmp_path))
    asked = spark.createDataFrame([(i, f"w{i:04d}", f"w{i:04d}") for i in range(0, 1000, 7)], "query_id long, lo string, hi string")
    assert sorted(map(tuple, f.probe(asked).collect())) == sorted(map(tuple, again.probe(asked).collect()))
