"""Streams of inserts and deletes: each micro-batch rewrites the shards it touches and becomes one committed version."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.dynamic import DynamicFilter
from ..plans.store import commit


def read_ops(spark: SparkSession, path: str, schema, watermark: str = "1 hour") -> DataFrame:
    """(op, key, seq, ts) of an event stream: the key is the event's time in microseconds, an "error" event deletes it.

    Inserts must be a set, so repeats inside the watermark are dropped.
    """
    events = spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    ops = events.select(F.when(F.col("event_type") == "error", "delete").otherwise("insert").alias("op"), F.unix_micros("ts").alias("key"), F.unix_micros("ts").alias("seq"), "ts")
    return ops.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["op", "key"])


def windowed_counts(ops: DataFrame, size: str = "1 day") -> DataFrame:
    """Inserts and deletes of each tumbling window, once the watermark has passed it."""
    return ops.groupBy(F.window("ts", size), "op").agg(F.count("*").alias("n")).select("window.start", "op", "n")


def apply_stream(ops: DataFrame, f: DynamicFilter, path: str, checkpoint: str) -> tuple[StreamingQuery, dict]:
    """Starts the query; the second result's "filter" is always the last committed version, which readers probe."""
    held = {"filter": commit(f, path, 0)}

    def one(batch: DataFrame, epoch: int) -> None:
        # a replayed epoch starts from the version before it and overwrites its own
        before = DynamicFilter(batch.sparkSession.read.schema(f.state.schema).parquet(f"{path}/version={epoch}"), f.bounds, f.t, f.r, f.options)
        held["filter"] = commit(before.apply(batch.select("op", "key", "seq")), path, epoch + 1)

    return ops.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(), held


def window_keys(events: DataFrame, size: str = "1 day") -> DataFrame:
    """(start, key): the inserted keys of each tumbling window, of a stream or a table of events."""
    at = events.where("event_type <> 'error'").withColumn("ts", F.col("ts").cast("timestamp"))
    return at.select(F.window("ts", size)["start"].alias("start"), F.unix_micros("ts").alias("key"))


def window_filters(spark: SparkSession, events: DataFrame, path: str, checkpoint: str, size: str = "1 day", t: int = 256, r: int = 8) -> StreamingQuery:
    """One filter for each window: a batch adds its keys to the windows that it touches, and each window's filter is a versioned folder.

    A range of times is asked of the filters of the windows that it meets: probe_windows.
    """

    def one(batch: DataFrame, epoch: int) -> None:
        for row in batch.select("start").distinct().collect():  # windows of one batch
            at = f"{path}/window={int(row['start'].timestamp())}"
            keys = batch.where(F.col("start") == F.lit(row["start"])).select("key").distinct()
            before = _versions(spark, at)
            held = spark.read.parquet(f"{at}/version={max(v for v in before if v < epoch + 1)}") if any(v < epoch + 1 for v in before) else None
            f = DynamicFilter(held, [], t, r).insert(keys) if held is not None else DynamicFilter.build(keys, t=t, r=r, bounds=[])
            commit(f, at, epoch + 1)

    return window_keys(events, size).writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _versions(spark: SparkSession, path: str) -> list[int]:
    root = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return sorted(int(f.getPath().getName().split("=")[1]) for f in fs.listStatus(root)) if fs.exists(root) else []


def probe_windows(spark: SparkSession, queries: DataFrame, path: str, t: int = 256, r: int = 8, seconds: int = 86_400) -> DataFrame:
    """(query_id, positive) of ranges of times in microseconds: any filter of a window that a range meets may answer it."""
    root = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    out = queries.select("query_id", F.lit(False).alias("positive"))
    for status in fs.listStatus(root):  # one folder for each window
        name = status.getPath().getName()
        start = int(name.split("=")[1]) * 1_000_000
        met = queries.where((F.col("hi") >= start) & (F.col("lo") < start + seconds * 1_000_000))
        last = max(_versions(spark, f"{path}/{name}"))
        out = out.union(DynamicFilter(spark.read.parquet(f"{path}/{name}/version={last}"), [], t, r).probe(met))
    return out.groupBy("query_id").agg(F.bool_or("positive").alias("positive"))


def late_rows(events: DataFrame, order: str = "event_id", watermark_seconds: int = 3600) -> DataFrame:
    """(n, n_distinct, n_late) of a table in the order of arrival: late rows come after one that is more than the watermark ahead of them.

    The greatest time so far is carried over ranges of the order, so that no task sees all rows.
    """
    from ..operators.anchors import rank_keys

    ranked = rank_keys(events.select(F.col(order).alias("key"), F.unix_micros(F.col("ts").cast("timestamp")).alias("at"), (F.col("event_type") == "error").alias("gone")))
    so_far = Window.partitionBy("shard").orderBy("key").rowsBetween(Window.unboundedPreceding, -1)
    most = ranked.rows.groupBy("shard").agg(F.max("at").alias("_m"))
    before = most.select("shard", F.max("_m").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)).alias("_before"))
    # one row for each shard
    seen = ranked.rows.join(F.broadcast(before), "shard").withColumn("_seen", F.greatest(F.max("at").over(so_far), F.col("_before")))
    late = F.coalesce(F.col("at") < F.col("_seen") - watermark_seconds * 1_000_000, F.lit(False))
    return seen.agg(F.count("*").alias("n"), F.countDistinct("gone", "at").alias("n_distinct"), F.sum(late.cast("long")).alias("n_late"))
