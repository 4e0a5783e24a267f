"""Sorted ranks, anchors and the predecessor joins that route queries to blocks, all without a global sort in one task.

Keys are dealt into ranges and sorted once; a row's place in its range and the counts of the ranges before give its rank, and the sorted
table is written, so that nothing sorts again.  The same ranges, the shards, route queries: a query meets the anchors of its shard, and the
last anchor of the shards before comes from a table with one row for each shard.  Their number follows from the number of keys.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.lineage import written

#: Keys of a shard: at most the first, and not fewer than the second only to occupy more tasks.
SHARD_KEYS, SMALL_SHARD = 1 << 21, 1 << 14
#: Bounds that one expression searches as nested conditions; more are searched in an array.
NESTED = 64


def shard_count(n: int, tasks: int = 8) -> int:
    return max(1, -(-n // SHARD_KEYS), min(tasks, n // SMALL_SHARD))


def shard_bounds(keys: DataFrame, key: str = "key", shards: int | None = None) -> list:
    """Keys that cut the key set into parts of similar size, `shards` or as many as its size asks for."""
    tasks = keys.sparkSession.sparkContext.defaultParallelism
    if dict(keys.dtypes)[key] in ("bigint", "int", "double"):
        at = lambda k: F.percentile_approx(key, [i / k for i in range(1, k)], 100 * k).alias("c")
        first = shards or max(2, tasks)
        r = keys.agg(F.count(key).alias("n"), at(first) if first > 1 else F.lit(None).alias("c")).first()
        wanted = shards or shard_count(r["n"], tasks)
        cut = r["c"] if wanted == first else keys.agg(at(wanted)).first()["c"] if wanted > 1 else []
        return sorted(set(cut or []))
    # byte strings have no quantiles: equal steps through a bounded sample, the keys of smallest hash
    wanted = shards or shard_count(keys.count(), tasks)
    sample = sorted(r[0] for r in keys.select(key).orderBy(F.xxhash64(key), key).limit(50 * wanted).collect())
    step = max(1, len(sample) // wanted)
    return [bytes(b) if isinstance(b, bytearray) else b for b in sorted(set(sample[step::step]))]


def shard_of(x: Column, bounds: list) -> Column:
    """How many bounds are at most x, by binary search."""
    if len(bounds) > NESTED:
        # integers as one text: a literal each takes the driver a call each
        whole = all(type(b) is int for b in bounds)
        all_bounds, steps = F.expr(f"array({', '.join(f'{b}L' for b in bounds)})") if whole else F.array(*map(F.lit, bounds)), F.array(*(F.lit(1 << s) for s in reversed(range(len(bounds).bit_length()))))
        return F.aggregate(steps, F.lit(0), lambda p, s: F.when((p + s <= len(bounds)) & (F.get(all_bounds, p + s - 1) <= x), p + s).otherwise(p))

    def search(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(x < F.lit(bounds[mid]), search(lo, mid)).otherwise(search(mid + 1, hi))

    return search(0, len(bounds)).cast("int")


@dataclass
class Ranked:
    """rows: the keys with shard and rank 0..n-1 in key order, as a written table; bounds: the first key of each shard but the first."""

    rows: DataFrame
    bounds: list
    n: int


def rank_keys(keys: DataFrame, key: str = "key") -> Ranked:
    """One exchange by range, one sort and one write; a row's place in its task is the low part of its running number."""
    shards = shard_count(keys.count(), keys.sparkSession.sparkContext.defaultParallelism)
    ordered = keys.repartitionByRange(shards, key).sortWithinPartitions(key).withColumn("_m", F.monotonically_increasing_id())
    table = written(ordered.select("*", F.shiftright("_m", 33).cast("int").alias("shard")).withColumn("_at", F.col("_m").bitwiseAND(F.lit((1 << 33) - 1))).drop("_m"))
    # one row for each shard
    parts = sorted(table.groupBy("shard").agg(F.count("*").alias("n"), F.min(key).alias("first")).collect(), key=lambda r: r["shard"])
    offset, total = {}, 0
    for r in parts:
        offset[r["shard"]] = total
        total += r["n"]
    before = F.get(F.array(*(F.lit(offset.get(s, 0)).cast("long") for s in range(shards))), F.col("shard"))
    firsts = [bytes(r["first"]) if isinstance(r["first"], bytearray) else r["first"] for r in parts[1:]]
    return Ranked(table.withColumn("rank", F.col("_at") + before).drop("_at"), firsts, total)


def with_neighbours(ranked: Ranked) -> Ranked:
    """The ranked keys with p and q, the keys before and after, null at the ends, as a written table; edges of shards come from a table with one row for each."""
    by = Window.orderBy("shard")
    edges = ranked.rows.groupBy("shard").agg(F.min("key").alias("_a"), F.max("key").alias("_b")).select("shard", F.lag("_b").over(by).alias("_before"), F.lead("_a").over(by).alias("_after"))
    own = Window.partitionBy("shard").orderBy("key")
    near = ranked.rows.join(F.broadcast(edges), "shard").select("key", "shard", "rank", F.coalesce(F.lag("key").over(own), F.col("_before")).alias("p"), F.coalesce(F.lead("key").over(own), F.col("_after")).alias("q"))
    return Ranked(written(near), ranked.bounds, ranked.n)


def with_rank(keys: DataFrame, key: str = "key") -> DataFrame:
    """keys with shard and rank 0..N-1 in key order."""
    return rank_keys(keys, key).rows


def prepare_keys(df: DataFrame, key: str = "key", sorted_input: bool = False) -> DataFrame:
    """The key set: distinct non-null keys; input that is known to be a sorted set passes as it is."""
    only = df.select(F.col(key).alias("key"))
    return only if sorted_input else only.where("key IS NOT NULL").distinct()


def pick_anchors(ranked: Ranked, t: int) -> DataFrame:
    """(anchor_no, key, is_sentinel): every t-th key, and the greatest key as closing anchor where it isn't one."""
    picked = ranked.rows.where((F.col("rank") % t == 0) | (F.col("rank") == ranked.n - 1))
    return picked.select(F.ceil(F.col("rank") / t).cast("long").alias("anchor_no"), "key", (F.col("rank") % t != 0).alias("is_sentinel"))


def block_bounds(anchors: DataFrame, bounds: list) -> DataFrame:
    """(block_id, pred, succ) of neighbouring anchors; the neighbour in the next shard comes from the shard directory."""
    dealt = anchors.withColumn("_s", shard_of(F.col("key"), bounds))
    firsts = dealt.groupBy("_s").agg(F.min("key").alias("_first"))
    after = firsts.select("_s", F.lead("_first").over(Window.orderBy("_s")).alias("_after"))
    order = Window.partitionBy("_s").orderBy("key")
    out = dealt.join(F.broadcast(after), "_s").select(F.col("anchor_no").alias("block_id"), F.col("key").alias("pred"), F.coalesce(F.lead("key").over(order), F.col("_after")).alias("succ"))
    return out.where("succ IS NOT NULL")


def predecessors(points: DataFrame, at: str, keys: DataFrame, key: str, payload: list[str], bounds: list) -> DataFrame:
    """points with the greatest key that is at most points.`at`, and that key's payload columns; null where there is none.

    An as-of join: keys and points meet in their shard, sorted, and the last key seen is carried on; a shard's points before its first key
    take the last key of the shards before.
    """
    tags = [c for c in points.columns]
    left = keys.select(F.col(key).alias("_x"), F.lit(0).alias("_t"), F.struct(F.col(key).alias("key"), *payload).alias("_k"), *(F.lit(None).cast(points.schema[c].dataType).alias(c) for c in tags))
    right = points.select(F.col(at).alias("_x"), F.lit(1).alias("_t"), F.lit(None).cast(left.schema["_k"].dataType).alias("_k"), *tags)
    both = left.union(right).withColumn("_s", shard_of(F.col("_x"), bounds))
    carry = Window.partitionBy("_s").orderBy("_x", "_t").rowsBetween(Window.unboundedPreceding, 0)
    last = left.withColumn("_s", shard_of(F.col("_x"), bounds)).groupBy("_s").agg(F.max_by("_k", "_x").alias("_m"))
    directory = both.sparkSession.range(len(bounds) + 1).select(F.col("id").cast("int").alias("_s")).join(last, "_s", "left")
    before = directory.select("_s", F.last("_m", ignorenulls=True).over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)).alias("_b"))
    seen = both.withColumn("_k", F.last("_k", ignorenulls=True).over(carry)).where("_t = 1")
    # one row for each shard
    return seen.join(F.broadcast(before), "_s").select(*tags, F.coalesce("_k", "_b").alias("_near")).select(*tags, F.col("_near.key").alias("near_key"), *(F.col(f"_near.{p}").alias(f"near_{p}") for p in payload))


def range_is_empty(queries: DataFrame, keys: DataFrame, bounds: list | None = None) -> DataFrame:
    """queries with `empty`: the greatest key up to hi is below lo, or there is none."""
    bounds = shard_bounds(keys) if bounds is None else bounds
    near = predecessors(queries, "hi", keys, "key", [], bounds)
    return near.withColumn("empty", F.coalesce(F.col("near_key") < F.col("lo"), F.lit(True))).drop("near_key")


def range_is_empty_until(queries: DataFrame, keys: DataFrame, step: str, bounds: list | None = None) -> DataFrame:
    """integer queries with `filled`, the least step of the keys inside, null if there is none: a range is empty as long as the steps are below it.

    What range_is_empty tells for the keys of each step and those before, for all steps at once: keys and queries meet in the shard of hi,
    and the greatest key of each step in the shards before comes from a table with one row for each shard and step.
    """
    bounds = shard_bounds(keys) if bounds is None else bounds
    placed = keys.select(shard_of(F.col("key"), bounds).alias("_s"), F.col("key").alias("_key"), F.col(step).cast("int").alias("_step"))
    before: dict[int, list[tuple[int, int]]] = {}
    for r in placed.groupBy("_s", "_step").agg(F.max("_key").alias("_key")).collect():
        before.setdefault(r["_step"], []).append((r["_s"], r["_key"]))
    names = queries.columns
    schema = T.StructType([*queries.schema.fields, T.StructField("filled", T.IntegerType())])

    def one(held: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        filled = np.full(len(asked), -1, np.int32)
        if len(asked):
            shard, lo, hi = int(asked["_s"].iloc[0]), asked["lo"].to_numpy(np.int64), asked["hi"].to_numpy(np.int64)
            of = held["_step"].to_numpy()
            # the least step comes last
            for s in sorted(before, reverse=True):
                inner = np.sort(held["_key"].to_numpy()[of == s]).astype(np.int64)
                at = np.searchsorted(inner, hi, side="right") - 1
                found = np.zeros(len(asked), bool)
                if len(inner):
                    found = (at >= 0) & (inner[np.maximum(at, 0)] >= lo)
                if (last := max((k for t, k in before[s] if t < shard), default=None)) is not None:
                    found |= (lo <= last) & (last <= hi)
                filled[found] = s
        return asked[names].assign(filled=filled)

    met = placed.groupBy("_s").cogroup(queries.withColumn("_s", shard_of(F.col("hi"), bounds)).groupBy("_s")).applyInPandas(one, schema)
    return met.withColumn("filled", F.when(F.col("filled") >= 0, F.col("filled")))


def prefix_hash_table(anchors: DataFrame, width: int, group: int) -> DataFrame:
    """(plen, prefix, least, most): every prefix of the first anchor of each group of `group` anchors, as a fast trie keeps them."""
    firsts = anchors.where(F.col("anchor_no") % group == 0)
    shifted = F.expr(f"shiftright(key, {width} - plen)")
    return firsts.select("key", F.explode(F.sequence(F.lit(0), F.lit(width))).alias("plen")).select("plen", shifted.alias("prefix"), "key").groupBy("plen", "prefix").agg(F.min("key").alias("least"), F.max("key").alias("most"))


def longest_prefix_rounds(points: DataFrame, at: str, prefixes: DataFrame, width: int) -> DataFrame:
    """points with the length of the longest prefix in the table, by binary search over lengths: one equi-join for each halving."""
    now = points.withColumn("_lo", F.lit(0)).withColumn("_hi", F.lit(width))
    have = prefixes.select(F.col("plen").alias("_p"), F.col("prefix").alias("_q")).withColumn("_hit", F.lit(True))
    for _ in range(width.bit_length()):
        now = now.withColumn("_mid", F.floor((F.col("_lo") + F.col("_hi") + 1) / 2).cast("int"))
        now = now.join(have, (F.col("_mid") == F.col("_p")) & (F.expr(f"shiftright({at}, {width} - _mid)") == F.col("_q")), "left")
        found = F.coalesce("_hit", F.lit(False)) | (F.col("_mid") == 0)
        now = now.withColumn("_lo", F.when(found, F.col("_mid")).otherwise(F.col("_lo"))).withColumn("_hi", F.when(found, F.col("_hi")).otherwise(F.greatest(F.col("_mid") - 1, F.col("_lo")))).drop("_p", "_q", "_hit", "_mid")
    return now.withColumnRenamed("_lo", "prefix_len").drop("_hi")


#: Anchors that one task may hold to search them itself: 8 MB of integers.
BROADCAST_ANCHORS = 1 << 20


def search_anchors(points: DataFrame, at: str, anchors: DataFrame, key: str = "key", width: int = 62) -> DataFrame:
    """points with near_key, the greatest anchor at or before `at`, and steps, how many bytes a descent in a plain trie of them would read.

    For at most BROADCAST_ANCHORS integer anchors, which travel to every task as one sorted array; more are an error, and `predecessors`
    is the way for them.
    """
    n = anchors.count()
    if n > BROADCAST_ANCHORS:
        raise ValueError(f"{n} anchors are too many for one task")
    spark = points.sparkSession
    held = spark.sparkContext.broadcast(np.sort(anchors.select(key).toArrow().column(0).to_numpy()))
    top = -(-width // 8)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every = held.value
        for b in batches:
            x = b.column(b.schema.get_field_index(at)).to_numpy(zero_copy_only=False)
            i = np.searchsorted(every, x, side="right") - 1
            shared = np.zeros(len(x), np.int64)
            for k in (i, i + 1):
                inside = (k >= 0) & (k < len(every))
                other = every[np.clip(k, 0, max(0, len(every) - 1))] if len(every) else x
                apart = (x ^ other).astype(np.uint64)
                same = np.sum([(apart >> np.uint64(8 * (top - 1 - j))) == 0 for j in range(top)], axis=0)
                shared = np.maximum(shared, np.where(inside, same, 0))
            near = pa.array(every[np.clip(i, 0, max(0, len(every) - 1))] if len(every) else x, pa.int64(), mask=i < 0)
            yield pa.RecordBatch.from_arrays([*b.columns, near, pa.array(np.minimum(shared + 1, top).astype(np.int32))], names=[*b.schema.names, "near_key", "steps"])

    schema = T.StructType([*points.schema.fields, T.StructField("near_key", T.LongType()), T.StructField("steps", T.IntegerType())])
    return points.mapInArrow(run, schema)
