"""Sharding: contiguous shards of near-equal bytes, cut from a global prefix sum of sizes.

The rows are dealt into ranges of the key, every range reports one total, the totals are summed to range offsets, and
a running sum inside each range adds the rest.  A row belongs to the shard in which the middle of its bytes falls, so
every shard misses its equal target by less than one row at each end.

The ranges are cut at rows of a sample, so that a key that many rows share is cut too; they only balance the tasks.

Defined results: a null text has size 1; null keys come first; repeated rows each get a slot of their own; ties of
the key are ordered by size and then by a hash of the row; an empty table gives an empty result; further columns pass
through, and input columns named like an output column are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut_lineage, shuffle_width, table

LAW = "bytes"


def text_bytes(text: str = "text") -> Column:
    """UTF-8 bytes of the text plus one for its separator."""
    return (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + 1).cast("long")


def shard_by_bytes(docs: DataFrame, n_shards: int = 8, key: str = "doc_id", size: Column | None = None, ranges: int | None = None) -> DataFrame:
    """docs with size, shard and slot (position within the shard, from 0).

    ranges: how many key ranges are summed on their own; a few per task of the cluster.
    """
    spark = docs.sparkSession
    ranges = ranges or 4 * shuffle_width(spark)
    size = text_bytes() if size is None else size
    names = [c for c in docs.columns if c not in ("size", "shard", "slot")]
    plain = [F.col(f"`{f.name}`") for f in docs.schema.fields if f.name in names and f.dataType.typeName() in ("byte", "short", "integer", "long", "string", "date", "boolean")]
    sized = docs.select(*(F.col(f"`{c}`") for c in names), size.alias("size")).withColumn("_tie", F.xxhash64(F.col(f"`{key}`"), "size", *plain))
    light = cut_lineage(sized.select(F.col(f"`{key}`").alias("_key"), "size", "_tie"))

    place = F.struct("_key", "size", "_tie")
    rows = light.count()
    # some 20 rows for each range
    drawn = light.sample(fraction=min(1.0, 20 * ranges / max(rows, 1)), seed=11) if rows > 20 * ranges else light
    kind = light.select(place.alias("p")).schema["p"].dataType
    held = drawn.agg(F.array_sort(F.collect_list(place)).alias("all")).select(F.filter("all", lambda _, i: i % F.greatest(F.lit(1), F.floor(F.size("all") / ranges)) == 0).alias("b")).select(F.size("b").alias("n"), F.to_json("b").alias("b")).first()
    bounds = F.from_json(F.lit(held["b"] or "[]"), T.ArrayType(kind))

    def dealt(df: DataFrame, by: str) -> DataFrame:
        at = F.struct(F.col(f"`{by}`").alias("_key"), "size", "_tie")
        # how many bounds lie before the row, bit by bit
        steps = F.array(*(F.lit(1 << s) for s in reversed(range(held["n"].bit_length() or 1))))
        before = F.aggregate(steps, F.lit(0), lambda p, s: F.when((p + s <= held["n"]) & (F.get(bounds, p + s - 1) < at), p + s).otherwise(p))
        return df.withColumn("_range", before.cast("int"))

    totals = dealt(light, "_key").groupBy("_range").agg(F.sum("size").alias("_bytes"))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_range", F.coalesce(F.sum("_bytes").over(before), F.lit(0)).alias("_offset"))
    whole = light.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]

    def placed(df: DataFrame, by: str) -> DataFrame:
        order = Window.partitionBy("_range").orderBy(F.col(f"`{by}`").asc_nulls_first(), "size", "_tie")
        up_to = F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) + F.col("_offset")
        middle = (2 * up_to - F.col("size")).cast("decimal(38,0)") * n_shards
        at = F.least(F.lit(n_shards - 1), F.floor(middle / F.lit(max(2 * whole, 1)).cast("decimal(20,0)")))
        # at most `ranges` + 1 rows are broadcast
        return dealt(df, by).join(F.broadcast(offsets), "_range").withColumn("shard", at.cast("int"))

    pieces = placed(light, "_key").groupBy("shard", "_range").agg(F.count("*").alias("_rows"))
    earlier = Window.partitionBy("shard").orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    firsts = pieces.select("shard", "_range", F.coalesce(F.sum("_rows").over(earlier), F.lit(0)).alias("_first"))
    within = Window.partitionBy("_range", "shard").orderBy(F.col(f"`{key}`").asc_nulls_first(), "size", "_tie")
    # at most `ranges` + `n_shards` rows are broadcast
    out = placed(sized, key).join(F.broadcast(firsts), ["shard", "_range"]).withColumn("slot", (F.col("_first") + F.row_number().over(within) - 1).cast("long"))
    return out.select(*(F.col(f"`{c}`") for c in names), "size", "shard", "slot")


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", text_bytes().alias("n_bytes"), F.crc32(F.coalesce("text", F.lit(""))).alias("text_crc32"))
    out = shard_by_bytes(cut_lineage(docs), 8, size=F.col("n_bytes"))
    return out.select("doc_id", "size", "text_crc32", F.lit(LAW).alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


