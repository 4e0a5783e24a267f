"""Guarded lookups: range queries read a file only if its own filter can't rule them out."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.geometry import Geometry
from ..operators.anchors import shard_bounds, shard_of
from ..operators.blocks import Block

#: Queries of a cell in which they meet rows or blocks, and cells at most; more queries make fuller cells, none is left out.
CELL_QUERIES, CELLS = 64, 4096
#: Queries that one row brings to a block, about.
BLOCK_QUERIES = 1 << 16
FILTERS = "file string, pred long, succ long, q_base long, q_count int, n_keys int, occupieds binary, runends binary, slots binary"


def predicate_range(op: str, value: int, width: int = 62) -> tuple[int, int]:
    """[lo, hi] of a comparison of an integer key."""
    top = (1 << width) - 1
    return {"=": (value, value), "<": (0, value - 1), "<=": (0, value), ">": (value + 1, top), ">=": (value, top)}[op]


def prefix_range(prefix: bytes, length: int) -> tuple[bytes, bytes]:
    """[lo, hi] of the byte strings of at most `length` bytes that begin with a prefix."""
    return prefix, prefix.ljust(length, b"\xff")


def file_keys(spark: SparkSession, path: str, key: str) -> DataFrame:
    """(file, key) of a table, distinct."""
    return spark.read.parquet(path).select(F.col("_metadata.file_path").alias("file"), F.col(key).cast("long").alias("key")).where("key IS NOT NULL").distinct()


def file_filters(spark: SparkSession, path: str, key: str, t: int = 256, r: int = 8) -> DataFrame:
    """FILTERS rows, one for each block of t keys of each file of a table whose key is a BIGINT; no task holds more than a block."""
    m = r + max(1, (t - 1).bit_length())
    order = Window.partitionBy("file").orderBy("key")
    ranked = file_keys(spark, path, key).withColumn("block", F.floor((F.row_number().over(order) - 1) / t))
    # t keys at most
    lists = ranked.groupBy("file", "block").agg(F.sort_array(F.collect_list("key")).alias("keys"))
    after = F.lead(F.col("keys")[0]).over(Window.partitionBy("file").orderBy("block"))
    bounded = lists.select("file", F.col("keys")[0].alias("pred"), F.coalesce(after, F.array_max("keys")).alias("succ"), "keys")

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for file, low, high, keys in zip(*(b.column(c).to_pylist() for c in ("file", "pred", "succ", "keys")), strict=True):
                inner = [x for x in keys if low < x < high]
                if not inner:
                    out.append((file, low, high, 0, 0, 0, b"", b"", b""))
                    continue
                g = Geometry(low, high, 62, m)
                packed = Block.pack(g.infix(np.array(inner, dtype=np.int64)), g.low, g.high, r)
                out.append((file, low, high, packed.q_base, len(packed.occupieds), len(packed.slots), *packed.to_bytes()))
            kinds = (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)] if out else [pa.array([], k) for k in kinds], names=[f.split()[0] for f in FILTERS.split(", ")])

    return bounded.mapInArrow(build, FILTERS)


def cell_bounds(queries: DataFrame) -> list:
    """Bounds for met_in_shards: their number follows from the queries, as each row of a shard is compared with all queries there."""
    return shard_bounds(queries, "lo", shards=max(1, min(CELLS, queries.count() // CELL_QUERIES)))


def met_in_shards(queries: DataFrame, spans: DataFrame, low: str, high: str, bounds: list) -> DataFrame:
    """queries x spans that overlap: both are dealt to the shards that they touch and meet there by an equi-join.

    A pair that meets in several shards comes out once, in the shard where the later of both begins.
    """
    many = lambda a, b: shard_of(F.col(a), bounds) if a == b else F.explode(F.sequence(shard_of(F.col(a), bounds), shard_of(F.col(b), bounds)))
    q, s = queries.withColumn("_s", many("lo", "hi")), spans.withColumn("_t", many(low, high))
    joined = q.join(s, (F.col("_s") == F.col("_t")) & (F.col("hi") >= F.col(low)) & (F.col("lo") <= F.col(high)))
    return joined.where(F.col("_s") == F.greatest(shard_of(F.col("lo"), bounds), shard_of(F.col(low), bounds))).drop("_s", "_t")


def surviving_files(filters: DataFrame, queries: DataFrame, t: int = 256, r: int = 8, min_max_only: bool = False) -> DataFrame:
    """(query_id, file): the files that may hold a key of a query's range; min and max alone rule out the first, the blocks the rest."""
    m = r + max(1, (t - 1).bit_length())
    spans = filters.groupBy("file").agg(F.min("pred").alias("pred"), F.max("succ").alias("succ")) if min_max_only else filters
    met = met_in_shards(queries.select("query_id", "lo", "hi"), spans.select("file", "pred", "succ"), "pred", "succ", cell_bounds(queries))
    if min_max_only:
        return met.select("query_id", "file").distinct()
    # a block is read once for many queries; BLOCK_QUERIES in a row, about
    some = F.pmod(F.xxhash64("query_id"), F.lit(1 + queries.count() // BLOCK_QUERIES))
    asked = met.groupBy("file", "pred", some.alias("_part")).agg(F.collect_list(F.struct("query_id", "lo", "hi")).alias("asked")).join(filters, ["file", "pred"])

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(b.schema.get_field_index("asked"))
            ids, lows, highs = lists.flatten().flatten()
            lows, highs = lows.to_numpy(zero_copy_only=False), highs.to_numpy(zero_copy_only=False)
            size = lists.value_lengths().to_numpy(zero_copy_only=False)
            ends, keep = np.cumsum(size), np.zeros(len(ids), dtype=bool)
            fields = zip(*(b.column(b.schema.get_field_index(c)).to_pylist() for c in ("pred", "succ", "q_base", "q_count", "n_keys", "occupieds", "runends", "slots")), strict=True)
            for start, end, (pred, succ, base, count, n, *raw) in zip((ends - size).tolist(), ends.tolist(), fields, strict=True):
                lo, hi = lows[start:end], highs[start:end]
                hit = ((lo <= pred) & (pred <= hi)) | ((lo <= succ) & (succ <= hi))
                if n:
                    g = Geometry(pred, succ, 62, m)
                    # a positive answer of Block.probe: an infix between those of the ends
                    infixes = Block.from_bytes(r, base, count, n, *raw).infixes()
                    hit |= np.searchsorted(infixes, g.infix(np.maximum(lo, pred))) < np.searchsorted(infixes, g.infix(np.minimum(hi, succ)), side="right")
                keep[start:end] = hit
            files = b.column(b.schema.get_field_index("file")).take(pa.array(np.repeat(np.arange(b.num_rows), size)[keep]))
            yield pa.RecordBatch.from_arrays([ids.filter(pa.array(keep)), files], names=["query_id", "file"])

    return asked.mapInArrow(ask, f"query_id {queries.schema['query_id'].dataType.simpleString()}, file string").distinct()


def guarded_lookup(spark: SparkSession, path: str, key: str, queries: DataFrame, filters: DataFrame, survivors: DataFrame | None = None) -> DataFrame:
    """Rows of the table in any of the query ranges, read from the surviving files only; the file list is metadata."""
    survivors = surviving_files(filters, queries) if survivors is None else survivors
    files = sorted(r["file"] for r in survivors.select("file").distinct().collect())
    rows = spark.read.parquet(*files) if files else spark.read.parquet(path).limit(0)
    spread = rows.withColumn("_low", F.col(key).cast("long"))
    return met_in_shards(queries.select("query_id", "lo", "hi"), spread, "_low", "_low", cell_bounds(queries)).drop("_low")


def read_cost(spark: SparkSession, path: str, key: str, survivors: DataFrame) -> tuple[int, int]:
    """(files, rows) that all queries together read when each opens its surviving files."""
    sizes = spark.read.parquet(path).groupBy(F.col("_metadata.file_path").alias("file")).agg(F.count(key).alias("n"))
    r = survivors.join(sizes, "file").agg(F.count("*").alias("files"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows")).first()
    return r["files"], r["rows"]
