"""What the operators share: cutting lineage in the shared folder, packed hash exchanges, connected components."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _shared_folder(spark: SparkSession) -> str:
    """The cluster's shared checkpoint folder; where none is set, one process may use a folder of its own, as tests do, and a cluster may not."""
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir")
        if folder is None and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """df as a compressed table in the shared folder: every executor can read it, and none has to compute it again.

    The tables lie under the session's own checkpoint folder and go when the driver ends.
    """
    spark = df.sparkSession
    path = f"{_shared_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    if path not in _written:
        _written.append(path)
        if len(_written) == 1:
            atexit.register(_clear, spark)
    return spark.read.schema(df.schema).parquet(path)


_written: list[str] = []


def _clear(spark: SparkSession) -> None:
    """Removes this driver's tables, if its session still runs."""
    context = spark.sparkContext
    if context._jsc is None or context._jsc.sc().isStopped():
        return
    for path in _written:
        at = context._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(context._jsc.hadoopConfiguration()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def hex_sha256(column: Column | str) -> Column:
    return F.sha2(F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit("")), 256)


def joined_to_key(rows: DataFrame, key: str, found: DataFrame, copies: int = 16) -> DataFrame:
    """rows with the columns of found, which has one row for some of the keys; rows of one key are spread over `copies` tasks.

    key: a column of both, which the result keeps.
    """
    salt = F.pmod(F.monotonically_increasing_id(), F.lit(copies)).cast("int")
    many = found.select(F.col(key).alias("_join_key"), *(F.col(c) for c in found.columns if c != key), F.explode(F.array(*map(F.lit, range(copies)))).alias("_join_copy"))
    return rows.withColumn("_join_salt", salt).join(many, (F.col(key) == F.col("_join_key")) & (F.col("_join_salt") == F.col("_join_copy")), "left").drop("_join_salt", "_join_copy", "_join_key")


#: Bits of the table that thins out rows before an exchange: 1 MB, whatever the data.
SIEVE_BITS = 1 << 23


def sifted(df: DataFrame, column: str, wanted: DataFrame, wanted_column: str) -> DataFrame:
    """The rows of df whose `column` may be among the wanted values; a join must follow.

    Rows that no wanted value can match stay out of the exchange.  The broadcast table has SIEVE_BITS bits; with far more wanted values
    than that it lets everything pass, and the join does the work.
    """
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(SIEVE_BITS)) + 1
    held = wanted.select(place(wanted_column).alias("p")).groupBy(F.bitmap_bucket_number("p").alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("_bits"))
    bit = F.bitmap_bit_position(place(column))
    byte = F.conv(F.hex(F.substring(F.col("_bits"), (F.floor(bit / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    joined = df.join(F.broadcast(held), F.bitmap_bucket_number(place(column)) == F.col("_bucket"))
    return joined.where(F.call_function("shiftright", byte, (bit % 8).cast("int")).bitwiseAND(F.lit(1)) == 1).drop("_bucket", "_bits")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest node that is reachable over `edges` (a, b), for each node of an edge.

    Alternates two star contractions until the edge set is a forest of stars; each round is two aggregations over the
    edges, the number of rounds is logarithmic, and no component is gathered in one place.
    """
    both = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    both = cut_lineage(both)
    state = None
    for _ in range(max_rounds):
        mirrored = both.union(both.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = mirrored.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = mirrored.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        smaller = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(smaller, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        both = cut_lineage(small)
        now = both.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    else:
        raise RuntimeError("components did not converge")
    return both.select(F.col("u").alias("node"), F.col("v").alias("component")).union(both.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
