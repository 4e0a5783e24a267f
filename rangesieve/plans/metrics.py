"""Accuracy, memory and shape measures as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import theory


def fpr(verdicts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Over verdicts (empty, positive, ...): queries, positives on empty ranges, their share, and false negatives."""
    wrong, missed = (F.col("empty") & F.col("positive")).cast("long"), (~F.col("empty") & ~F.col("positive")).cast("long")
    return verdicts.groupBy(*by).agg(F.count("*").alias("n_queries"), F.sum(F.col("empty").cast("long")).alias("n_empty"), F.sum(wrong).alias("false_positives"), F.sum(missed).alias("false_negatives"))


def verdicts(f: object, queries: DataFrame) -> DataFrame:
    """queries with the filter's answer, `positive`; a filter that keeps their columns needs no join."""
    return f.judged(queries) if hasattr(f, "judged") else queries.join(f.probe(queries.select("query_id", "lo", "hi")), "query_id")


def with_rate(measured: DataFrame) -> DataFrame:
    return measured.withColumn("fpr", F.round(F.col("false_positives") / F.greatest(F.col("n_empty"), F.lit(1)), 6))


def bits_per_key(bits: DataFrame, keys: DataFrame) -> DataFrame:
    n = keys.agg(F.count("*").alias("n"))
    # one row
    return bits.join(F.broadcast(n)).select("component", "bits", F.round(F.col("bits") / F.col("n"), 4).alias("bpk"))


def goal_matrix(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(theory.GOALS), "filter string, robust boolean, semi_robust boolean, any_length_queries boolean, any_length_keys boolean, dynamic boolean")


def runs(infixes: DataFrame, r: int) -> DataFrame:
    """(block_id, quotient, run_length) of a relational filter."""
    return infixes.groupBy("block_id", F.shiftright("infix", r).alias("quotient")).agg(F.count("*").alias("run_length"))


def identical_share(infixes: DataFrame) -> DataFrame:
    """(n, n_identical): infixes, and those that share theirs with another key of the block."""
    return infixes.groupBy("block_id", "infix").agg(F.count("*").alias("c")).agg(F.sum("c").alias("n"), F.coalesce(F.sum(F.when(F.col("c") > 1, F.col("c"))), F.lit(0)).alias("n_identical"))


def uniformity(infixes: DataFrame, m: int, bins_log2: int = 4) -> DataFrame:
    """(bin, n): how infixes spread over equal parts of their range; a chi-square statistic follows from it."""
    return infixes.groupBy(F.shiftright("infix", m - bins_log2).alias("bin")).agg(F.count("*").alias("n"))


def chi_square(spread: DataFrame) -> DataFrame:
    mean = F.avg("n").over(Window.partitionBy(F.lit(0)))  # as many rows as bins
    return spread.withColumn("_e", mean).agg(F.count("*").alias("bins"), F.sum("n").alias("n"), F.round(F.sum((F.col("n") - F.col("_e")) ** 2 / F.col("_e")), 3).alias("chi2"))


def gaps(keys: DataFrame, bounds: list) -> DataFrame:
    """(after, width): maximal empty ranges between neighbouring keys; shards are joined by a directory of their first keys."""
    from ..operators.anchors import block_bounds

    numbered = keys.withColumn("anchor_no", F.lit(0).cast("long"))
    return block_bounds(numbered, bounds).select(F.col("pred").alias("after"), (F.col("succ") - F.col("pred") - 1).alias("width")).where("width > 0")
