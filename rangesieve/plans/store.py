"""A catalogue of filters as versioned tables: static filters as packed blocks, dynamic ones as shard states."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.base import BaseFilter
from ..operators.dynamic import DynamicFilter


def save_base(f: BaseFilter, path: str) -> None:
    """anchors, blocks, infixes and the parameters, as tables under path."""
    spark = f.blocks.sparkSession
    for name in ("anchors", "blocks", "infixes"):
        getattr(f, name).write.mode("overwrite").parquet(f"{path}/{name}")
    bounds = [bytes(b).hex() if f.binary else str(b) for b in f.bounds]
    spark.createDataFrame([(f.t, f.r, f.drop_redundant, f.binary, bounds)], "t int, r int, drop_redundant boolean, binary boolean, bounds array<string>").write.mode("overwrite").parquet(f"{path}/parameters")


def load_base(spark: SparkSession, path: str) -> BaseFilter:
    p = spark.read.parquet(f"{path}/parameters").first()
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    return BaseFilter(read("anchors"), read("blocks"), read("infixes"), [bytes.fromhex(b) if p["binary"] else int(b) for b in p["bounds"]], p["t"], p["r"], p["drop_redundant"], p["binary"])


def commit(f: DynamicFilter, path: str, version: int) -> DynamicFilter:
    """Writes the shard states as one version and gives the filter that reads it."""
    spark = f.state.sparkSession
    f.state.write.mode("overwrite").parquet(f"{path}/version={version}")
    return DynamicFilter(spark.read.schema(f.state.schema).parquet(f"{path}/version={version}"), f.bounds, f.t, f.r, f.options)


def as_table(verdicts: DataFrame, path: str) -> None:
    verdicts.write.mode("append").parquet(path)
