"""Static and dynamic filters and the comparison filters on the smallest tables: no false negatives, equal forms."""

import pytest
from pyspark.sql import functions as F

from rangesieve import catalogue
from rangesieve.baselines import filters as baselines
from rangesieve.operators.anchors import range_is_empty
from rangesieve.operators.base import BaseFilter
from rangesieve.sources import keysets as k

D = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["uniform", "clustered"])
def test_base_filter(spark, name):
    keys, asked = k.range_queries(k.integer_keys(spark, D, name), "mixed", 1 << 10)
    f = BaseFilter.build(keys, t=64, eps=2 / 256)
    rows = range_is_empty(asked, keys).join(f.probe(asked), "query_id").join(f.probe_packed(asked).select("query_id", F.col("positive").alias("p")), "query_id").collect()
    assert rows and all(r["positive"] == r["p"] for r in rows) and all(r["positive"] for r in rows if not r["empty"])


@pytest.mark.parametrize("cls", [baselines.TruncatedTrie, baselines.LocalHashSet, baselines.PrefixSuffixTable])
def test_comparison_filters(spark, cls):
    keys, asked = k.range_queries(k.integer_keys(spark, D, "skewed"), "mixed", 1 << 7)
    rows = range_is_empty(asked, keys).join(cls.build(keys).probe(asked), "query_id").collect()
    assert rows and all(r["positive"] for r in rows if not r["empty"])


def test_empty_key_set_is_negative(spark):
    keys = spark.createDataFrame([], "key long")
    asked = spark.createDataFrame([(1, 5, 9)], "query_id long, lo long, hi long")
    assert not BaseFilter.build(keys, t=8, eps=0.01).probe(asked).first()["positive"]


def test_every_oracle_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())
