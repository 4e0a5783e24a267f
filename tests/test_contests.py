"""Registered queries against their SQL on the smallest tables, and deletes of comparison filters whose keys share rows."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

from rangesieve import catalogue
from rangesieve.baselines import filters as baselines
from rangesieve.functions.udfs import dyadic_nodes
from rangesieve.operators.anchors import rank_keys, shard_of

D = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = (
    "setop_except", "json_key_ranges", "host_reverse", "pred_to_ranges", "dyadic_cover", "base_local_hash", "base_prefix_suffix", "base_spline_bitmap", "base_truncated_trie", "base_point_bloom",
    "join_asof", "stream_dedup_late", "neighbour_ranks", "lemma_infix_counts", "prune_files", "dyn_promoted_anchors", "theory_memory", "goal_matrix", "occupieds_bitmap",
)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", QUICK)
def test_query_agrees_with_sql(spark, duck, name):
    want = duck.execute(catalogue.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    plain = lambda rows: sorted(tuple(round(x, 6) if isinstance(x, float) else float(x) if hasattr(x, "as_tuple") else x for x in r) for r in rows)
    assert plain(map(tuple, catalogue.queries()[name](spark, D).select(*columns).collect())) == plain(want.fetchall())


@pytest.mark.parametrize("make", [lambda k: baselines.SplineBitmap.build(k, 6), lambda k: baselines.PrefixSuffixTable.build(k, 6, 8), lambda k: baselines.PrefixSuffixTableExtraBit.build(k, 6, 8)])
def test_delete_keeps_keys_that_share_a_row(spark, make):
    keys = spark.range(0, 2000).select((F.col("id") % 50 + F.floor(F.col("id") / 50) * 10_000).alias("key"))
    gone = keys.where("key % 3 = 0")
    f = make(keys).delete(gone)
    left = keys.where("key % 3 <> 0").select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
    assert make(keys).rows.agg(F.max("copies")).first()[0] > 1
    assert f.probe(left).where("not positive").count() == 0
    again = f.insert(gone)
    every = keys.select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
    assert again.probe(every).where("not positive").count() == 0


def test_ranks_and_shards(spark):
    keys = spark.range(0, 70_000).select((F.col("id") * 7919 % 70_001).alias("key"))
    ranked = rank_keys(keys)
    rows = ranked.rows.collect()
    assert [r["rank"] for r in sorted(rows, key=lambda r: r["key"])] == list(range(70_000)) == list(range(ranked.n))
    assert len(ranked.bounds) >= 1
    found = ranked.rows.where(shard_of(F.col("key"), ranked.bounds) != F.col("shard")).count()
    many = list(range(0, 70_000, 500))
    wrong = keys.where(shard_of(F.col("key"), many) != F.floor(F.col("key") / 500) + 1).where("key < 70000").count()
    assert found == 0 and wrong == 0


def test_dyadic_nodes_cover():
    for lo, hi in ((0, 0), (0, 31), (5, 5), (3, 100), (64, 127), (1, 4096)):
        values = [x for level, p in dyadic_nodes(lo, hi, 5) for x in range(p << level, (p + 1) << level)]
        assert values == list(range(lo, hi + 1)) and all(level <= 5 for level, _ in dyadic_nodes(lo, hi, 5))
        assert sum(1 for _ in dyadic_nodes(lo, hi, 62)) <= 2 * max(1, math.ceil(math.log2(hi - lo + 2)))
