"""Filters of a contest share one sorted key set, and filters of ranked keys equal those of the same keys as they come."""

from rangesieve import catalogue
from rangesieve.baselines import filters
from rangesieve.operators.anchors import rank_keys, with_neighbours


def test_a_contest_sorts_its_keys_once(spark, monkeypatch):
    keys = spark.range(0, 2000).selectExpr("id * 977 AS key")
    sorts, real = [], type(keys).repartitionByRange
    monkeypatch.setattr(type(keys), "repartitionByRange", lambda self, *a: sorts.append(a) or real(self, *a))
    rows = catalogue._contests.contest(spark, keys, "held_out", ("base", "spline_bitmap"), (16,), (32,)).collect()
    assert len(sorts) == 1 and all(r["false_negatives"] == 0 for r in rows)


def test_inner_nodes_of_a_trie(spark):
    """Suffix bits that reach the end of the key don't take inner nodes away."""
    keys, width = list(range(0, 600)) + [1 << 40, (1 << 61) + 5], filters.WIDTH
    inner = set()
    for i, x in enumerate(keys):
        bare = max(width - (x ^ y).bit_length() for y in keys[max(0, i - 1) : i] + keys[i + 1 : i + 2]) + 1
        inner |= {(d, x >> (width - 8 * d)) for d in range((bare - 1) // 8 + 1)}
    df = spark.createDataFrame([(x,) for x in keys], "key long")
    for m in (0, 8):
        assert filters.TruncatedTrie.build(df, m).bits() == 10 * (len(keys) + len(inner)) + m * len(keys)


def test_ranked_keys_make_the_same_rows(spark):
    df = spark.createDataFrame([(x * x * 31 + (x % 5),) for x in range(400)], "key long")
    ranked = with_neighbours(rank_keys(df))
    for cls in (filters.DyadicBloom, filters.SharedDyadicBitmap, filters.PrunedSplineBitmap):
        a, b = cls.build(df), cls.build(ranked)
        assert sorted(map(tuple, a.rows.collect())) == sorted(map(tuple, b.rows.collect())) and a.bits() == b.bits()
