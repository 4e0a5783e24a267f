"""Dyadic filters as packed bitmaps: the same hashes, the same answers as by joins, and no more prefixes than a range needs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangesieve.baselines import filters
from rangesieve.functions import md5


@pytest.mark.parametrize("few", [0, 1000])
def test_hashes_equal_those_of_spark(spark, monkeypatch, few):
    monkeypatch.setattr(md5, "FEW", few)
    numbers = [0, 9, 10, 99, 12345, 10**17, 10**18 - 1, 2**62, 2**63 - 1, -1, -(2**63)]
    df = spark.createDataFrame([(level, x) for level in (0, 7, 12) for x in numbers], "level long, x long")
    # the last text takes more than one block of md5
    for word in ("bit0", "word1", "w" * 50):
        rows = df.select("level", "x", filters.salted(word, F.col("level"), F.col("x")).alias("h")).collect()
        got = md5.h60_numbers(word, np.array([r["level"] for r in rows]), np.array([r["x"] for r in rows]))
        assert got.tolist() == [r["h"] for r in rows]


@pytest.mark.parametrize("cls", [filters.DyadicBloom, filters.SharedDyadicBitmap, filters.PrefixHashBitmap])
def test_packed_equals_joined(spark, monkeypatch, cls):
    keys = spark.range(0, 3000).select((F.col("id") * F.col("id") * 977 + F.col("id") % 7).alias("key"))
    # points, short and long ranges, one of more prefixes than are looked up, and one without an end
    asked = spark.createDataFrame([(i, i * 8_792_141, i * 8_792_141 + (0, 5, 700, 7000)[i % 4]) for i in range(1000)] + [(1000, 50, 100_000), (1001, 5, None)], "query_id long, lo long, hi long")
    monkeypatch.setattr(filters, "CHUNK", 16)
    packed = cls.build(keys, 10)
    got = sorted(map(tuple, packed.probe(asked).collect()))
    monkeypatch.setattr(filters, "PACKED_BITS", 0)
    joined = cls.build(keys, 10)
    assert packed.rows.columns != joined.rows.columns and packed.bits() == joined.bits()
    assert got == sorted(map(tuple, joined.probe(asked).collect())) and {p for _, p in got} == {True, False}


def test_a_walk_finds_what_a_search_of_all_points_finds(monkeypatch):
    rng, layout = np.random.default_rng(3), filters.Layout(4, 1, 64, 64, False)
    sets = [set(rng.choice(2000 >> level, (1500 >> level) // (4 if not level else 1), replace=False).tolist()) for level in range(5)]
    lo = rng.integers(0, 1900, 300)
    hi = lo + rng.integers(0, 60, 300)
    monkeypatch.setattr(filters, "POOL", 8)
    got = filters.walk(lo, hi, layout, lambda level, prefix: np.array([p in sets[v] for v, p in zip(level.tolist(), prefix.tolist(), strict=True)], bool))
    want = [any(all(x >> level in sets[level] for level in range(5)) for x in range(a, b + 1)) for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
    assert got.tolist() == want and {True, False} == set(want)


def test_a_walk_ends_at_the_first_point():
    """Where the levels are crowded a range's prefixes are many; only those on the way to the first point are looked up."""
    looked, layout = [], filters.Layout(7, 2, 64, 64, False)
    lo = np.arange(100) * 100_003
    got = filters.walk(lo, lo + 7000, layout, lambda level, prefix: looked.append(len(prefix)) or np.ones(len(prefix), bool))
    assert got.all() and sum(looked) == 8 * 100
