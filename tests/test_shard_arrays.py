"""The arrays of a shard hold and answer what the filter that works key by key does, and truth for all doublings is that of each."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangesieve.operators.anchors import range_is_empty, range_is_empty_until
from rangesieve.operators.dynamic import _COLUMNS, DynamicFilter, ShardFilter, _ask, _change
from rangesieve.operators.shardarrays import ShardArrays


@pytest.mark.parametrize("seed", range(24))
def test_inserts_and_probes_are_those_of_single_keys(seed):
    rng = random.Random(seed)
    t, r, width, skewed = rng.choice([4, 16, 64]), rng.choice([2, 4, 8]), rng.choice([32, 62]), seed % 2
    options = {"widening": rng.choice(["none", "per_doubling"]), "expansion": rng.choice(["stretch", "double"]), "promotion": rng.choice(["hash", "hash", "counter"]), "seed": seed}
    draw = lambda: (int(rng.random() ** 3 * 4000) << (width - 16)) + rng.randrange(1, 1 << 10) if skewed else rng.randrange(0, (1 << width) - 1)
    f = ShardFilter.build(sorted({draw() for _ in range(rng.choice([0, 5, 60]))}), 0, (1 << width) - 1, t, r, width, **options)
    rows = f.rows(0, 0)
    for step in range(4):
        arrays = ShardArrays.from_rows(rows, t, r, width, **options)
        keys = sorted({draw() for _ in range(rng.choice([0, 3, 300, 900]))} | ({0} if step == 2 else set()))
        for x in keys:
            _change(f, "insert", x, False)
        arrays.insert(np.array(keys, np.int64))
        rows = arrays.rows(3, step, _COLUMNS)
        for c, column in f.rows(3, step).items():
            assert column.tolist() == rows[c].tolist(), c
        asked = [(x, x + rng.choice([0, 1, 100, 1 << 12, 1 << 20])) for x in [draw() for _ in range(200)] + [max(0, x - rng.randrange(200)) for x in keys[:100]]]
        assert arrays.positive(*np.array(asked).T).tolist() == [_ask(f, *q) for q in asked]
        assert arrays.stats() == f.stats()


def test_keys_that_come_twice_and_ranges_over_shards(spark):
    keys = [7 * x * x + 3 for x in range(600)]
    f = DynamicFilter.build(spark.createDataFrame([(x,) for x in keys[::3]], "key long"), t=16, r=8, bounds=[keys[200], keys[400]])
    f = f.insert(spark.createDataFrame([(x,) for x in keys[1::3] * 2 + keys[2::3]], "key long"))
    asked = [(i, x - 2, x) for i, x in enumerate(keys)] + [(1000, keys[100], keys[500]), (1001, 1 << 60, (1 << 60) + 9)]
    found = {r["query_id"]: r for r in f.judged(spark.createDataFrame([(*q, "kept") for q in asked], "query_id long, lo long, hi long, note string")).collect()}
    assert len(found) == len(asked) and {r["note"] for r in found.values()} == {"kept"}
    assert all(found[i]["positive"] for i in (*range(600), 1000)) and not found[1001]["positive"]


def test_truth_for_all_steps_at_once(spark):
    rng = random.Random(5)
    keys = spark.createDataFrame([(x, rng.randrange(7)) for x in rng.sample(range(100_000), 3000)], "key long, step int").cache()
    asked = spark.createDataFrame([(i, lo, lo + rng.choice([0, 5, 60, 30_000])) for i, lo in enumerate(rng.randrange(-50, 101_000) for _ in range(2000))], "query_id long, lo long, hi long").cache()
    filled = {r["query_id"]: r["filled"] for r in range_is_empty_until(asked, keys, "step", [20_000, 20_010, 70_000]).collect()}
    for step in (0, 2, 6):
        empty = {r["query_id"]: r["empty"] for r in range_is_empty(asked, keys.where(F.col("step") <= step), [50_000]).collect()}
        assert empty == {i: s is None or s > step for i, s in filled.items()}
