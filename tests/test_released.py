"""Tables of one filter of a contest are gone before the next is built."""

from pyspark.sql import functions as F

from rangesieve import catalogue
from rangesieve.plans import lineage


def test_a_filters_tables_go_with_it(spark, monkeypatch):
    keys = spark.range(0, 3000).select((F.col("id") * 977).alias("key"))
    held = []
    real = catalogue._contests.CONTESTANTS["base"]
    monkeypatch.setitem(catalogue._contests.CONTESTANTS, "base", lambda k, b: held.append(len(lineage._written)) or real(k, b))
    rows = catalogue._contests.contest(spark, keys, "held_out", ("base",), (10, 16), (1, 32)).collect()
    assert len(rows) == 4 and all(r["false_negatives"] == 0 for r in rows)
    # the second budget finds only the key set and the queries, as the first did
    assert held[0] == held[1] == len(lineage._written)
