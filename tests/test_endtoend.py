"""Files of the key-value table, and what the registered queries read."""

import bisect

import pytest
from pyspark.sql import functions as F

from rangesieve import endtoend
from rangesieve.functions.geometry import Geometry
from rangesieve.operators.blocks import Block
from rangesieve.plans import prune

D = "/root/testdata/sf0.001"


def test_a_file_holds_the_keys_of_one_number(spark):
    path = endtoend.sorted_files(spark, D)
    number = F.pmod(F.col("key"), F.lit(endtoend.FILES)).alias("number")
    pairs = spark.read.parquet(path).select(F.col("_metadata.file_path").alias("file"), number).distinct().collect()
    assert len(pairs) == len({r["file"] for r in pairs}) == len({r["number"] for r in pairs}) == endtoend.FILES


def test_many_queries_meet_rows_in_many_cells(spark, tmp_path, monkeypatch):
    spark.range(0, 40_000, 2).selectExpr("(id * 48271) % 2147483647 AS key").repartition(4, "key").sortWithinPartitions("key").write.parquet(f"{tmp_path}/t")
    key = F.col("id") * 48271 % 2147483647
    asked = spark.range(10_000).select(F.col("id").alias("query_id"), key.alias("lo"), (key + F.col("id") % 3).alias("hi")).cache()
    filters = prune.file_filters(spark, f"{tmp_path}/t", "key").cache()
    seen, real = [], prune.met_in_shards
    monkeypatch.setattr(prune, "met_in_shards", lambda q, s, a, b, bounds: seen.append(len(bounds)) or real(q, s, a, b, bounds))
    survivors = prune.surviving_files(filters, asked)
    found = prune.guarded_lookup(spark, f"{tmp_path}/t", "key", asked, filters, survivors)
    keys = sorted(r[0] for r in spark.read.parquet(f"{tmp_path}/t").collect())
    hits = lambda lo, hi: bisect.bisect_right(keys, hi) - bisect.bisect_left(keys, lo)
    assert found.count() == sum(hits(r["lo"], r["hi"]) for r in asked.collect())
    assert min(seen) >= 100

    # the answers are those of one block for one query at a time
    want = set()
    for f in filters.collect():
        g, block = Geometry(f["pred"], f["succ"], 62, 16), Block.from_bytes(8, f["q_base"], f["q_count"], f["n_keys"], f["occupieds"], f["runends"], f["slots"])
        for q in asked.where((F.col("hi") >= f["pred"]) & (F.col("lo") <= f["succ"])).collect():
            ends = q["lo"] <= f["pred"] <= q["hi"] or q["lo"] <= f["succ"] <= q["hi"]
            if ends or f["n_keys"] and block.probe(g.infix(max(q["lo"], f["pred"])), g.infix(min(q["hi"], f["succ"]))) != "none":
                want.add((q["query_id"], f["file"]))
    assert set(map(tuple, survivors.collect())) == want


def test_doublings_ask_one_table_of_ranges(spark, monkeypatch):
    class Stage:
        def probe(self, asked):
            return asked.select("query_id", F.lit(True).alias("positive"))

        def stats(self):
            return spark.sql("SELECT 1L AS bits, 1L AS entries, 2L AS slots")

    made, keys = [], spark.range(100).select(F.col("id").alias("key"))
    monkeypatch.setattr(endtoend, "_stages", lambda *a, **o: [(step, Stage(), keys) for step in (0, 1, 2)])
    monkeypatch.setattr(endtoend.k, "integer_keys", lambda *a: made.append(a) or keys)
    rows = endtoend._by_doubling(spark, D).collect()
    assert len(made) == 1 and [(r["n_empty"], r["false_positives"], r["false_negatives"]) for r in rows] == [(100, 100, 0)] * 6


def _long_words(spark, tmp_path):
    """Five words: three are longer than 32 bytes, of which two share these, and one has 3,000."""
    long = "abc" + "x" * 40
    spark.createDataFrame([(f"{long} abcd {long}Y",), ("abc" + "z" * 2997,), ("abc",)], "text string").write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_inserts_count_words_of_any_length(spark, tmp_path):
    cases = {r["case"]: r["n"] for r in endtoend._case_counts(spark, _long_words(spark, tmp_path)).collect()}
    assert sum(cases.values()) == 5


def test_deletes_take_words_of_any_length(spark, tmp_path, monkeypatch):
    seen, real = [], endtoend.enhanced_updates
    monkeypatch.setattr(endtoend, "enhanced_updates", lambda keys: seen.append(keys) or real(keys))
    assert [r["missed_after"] for r in endtoend._enh_delete(spark, _long_words(spark, tmp_path)).collect()] == [0]
    assert sorted(len(r["key"]) for r in seen[0].collect()) == [3, 4, 43, 44, 3000]


def test_insert_cases_and_their_sql_count_words_of_any_length(spark, tmp_path):
    duckdb = pytest.importorskip("duckdb")
    d = _long_words(spark, tmp_path)
    (found,) = endtoend._cases(spark, d).collect()
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{d}/documents.parquet/*.parquet'")
    assert tuple(found) == con.execute(endtoend._WORD_COUNT).fetchone() == (5, 0)
