"""Code books of many contexts: what the driver holds for each is small, and the codes are those of all counts."""

import pickle

from pyspark.sql import functions as F

from rangesieve.functions.entropy import LEAST_CONTEXT, Codebook, bisection_codes, encode_columns, symbol_counts, to_bytes
from rangesieve.operators.enhanced import CodedKeys, EnhancedFilter


def test_book_of_many_contexts_is_packed(spark):
    keys = spark.range(0, 60_000).select(F.unhex(F.substring(F.sha2(F.col("id").cast("string"), 256), 1, 40)).alias("key"))
    book = Codebook.build(keys, 1)
    found: dict[bytes, dict[int, int]] = {}
    for r in symbol_counts(keys, 1).collect():
        found.setdefault(bytes.fromhex(r["context"]), {})[int(r["symbol"], 16)] = r["freq"]
    often = {c: x for c, x in found.items() if sum(x.values()) >= LEAST_CONTEXT}
    assert set(book.codes) == set(often) and len(often) == 257
    for c in list(often)[::16]:
        assert book.codes[c] == bisection_codes([(s, often[c].get(s, 0) + 1 / 256) for s in range(256)])
    # a code book travels to every task
    assert len(pickle.dumps(book.codes)) < 1500 * len(often)
    back = Codebook.from_rows(1, book.rows())
    assert all(back.encode(bytes(r["key"])) == book.encode(bytes(r["key"])) for r in keys.limit(50).collect())


def test_counts_of_long_keys(spark):
    keys = spark.createDataFrame([(b"",), (b"a",), (b"abc",), (bytes(range(256)) * 3,), (None,)], "key binary")
    for k in range(4):
        want: dict[tuple[str, str], int] = {}
        for x in (b"a", b"abc", bytes(range(256)) * 3):
            for i in range(len(x)):
                at = x[max(0, i - k) : i].hex().upper(), x[i : i + 1].hex().upper()
                want[at] = want.get(at, 0) + 1
        assert {(r["context"], r["symbol"]): r["freq"] for r in symbol_counts(keys, k).collect()} == want


def test_many_keys_are_coded_like_each(spark):
    keys = [b"", b"a", b"abc", b"abcabd" * 40, bytes(range(256)) * 3, "\u00fcber".encode()]
    df = spark.createDataFrame([(x,) for x in [*keys, None] * 40], "key binary")
    for k in range(4):
        book = Codebook.build(df, k)
        for b in (book, Codebook.from_rows(k, book.rows())):
            texts = [b.encode(x) for x in keys]
            assert b.encode_many(keys, {}) == ([to_bytes(x) for x in texts], texts)
    rows = {None if r["raw"] is None else bytes(r["raw"]): r for r in encode_columns(df.distinct().withColumn("raw", F.col("key")), ["key"], book).collect()}
    assert len(rows) == 7 and rows[None]["key"] is None and all(rows[x]["key_code"] == book.encode(x) for x in keys)


def test_filters_of_one_book_share_coded_keys(spark):
    keys = spark.range(3000).select(F.concat(F.lit("k"), F.sha2(F.col("id").cast("string"), 256)).alias("key"))
    asked = spark.range(3000, 4000).select(F.col("id").alias("query_id"), F.concat(F.lit("k"), F.sha2(F.col("id").cast("string"), 256)).alias("lo")).withColumn("hi", F.col("lo"))
    book = Codebook.build(keys, 2)
    coded = CodedKeys.prepare(keys, book=book)
    for tries in (False, True):
        one, other = EnhancedFilter.build(coded, t=64, bpk=12, tries=tries), EnhancedFilter.build(keys, t=64, bpk=12, tries=tries, book=book)
        assert sorted(map(tuple, one.probe(asked).collect())) == sorted(map(tuple, other.probe(asked).collect())) and one.n == other.n == 3000
        assert sorted(map(tuple, one.bits().collect())) == sorted(map(tuple, other.bits().collect()))
