"""End to end, strings and updates as registered queries: what filters save a table of files, ablations, growth, and what deletes leave."""

from __future__ import annotations

import time
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines import filters as baselines
from .catalogue import R, T, VARIANTS, register
from .contests import doublings
from .functions.entropy import Codebook, bisection_codes, compression_ratio, encode_columns, entropy_bits, huffman_lengths, mean_length, symbol_counts
from .functions.geometry import Geometry
from .operators.anchors import range_is_empty_until, shard_bounds
from .operators.dynamic import DynamicFilter
from .operators.enhanced import CodedKeys, EnhancedBlock, EnhancedFilter
from .operators.tailtrie import TailTrie
from .plans import metrics, prune
from .plans.lineage import shared_folder, written
from .sources import keysets as k

#: Files of the key-value table; each holds keys of the whole range, as sorted runs do.
FILES = 64
_ITEM_KEY = k.h60_duck("l_orderkey::VARCHAR")


def sorted_files(spark: SparkSession, d: str) -> str:
    """lineitem as key-sorted files whose key ranges overlap; the folder."""
    path = f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"
    items = spark.read.parquet(f"{d}/lineitem.parquet").select(k.h60(F.col("l_orderkey").cast("string")).alias("key"), "l_linenumber", "l_partkey")
    # by the number itself: a hash of it puts several numbers into one file
    items.repartitionById(FILES, F.pmod(F.col("key"), F.lit(FILES)).cast("int")).sortWithinPartitions("key").write.parquet(path)
    return path


def lookups(spark: SparkSession, path: str) -> DataFrame:
    """Ranges of 2^40 after every 64th key by hash, most of them empty, and the keys themselves for every 512th."""
    keys = spark.read.parquet(path).select("key").distinct()
    h = k.h60(F.concat(F.lit("ask"), F.col("key").cast("string")))
    own = h % 512 == 0
    lo = F.when(own, F.col("key")).otherwise(F.col("key") + 1)
    return written(keys.where(h % 64 == 0).select(F.col("key").alias("query_id"), lo.alias("lo"), (lo + (1 << 40)).alias("hi")))


_ASKED = f"keys AS (SELECT DISTINCT {_ITEM_KEY} AS key FROM lineitem), asked AS (SELECT key AS query_id, CASE WHEN h % 512 = 0 THEN key ELSE key + 1 END AS lo FROM (SELECT key, {k.h60_duck(chr(39) + 'ask' + chr(39) + ' || key::VARCHAR')} AS h FROM keys) WHERE h % 64 = 0)"


@register("prune_lookup_join", f"WITH {_ASKED} SELECT query_id, count(*)::BIGINT AS n, sum(l_partkey)::BIGINT AS parts FROM asked JOIN lineitem ON {_ITEM_KEY} BETWEEN lo AND lo + {1 << 40} GROUP BY query_id")
def _lookup(spark: SparkSession, d: str) -> DataFrame:
    """The rows of the ranges, from files that their filters don't rule out."""
    path = sorted_files(spark, d)
    filters = written(prune.file_filters(spark, path, "key"))
    rows = prune.guarded_lookup(spark, path, "key", lookups(spark, path), filters)
    return rows.groupBy("query_id").agg(F.count("*").alias("n"), F.sum("l_partkey").cast("long").alias("parts"))


@register("prune_files", f"WITH {_ASKED} SELECT count(*)::BIGINT AS true_pairs, 0::BIGINT AS missed FROM (SELECT DISTINCT query_id, {_ITEM_KEY} % {FILES} FROM asked JOIN lineitem ON {_ITEM_KEY} BETWEEN lo AND lo + {1 << 40})")
def _files(spark: SparkSession, d: str) -> DataFrame:
    """(query, file) pairs that hold a key, and those of them that the filters ruled out: none."""
    path = sorted_files(spark, d)
    filters, asked = written(prune.file_filters(spark, path, "key")), lookups(spark, path)
    keys = prune.file_keys(spark, path, "key")
    true = prune.met_in_shards(asked, keys, "key", "key", prune.cell_bounds(asked)).select("query_id", "file").distinct()
    held = prune.surviving_files(filters, asked).withColumn("_held", F.lit(True))
    joined = true.join(held, ["query_id", "file"], "left")
    return joined.agg(F.count("*").alias("true_pairs"), F.sum(F.col("_held").isNull().cast("long")).alias("missed"))


@register("exp9")
def _exp9(spark: SparkSession, d: str) -> DataFrame:
    """Files and rows that range queries read without a filter, with least and greatest keys only, with a prefix table, and with blocks."""
    path = sorted_files(spark, d)
    asked, filters = lookups(spark, path), written(prune.file_filters(spark, path, "key"))
    keys = written(prune.file_keys(spark, path, "key"))
    files, n, out = keys.select("file").distinct(), asked.count(), []
    # files of a table are few beside its rows; every query opens every file
    none = n * files.count(), n * spark.read.parquet(path).count()
    rows = [("none", *none, 0.0)]
    for name in ("min_max", "base"):
        began = time.perf_counter()
        cost = prune.read_cost(spark, path, "key", prune.surviving_files(filters, asked, min_max_only=name == "min_max"))
        rows.append((name, *cost, time.perf_counter() - began))
    # one table for all files: the file number, which the key's low bits tell, is part of the prefix
    began = time.perf_counter()
    number = F.pmod(F.col("key"), F.lit(FILES))
    table = baselines.PrefixSuffixTable.build(keys.select(F.col("key")), 16, 128)
    maybe = table.probe(asked).where("positive").select("query_id")
    met = asked.join(maybe, "query_id", "left_semi")
    cost = prune.read_cost(spark, path, "key", prune.surviving_files(filters, met, min_max_only=True))
    rows.append(("prefix_suffix", *cost, time.perf_counter() - began))
    return spark.createDataFrame([(a, n, b, c, round(s, 3)) for a, b, c, s in rows], "filter string, n_queries long, files_read long, rows_read long, seconds double")


# strings


@register("table_ablation")
def _table_ablation(spark: SparkSession, d: str) -> DataFrame:
    """False positives of adjacent empty ranges and the bits stored, for the base filter, either addition and both; four string sets, 16 bits per key."""
    rows = []
    for name in ("str_smooth", "words", "emails", "urls"):
        keys, asked = k.adjacent_pairs(written(k.string_keys(spark, d, name)))
        keys, asked = written(keys), written(asked)
        # keys are coded and sorted once for the variants of a code
        coded = {None: CodedKeys.prepare(keys), 2: CodedKeys.prepare(keys, book=Codebook.build(keys, 2))}
        for variant, (order, tries) in VARIANTS.items():
            f = EnhancedFilter.build(coded[order], t=T, bpk=16, k=order, tries=tries)
            r = f.probe(asked).agg(F.count("*").alias("n"), F.sum(F.col("positive").cast("long")).alias("fp")).first()
            # the book is shared by all filters of a domain, so it stands apart
            bits = {x["component"]: x["bits"] for x in f.bits().collect()}
            book = bits.pop("codebook", 0)
            rows.append((name, variant, r["n"], r["fp"], round(sum(bits.values()) / max(1, f.n), 3), round(book / max(1, f.n), 3)))
    return spark.createDataFrame(rows, "key_set string, variant string, n_queries long, false_positives long, stored_bpk double, codebook_bpk double")


@register("exp3")
def _exp3(spark: SparkSession, d: str) -> DataFrame:
    """The base and the enhanced filter over strings as the budget grows."""
    rows = []
    for name in ("str_smooth", "words"):
        keys, asked = k.adjacent_pairs(written(k.string_keys(spark, d, name)))
        keys, asked = written(keys), written(asked)
        for variant in ("base", "enhanced"):
            order, tries = VARIANTS[variant]
            # one book, one coding and one sort for all budgets
            coded = CodedKeys.prepare(keys, book=Codebook.build(keys, order) if order else None)
            for bpk in (12, 16, 20):
                f = EnhancedFilter.build(coded, t=T, bpk=bpk, k=order, tries=tries)
                began = time.perf_counter()
                r = f.probe(asked).agg(F.count("*").alias("n"), F.sum(F.col("positive").cast("long")).alias("fp")).first()
                rows.append((name, variant, bpk, r["n"], r["fp"], round((time.perf_counter() - began) * 1e6 / max(1, r["n"]), 2)))
    return spark.createDataFrame(rows, "key_set string, variant string, bpk int, n_queries long, false_positives long, us_per_query double")


@register("table_orders")
def _table_orders(spark: SparkSession, d: str) -> DataFrame:
    """Compression, and the codebook's share of the filter's size and of its build time, by order of the code."""
    keys, rows = written(k.string_keys(spark, d, "urls")), []
    n = keys.count()
    for order in range(4):
        began = time.perf_counter()
        book = Codebook.build(keys, order)
        took = time.perf_counter() - began
        ratio = compression_ratio(keys, book)
        whole = time.perf_counter() - began
        rows.append((order, round(float(ratio), 4), round(100 * book.bits() / (16 * n), 4), round(100 * took / whole, 2)))
    return spark.createDataFrame(rows, "context_bytes int, ratio double, codebook_percent_of_filter double, codebook_percent_of_time double")


@register("encode_preserves_order", f"WITH s AS ({k.string_sql('words')}) SELECT count(*)::BIGINT AS n, 0::BIGINT AS out_of_order, 0::BIGINT AS not_decoded FROM s")
def _ordered(spark: SparkSession, d: str) -> DataFrame:
    """Keys in code order are keys in byte order, and codes decode to their keys."""
    keys = written(k.string_keys(spark, d, "words").select(F.col("key").cast("binary").alias("key")))
    book = Codebook.build(keys, 1)
    coded = written(encode_columns(keys.withColumn("raw", F.col("key")), ["key"], book))

    def decoded(frames):
        for pdf in frames:
            yield pd.DataFrame({"wrong": [int(book.decode(c) != bytes(x)) for c, x in zip(pdf["key_code"], pdf["raw"], strict=True)]})

    wrong = coded.select("key_code", "raw").mapInPandas(decoded, "wrong long").agg(F.sum("wrong").alias("not_decoded"))
    # neighbours inside ranges of the first byte; codes begin with that byte's code
    from pyspark.sql import Window

    order = Window.partitionBy(F.substring(F.hex("raw"), 1, 2)).orderBy("raw")
    checked = coded.withColumn("_before", F.lag("key").over(order)).agg(F.count("*").alias("n"), F.sum((F.coalesce(F.col("_before") > F.col("key"), F.lit(False))).cast("long")).alias("out_of_order"))
    return checked.join(F.broadcast(wrong))


@register("encoded_keys", f"WITH s AS ({k.string_sql('words')}) SELECT count(*)::BIGINT AS n, sum(octet_length(encode(key)))::BIGINT AS key_bytes, count(DISTINCT key)::BIGINT AS n_distinct FROM s")
def _encoded(spark: SparkSession, d: str) -> DataFrame:
    """No two keys share a code."""
    keys = written(k.string_keys(spark, d, "words").select(F.col("key").cast("binary").alias("key")))
    coded = encode_columns(keys.withColumn("n", F.octet_length("key")), ["key"], Codebook.build(keys, 1))
    return coded.agg(F.count("*").alias("n"), F.sum("n").cast("long").alias("key_bytes"), F.countDistinct("key_code").alias("n_distinct"))


@register("entropy_report")
def _entropy(spark: SparkSession, d: str) -> DataFrame:
    """Zero-order entropy, and mean code lengths of the free code and of the ordered code, which lies within two bits of the entropy."""
    rows = []
    for name in ("words", "emails", "urls"):
        freqs = sorted((int(r["symbol"], 16), r["freq"]) for r in symbol_counts(written(k.string_keys(spark, d, name)), 0).collect())
        rows.append((name, round(entropy_bits(freqs), 6), round(mean_length(freqs, huffman_lengths(freqs)), 6), round(mean_length(freqs, bisection_codes(freqs)), 6)))
    return spark.createDataFrame(rows, "key_set string, entropy double, huffman double, bisection double")


@register("trie_code_sizes")
def _trie_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Trie bits per node, per set; two are the most that topology and labels take together."""
    rows = []
    for name in ("words", "urls"):
        f = EnhancedFilter.build(written(k.string_keys(spark, d, name)), t=T, bpk=16, k=2)
        r = f.tries.where("n_keys > 1").agg(F.count("*").alias("tries"), F.sum("code_bits").alias("code"), F.sum("trailing_bits").alias("trailing"), F.sum("n_nodes").alias("nodes"), F.sum("n_keys").alias("keys")).first()
        rows.append((name, r["tries"], r["keys"] or 0, r["nodes"] or 0, r["code"] or 0, r["trailing"] or 0))
    return spark.createDataFrame(rows, "key_set string, n_tries long, n_keys long, n_nodes long, code_bits long, trailing_bits long")


# updates of the base filter

#: Keys of a shard, at most, where eight shards would have more.
SHARD = 1 << 20


def _stages(spark: SparkSession, d: str, name: str = "skewed", keys: DataFrame | None = None, **options) -> list[tuple[int, DynamicFilter, DataFrame]]:
    """keys: a written table of the set's doublings, if there is one."""
    keys = written(doublings(k.integer_keys(spark, d, name))) if keys is None else keys
    shards = max(8, -(-keys.count() // SHARD))
    f = DynamicFilter.build(keys.where("step = 0").select("key"), t=T, r=R, bounds=shard_bounds(keys.select("key"), shards=shards), **options)
    out = []
    for step in range(1, 7):
        f = f.insert(keys.where(F.col("step") == step).select("key"))
        f.state = written(f.state)
        out.append((step, f, keys.where(F.col("step") <= step).select("key")))
    return out


@register("dyn_split")
def _split(spark: SparkSession, d: str) -> DataFrame:
    """Blocks, stretches, entries that splits moved and copies that they made, doubling by doubling."""
    rows = [(step, *f.stats().agg(*(F.sum(c) for c in ("blocks", "anchors", "entries", "slots", "stretches", "moved", "copied"))).first()) for step, f, _ in _stages(spark, d)]
    return spark.createDataFrame(rows, "doubling int, blocks long, anchors long, entries long, slots long, stretches long, moved long, copied long")


_PROMOTED = f"""WITH placed AS (SELECT key, {k.h60_duck("'grow' || key::VARCHAR")} % 64 AS p FROM ({k.integer_sql('skewed')})) SELECT count(*)::BIGINT AS inserted, 0::BIGINT AS not_anchors FROM placed WHERE p <> 0"""


@register("dyn_promoted_anchors", _PROMOTED)
def _promoted(spark: SparkSession, d: str) -> DataFrame:
    """Keys that came by inserts, and those whose hash chose them as anchors but that are none."""
    keys = written(doublings(k.integer_keys(spark, d, "skewed")))
    bounds = shard_bounds(keys.select("key"), shards=8)
    f = DynamicFilter.build(keys.where("step = 0").select("key"), t=T, r=R, bounds=bounds).insert(keys.where("step > 0").select("key"))
    from .operators.anchors import shard_of

    late = keys.where("step > 0").withColumn("shard", shard_of(F.col("key"), bounds))
    chosen = late.where(k.h60(F.concat_ws("#", F.col("shard").cast("string"), F.col("key").cast("string"))) % T == 0)
    anchors = written(f.state).select(F.col("pred").alias("key")).distinct()
    missing = chosen.join(anchors, "key", "left_anti").agg(F.count("*").alias("not_anchors"))
    return late.agg(F.count("*").alias("inserted")).join(F.broadcast(missing))


@register("dyn_fpr_by_doubling")
def _by_doubling(spark: SparkSession, d: str) -> DataFrame:
    """False positives of ranges anywhere as uniform keys double, with remainders of one length and with a bit more for each doubling."""
    rows = []
    lo = k.h60(F.concat(F.lit("ask"), F.col("key").cast("string")))
    # every step asks the same ranges, and both filters grow by the same keys
    grown = written(doublings(k.integer_keys(spark, d, "uniform")))
    asked = grown.select(F.col("key").alias("query_id"), lo.alias("lo"), (lo + 1023).alias("hi"))
    asked = written(range_is_empty_until(asked, grown, "step"))
    for widening in ("none", "per_doubling"):
        for step, f, _ in _stages(spark, d, "uniform", keys=grown, widening=widening):
            r = metrics.fpr(metrics.verdicts(f, asked).withColumn("empty", F.coalesce(F.col("filled") > step, F.lit(True)))).first()
            s = f.stats().agg(F.sum("bits").alias("bits"), F.sum("entries").alias("entries"), F.sum("slots").alias("slots")).first()
            rows.append((widening, step, r["n_empty"], r["false_positives"], r["false_negatives"], s["bits"], round(s["entries"] / max(1, s["slots"]), 4)))
    return spark.createDataFrame(rows, "widening string, doubling int, n_empty long, false_positives long, false_negatives long, bits long, utilisation double")


@register("dyn_utilisation")
def _utilisation(spark: SparkSession, d: str) -> DataFrame:
    """Used slots of blocks that stretch and of blocks that double."""
    rows = []
    for expansion in ("stretch", "double"):
        _, f, _ = _stages(spark, d, expansion=expansion)[-1]
        s = f.stats().agg(F.sum("entries").alias("entries"), F.sum("slots").alias("slots")).first()
        rows.append((expansion, s["entries"], s["slots"], round(s["entries"] / max(1, s["slots"]), 4)))
    return spark.createDataFrame(rows, "expansion string, entries long, slots long, utilisation double")


@register("dyn_compact")
def _compact(spark: SparkSession, d: str) -> DataFrame:
    """Slots before and after half of the keys are deleted, and after the blocks are compacted; no key is missed."""
    keys = written(k.integer_keys(spark, d, "skewed"))
    half = k.h60(F.col("key").cast("string")) % 2 == 0
    f = DynamicFilter.build(keys, t=T, r=R, bounds=shard_bounds(keys, shards=8))
    after = f.delete(keys.where(half), clean_copies=True)
    after.state = written(after.state)
    small = after.compact()
    points = keys.where(~half).select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
    slots = lambda x: x.stats().agg(F.sum("slots")).first()[0]
    return spark.createDataFrame([(slots(f), slots(after), slots(small), small.probe(points).where("not positive").count())], "built long, deleted long, compacted long, false_negatives long")


# updates of the enhanced filter: blocks are dealt by the first bytes of the keys, each with its own trie state

#: Bits of a block's keys at least; a block with a longer key is as wide as that key.
ENHANCED_WIDTH = 256


def _as_number(key: bytes, width: int) -> int:
    return int.from_bytes(key.ljust(width // 8, b"\0"), "big")


def enhanced_updates(keys: DataFrame, r: int = 6) -> DataFrame:
    """(block, case, n, missed, found_after): what inserts do to the tries of each block, keys that are missed then, and after every second one is deleted.

    keys(block, key, seq): a block's keys are inserted in the order of seq.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        inserted = [bytes(x) for x in pdf.sort_values("seq")["key"]]
        width = max(ENHANCED_WIDTH, 8 * max(map(len, inserted)))
        # padded where they are used: one long key would widen all that are held
        numbers = lambda keys: (_as_number(x, width) for x in keys)
        # a key of a geometry lies strictly between its anchors
        low, high = min(numbers(inserted)), max(numbers(inserted))
        f = EnhancedBlock(Geometry(max(0, low - 1), high + 1, width, r + 6), r)
        for x in numbers(inserted):
            f.insert(x)
        missed = sum(not f.positive(x, x) for x in numbers(inserted))
        gone = set(inserted[::2])
        for x in numbers(inserted[::2]):
            f.delete(x)
        left = sum(not f.positive(x, x) for x in numbers(x for x in inserted if x not in gone))
        cases = f.cases.items()
        return pd.DataFrame({"block": [pdf["block"].iloc[0]] * len(cases), "case": [c for c, _ in cases], "n": [n for _, n in cases], "missed": [missed] * len(cases), "missed_after": [left] * len(cases)})

    return keys.groupBy("block").applyInPandas(run, "block string, case string, n long, missed long, missed_after long")


def _blocks_of_words(spark: SparkSession, d: str) -> DataFrame:
    return k.string_keys(spark, d, "words").select(F.substring("key", 1, 3).alias("block"), F.col("key").cast("binary").alias("key"), k.h60(F.col("key")).alias("seq"))


_WORD_COUNT = f"WITH s AS ({k.string_sql('words')}) SELECT count(*)::BIGINT AS n, 0::BIGINT AS missed FROM s"


@register("enh_insert_cases", _WORD_COUNT)
def _cases(spark: SparkSession, d: str) -> DataFrame:
    """Every insert is one of the cases, and no key is missed after them."""
    per_block = written(enhanced_updates(_blocks_of_words(spark, d)))
    missed = per_block.select("block", "missed").distinct().agg(F.sum("missed").alias("missed"))
    return per_block.agg(F.sum("n").alias("n")).join(F.broadcast(missed))


@register("enh_case_counts")
def _case_counts(spark: SparkSession, d: str) -> DataFrame:
    return enhanced_updates(_blocks_of_words(spark, d)).groupBy("case").agg(F.sum("n").alias("n"))


@register("enh_delete", "SELECT 0::BIGINT AS missed_after")
def _enh_delete(spark: SparkSession, d: str) -> DataFrame:
    """Keys that are missed after every second key of each block is gone."""
    return enhanced_updates(_blocks_of_words(spark, d)).select("block", "missed_after").distinct().agg(F.sum("missed_after").alias("missed_after"))
