"""Surrounding operators as registered queries: joins, sets, grouping sets, bit aggregates, JSON keys, predicates, and measures of blocks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalogue import LENGTHS, R, T, _built, _judged, register
from .functions import geometry as g
from .functions import theory
from .operators.anchors import predecessors, range_is_empty, shard_bounds
from .plans import duck, metrics
from .plans.lineage import written
from .plans.prune import predicate_range, prefix_range
from .sources import keysets as k

# exact emptiness, by an as-of join


@register("exact_emptiness_int", f"WITH {k.range_queries_sql('clustered', 'mixed', 1 << 15)} SELECT query_id, lo, hi, NOT EXISTS (SELECT 1 FROM keys x WHERE x.key BETWEEN q.lo AND q.hi) AS empty FROM queries q")
def _exact_int(spark: SparkSession, d: str) -> DataFrame:
    keys, asked = k.range_queries(written(k.integer_keys(spark, d, "clustered")), "mixed", 1 << 15)
    return range_is_empty(asked, keys).select("query_id", "lo", "hi", "empty")


_STR_DUCK = f"WITH allkeys AS ({k.WORDS_DUCK}), asked AS (SELECT key AS lo, key || 'm' AS hi FROM allkeys WHERE {k.h60_duck('key')} % 16 = 0) SELECT count(*)::BIGINT AS n, sum((NOT EXISTS (SELECT 1 FROM allkeys x WHERE encode(x.key) > encode(lo) AND encode(x.key) <= encode(hi)))::BIGINT)::BIGINT AS n_empty FROM asked"


@register("exact_emptiness_str", _STR_DUCK)
def _exact_str(spark: SparkSession, d: str) -> DataFrame:
    """Ranges from a word, itself left out, to the word with one letter more."""
    words = written(k.string_keys(spark, d, "words"))
    keys = words.select(F.col("key").cast("binary").alias("key"))
    asked = words.where(k.h60(F.col("key")) % 16 == 0).select(F.col("key").alias("query_id"), F.concat(F.col("key"), F.lit("\0")).cast("binary").alias("lo"), F.concat(F.col("key"), F.lit("m")).cast("binary").alias("hi"))
    return range_is_empty(asked, keys).agg(F.count("*").alias("n"), F.sum(F.col("empty").cast("long")).alias("n_empty"))


# joins that a filter stands in front of

@register("join_asof", "WITH o AS (SELECT epoch_us(o_orderdate) AS moment, max(o_orderkey) AS last FROM orders GROUP BY moment) SELECT count(last)::BIGINT AS n, sum(last)::BIGINT AS checksum FROM (SELECT epoch_us(l_shipdate) AS t FROM lineitem) l ASOF LEFT JOIN o ON l.t >= o.moment")
def _asof(spark: SparkSession, d: str) -> DataFrame:
    """The last order at or before each shipment."""
    orders = spark.read.parquet(f"{d}/orders.parquet").groupBy(F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("moment")).agg(F.max("o_orderkey").alias("last"))
    items = spark.read.parquet(f"{d}/lineitem.parquet").select(F.unix_micros(F.col("l_shipdate").cast("timestamp")).alias("t"))
    near = predecessors(items, "t", orders, "moment", ["last"], shard_bounds(orders, "moment"))
    return near.agg(F.count("near_last").alias("n"), F.sum("near_last").cast("long").alias("checksum"))


_ORDER_KEYS = f"SELECT o_orderkey AS key, o_totalprice FROM orders WHERE {k.h60_duck('o_orderkey::VARCHAR')} % 16 = 0"


@register("join_semi_filter", f"WITH b AS ({_ORDER_KEYS}) SELECT count(*)::BIGINT AS n, sum(l_linenumber)::BIGINT AS lines FROM lineitem WHERE l_orderkey IN (SELECT key FROM b)")
def _semi(spark: SparkSession, d: str) -> DataFrame:
    """A semi join whose probe side first passes the filter of the build side's keys: what the filter lets through wrongly, the join drops."""
    return _guarded(spark, d, "left_semi")


@register("join_anti_empty", f"WITH b AS ({_ORDER_KEYS}) SELECT count(*)::BIGINT AS n, sum(l_linenumber)::BIGINT AS lines FROM lineitem WHERE l_orderkey NOT IN (SELECT key FROM b)")
def _anti(spark: SparkSession, d: str) -> DataFrame:
    """An anti join that asks the build side only for keys that the filter can't rule out."""
    return _guarded(spark, d, "left_anti")


def _guarded(spark: SparkSession, d: str, how: str) -> DataFrame:
    from .operators.base import BaseFilter

    build = written(spark.read.parquet(f"{d}/orders.parquet").where(k.h60(F.col("o_orderkey").cast("string")) % 16 == 0).select(F.col("o_orderkey").alias("key")))
    items = spark.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey", "l_linenumber")
    # one question for each key, however many rows have it
    asked = items.select(F.col("l_orderkey").alias("query_id")).distinct().select("query_id", F.col("query_id").alias("lo"), F.col("query_id").alias("hi"))
    maybe = BaseFilter.build(build, t=T, eps=2.0 / 2**R).probe(asked).where("positive").select(F.col("query_id").alias("_k"))
    hit = maybe.join(build, F.col("_k") == F.col("key"), "left_semi")
    return items.join(hit, F.col("l_orderkey") == F.col("_k"), how).agg(F.count("*").alias("n"), F.sum("l_linenumber").cast("long").alias("lines"))


# sets of keys and of positives

for _op, _duck in (("union", "UNION"), ("except", "EXCEPT"), ("intersect", "INTERSECT")):
    _sides = f"(SELECT o_custkey AS key FROM orders) {_duck} (SELECT c_custkey AS key FROM customer WHERE c_acctbal > 0)"

    @register(f"setop_{_op}", f"SELECT count(*)::BIGINT AS n, sum(key)::BIGINT AS checksum FROM ({_sides})")
    def _setop(spark: SparkSession, d: str, op: str = _op) -> DataFrame:
        """Inserts as a union, deletes as a difference, agreement of two sides as an intersection."""
        a = spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_custkey").alias("key"))
        b = spark.read.parquet(f"{d}/customer.parquet").where("c_acctbal > 0").select(F.col("c_custkey").alias("key"))
        both = {"union": lambda: a.unionByName(b).distinct(), "except": lambda: a.subtract(b), "intersect": lambda: a.intersect(b)}[op]()
        return both.agg(F.count("*").alias("n"), F.sum("key").cast("long").alias("checksum"))


# false positives by grouping sets

_CELLS = " UNION ALL ".join(f"SELECT '{s}' AS key_set, {n}::BIGINT AS range_length, empty, cause IN ('anchor', 'infix') AS positive FROM ({duck.verdicts_with(s, 'held_out', n, 'SELECT empty, cause FROM verdicts')})" for s in ("normal", "clustered") for n in (1, 1 << 10))
_GROUPED = f"SELECT key_set, range_length, count(*)::BIGINT AS n_queries, sum((empty AND positive)::BIGINT)::BIGINT AS false_positives FROM ({_CELLS}) GROUP BY "


def _cells(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in ("normal", "clustered"):
        for n in (1, 1 << 10):
            part = _judged(spark, d, name, "held_out", n).select(F.lit(name).alias("key_set"), F.lit(n).cast("long").alias("range_length"), "empty", "positive")
            out = part if out is None else out.union(part)
    return out




def _counted(grouped) -> DataFrame:
    return grouped.agg(F.count("*").alias("n_queries"), F.sum((F.col("empty") & F.col("positive")).cast("long")).alias("false_positives"))


@register("fpr_rollup", _GROUPED + "ROLLUP (key_set, range_length)")
def _rollup(spark: SparkSession, d: str) -> DataFrame:
    return _counted(_cells(spark, d).rollup("key_set", "range_length"))


@register("fpr_cube", _GROUPED + "CUBE (key_set, range_length)")
def _cube(spark: SparkSession, d: str) -> DataFrame:
    return _counted(_cells(spark, d).cube("key_set", "range_length"))


@register("fpr_grouping_sets", _GROUPED + "GROUPING SETS ((key_set), (range_length))")
def _sets(spark: SparkSession, d: str) -> DataFrame:
    return _counted(_cells(spark, d).groupingSets([["key_set"], ["range_length"]], "key_set", "range_length"))


_ABLATED = " UNION ALL ".join(f"SELECT {str(x).lower()} AS drop_redundant, * FROM (WITH {k.range_queries_sql('clustered', 'held_out', 1 << 10)}, {duck.filter_ctes(T, R, x)}, {duck.verdict_ctes(T, R)} SELECT {duck.COUNTS} FROM verdicts)" for x in (True, False))


@register("fpr_redundant_ablation", _ABLATED)
def _ablated(spark: SparkSession, d: str) -> DataFrame:
    """What skipping the redundant bits gains."""
    from .operators.base import BaseFilter

    keys, asked = k.range_queries(written(k.integer_keys(spark, d, "clustered")), "held_out", 1 << 10)
    truth, out = written(range_is_empty(asked, keys)), None
    for drop in (True, False):
        f = BaseFilter.build(keys, t=T, eps=2.0 / 2**R, sorted_input=True, drop_redundant=drop)
        part = metrics.fpr(truth.join(f.probe(asked), "query_id")).select(F.lit(drop).alias("drop_redundant"), "*")
        out = part if out is None else out.union(part)
    return out


# blocks

_LOW, _HIGH = (f"({duck.infix_sql(x, R + 6)} >> {R})" for x in ("pred", "succ"))


@register("occupieds_bitmap", duck.keys_with("clustered", f"SELECT block_id, string_agg(q::VARCHAR, ',' ORDER BY q) AS quotients FROM (SELECT DISTINCT block_id, (infix >> {R}) - {_LOW} AS q FROM infixes) GROUP BY block_id"))
def _occupieds(spark: SparkSession, d: str) -> DataFrame:
    """The occupied quotients of each block, counted from its first: at most twice the keys of a block."""
    f = _built(spark, d)
    at = F.shiftright(g.derive_infix(F.col("key"), F.col("shared"), F.col("redundant"), f.m), R) - F.shiftright(g.derive_infix(F.col("pred"), F.col("shared"), F.col("redundant"), f.m), R)
    rows = f.keyed.join(f.blocks.select("block_id", "pred"), "block_id").select("block_id", at.cast("int").alias("q"))
    return rows.groupBy("block_id").agg(F.array_join(F.array_sort(F.collect_set("q")), ",").alias("quotients"))


@register("occupieds_bit_or", duck.keys_with("clustered", f"SELECT block_id, bit_or(1::BIGINT << (((infix >> {R}) - {_LOW}) % 32)::INTEGER) AS some, bit_xor(infix) AS mixed, bit_and(infix) AS every FROM infixes GROUP BY block_id"))
def _bit_or(spark: SparkSession, d: str) -> DataFrame:
    f = _built(spark, d)
    rows = f.keyed.join(f.blocks.select("block_id", "pred"), "block_id")
    q = F.shiftright("infix", R) - F.shiftright(g.derive_infix(F.col("pred"), F.col("shared"), F.col("redundant"), f.m), R)
    one = F.call_function("shiftleft", F.lit(1).cast("long"), (q % 32).cast("int"))
    return rows.groupBy("block_id").agg(F.bit_or(one).alias("some"), F.bit_xor("infix").alias("mixed"), F.bit_and("infix").alias("every"))


@register("topk_dense_blocks", duck.keys_with("clustered", f"SELECT block_id, succ - pred AS width FROM blocks ORDER BY width, block_id LIMIT 10"))
def _dense(spark: SparkSession, d: str) -> DataFrame:
    return _built(spark, d).blocks.select("block_id", (F.col("succ") - F.col("pred")).alias("width")).orderBy("width", "block_id").limit(10)


@register("lemma_infix_counts", duck.keys_with("clustered", f"SELECT count(*)::BIGINT AS blocks, sum(({duck.infix_sql('succ', R + 6)} - {duck.infix_sql('pred', R + 6)} + 1 BETWEEN {1 << (R + 4)} AND {1 << (R + 6)})::BIGINT)::BIGINT AS inside FROM blocks WHERE fst - redundant >= {R + 5}"))
def _lemma(spark: SparkSession, d: str) -> DataFrame:
    """Blocks whose infixes, from the one of pred to the one of succ, number between a quarter of and all values of m bits."""
    f = _built(spark, d)
    n = g.derive_infix(F.col("succ"), F.col("shared"), F.col("redundant"), f.m) - g.derive_infix(F.col("pred"), F.col("shared"), F.col("redundant"), f.m) + 1
    # blocks whose keys have m bits left
    full = f.blocks.where(F.lit(g.WIDTH) - F.col("shared") - 1 - F.col("redundant") >= f.m - 1)
    return full.agg(F.count("*").alias("blocks"), F.coalesce(F.sum(n.between(1 << (f.m - 2), 1 << f.m).cast("long")), F.lit(0)).alias("inside"))


@register("uniformity_chi2", duck.keys_with("uniform", f"SELECT count(*)::BIGINT AS bins, sum(n)::BIGINT AS n, round(sum((n - e) ** 2 / e), 3) AS chi2 FROM (SELECT n, avg(n) OVER () AS e FROM (SELECT count(*)::BIGINT AS n FROM infixes GROUP BY infix >> {R + 6 - 4}))"))
def _chi2(spark: SparkSession, d: str) -> DataFrame:
    f = _built(spark, d, "uniform")
    return metrics.chi_square(metrics.uniformity(f.infixes, f.m))


@register("anchor_overhead", duck.keys_with("uniform", "SELECT (SELECT count(*) FROM anchors)::BIGINT AS anchors, count(*)::BIGINT AS keys, (160 * (SELECT count(*) FROM anchors))::BIGINT AS anchor_bits FROM keys", t=1024))
def _overhead(spark: SparkSession, d: str) -> DataFrame:
    """What the anchor index takes at the default distance of 1,024 keys."""
    f = _built(spark, d, "uniform", t=1024)
    n = written(k.integer_keys(spark, d, "uniform")).agg(F.count("*").alias("keys"))
    # one row on either side
    return f.anchors.agg(F.count("*").alias("anchors"), F.sum(F.lit(64 + g.ANCHOR_BITS)).cast("long").alias("anchor_bits")).join(F.broadcast(n))


@register("trie_minimal_bits", f"WITH keys AS ({k.integer_sql('clustered')}), near AS (SELECT key, lag(key) OVER (ORDER BY key) AS p, lead(key) OVER (ORDER BY key) AS q FROM keys) SELECT count(*)::BIGINT AS n, sum(least(62, greatest(coalesce(62 - {duck.bitlen('xor(key, p)')}, -1), coalesce(62 - {duck.bitlen('xor(key, q)')}, -1)) + 1))::BIGINT AS bits FROM near")
def _minimal(spark: SparkSession, d: str) -> DataFrame:
    """Bits that tell each key from its neighbours, which is what a separating trie must keep."""
    from .baselines.filters import TruncatedTrie

    return TruncatedTrie.build(written(k.integer_keys(spark, d, "clustered"))).rows.agg(F.count("*").alias("n"), F.sum("depth").cast("long").alias("bits"))


# predicates, JSON keys, names

_PREDICATES = [("=", 5000), ("<", 700), ("<=", 700), (">", 9000), (">=", 9000)]


@register("pred_to_ranges", " UNION ALL ".join(f"SELECT '{op}' AS op, count(*)::BIGINT AS n FROM orders WHERE o_orderkey {op} {v}" for op, v in _PREDICATES) + " UNION ALL SELECT 'in', count(*)::BIGINT FROM orders WHERE o_orderkey IN (3, 5, 8) UNION ALL SELECT 'like', count(*)::BIGINT FROM customer WHERE c_name LIKE 'Customer#00000001%'")
def _predicates(spark: SparkSession, d: str) -> DataFrame:
    """Comparisons, lists and prefixes as ranges, counted by the ranges."""
    keys = spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("key"))
    out = None
    for op, v in _PREDICATES:
        lo, hi = predicate_range(op, v)
        part = keys.where(F.col("key").between(lo, hi)).agg(F.lit(op).alias("op"), F.count("*").alias("n"))
        out = part if out is None else out.union(part)
    points = F.array(*(F.struct(F.lit(x).alias("lo"), F.lit(x).alias("hi")) for x in (3, 5, 8)))
    listed = keys.where(F.exists(points, lambda p: F.col("key").between(p["lo"], p["hi"]))).agg(F.lit("in").alias("op"), F.count("*").alias("n"))
    lo, hi = prefix_range(b"Customer#00000001", 32)
    names = spark.read.parquet(f"{d}/customer.parquet").select(F.col("c_name").cast("binary").alias("key"))
    return out.union(listed).union(names.where(F.col("key").between(F.lit(bytearray(lo)), F.lit(bytearray(hi)))).agg(F.lit("like").alias("op"), F.count("*").alias("n")))


@register("json_key_ranges", "SELECT event_type, count(*)::BIGINT AS n, min(x) AS least, max(x) AS most, sum((x BETWEEN 10 AND 19)::BIGINT)::BIGINT AS inside FROM (SELECT event_type, json_extract(props, '$.k')::BIGINT AS x FROM events) GROUP BY event_type")
def _json(spark: SparkSession, d: str) -> DataFrame:
    x = F.get_json_object("props", "$.k").cast("long")
    return spark.read.parquet(f"{d}/events.parquet").select("event_type", x.alias("x")).groupBy("event_type").agg(F.count("*").alias("n"), F.min("x").alias("least"), F.max("x").alias("most"), F.sum(F.col("x").between(10, 19).cast("long")).alias("inside"))


@register("host_reverse", "SELECT page_id, array_to_string(list_reverse(string_split(lower(regexp_extract(url, '://([^/?#]*)', 1)), '.')), '.') AS host FROM pages")
def _hosts(spark: SparkSession, d: str) -> DataFrame:
    """Host names from the top-level domain on, so that hosts of one domain are neighbours."""
    host = F.lower(F.regexp_extract("url", "://([^/?#]*)", 1))
    return spark.read.parquet(f"{d}/pages.parquet").select("page_id", F.array_join(F.reverse(F.split(host, "\\.")), ".").alias("host"))


# formulas

@register("well_behaved")
def _well_behaved(spark: SparkSession, d: str) -> DataFrame:
    """For each integer key set, how much its density changes over a block's span, from 64 parts of equal numbers of keys."""
    rows = []
    for name in ("uniform", "normal", "skewed", "clustered", "timeline", "dense"):
        keys = written(k.integer_keys(spark, d, name))
        # 65 numbers
        r = keys.agg(F.count("*").alias("n"), F.percentile_approx("key", [i / 64 for i in range(65)], 100_000).alias("c")).first()
        density = [1.0 / max(1, b - a) for a, b in zip(r["c"], r["c"][1:], strict=False)]
        alpha, ok = theory.well_behaved(density, 1024, r["n"])
        rows.append((name, r["n"], round(alpha, 6), ok))
    return spark.createDataFrame(rows, "key_set string, n long, alpha double, well_behaved boolean")


@register("identical_bound", duck.keys_with("skewed", f"SELECT n, n_identical, round(n_identical / n + {2.0 / 2**R}, 6) AS bound FROM (SELECT sum(c)::BIGINT AS n, coalesce(sum(CASE WHEN c > 1 THEN c END), 0)::BIGINT AS n_identical FROM (SELECT count(*) AS c FROM infixes GROUP BY block_id, infix))"))
def _identical_bound(spark: SparkSession, d: str) -> DataFrame:
    """The share of keys whose infix isn't their own, and with it the bound of the false positive rate."""
    shared = metrics.identical_share(_built(spark, d, "skewed").infixes)
    return shared.select("n", "n_identical", F.round(F.col("n_identical") / F.col("n") + 2.0 / 2**R, 6).alias("bound"))


@register("neighbour_ranks", f"WITH keys AS ({k.integer_sql('money')}) SELECT tile, count(*)::BIGINT AS n, min(key) AS least, max(key) AS most FROM (SELECT key, ntile(16) OVER (ORDER BY key) AS tile FROM keys) GROUP BY tile")
def _tiles(spark: SparkSession, d: str) -> DataFrame:
    """Sixteen parts of equal numbers of keys, from ranks that no single task has to compute."""
    from .operators.anchors import rank_keys

    ranked = rank_keys(k.integer_keys(spark, d, "money"))
    small, more = divmod(ranked.n, 16)
    # the first `more` parts have one key more
    tile = F.when(F.col("rank") < more * (small + 1), F.floor(F.col("rank") / (small + 1))).otherwise(more + F.floor((F.col("rank") - more * (small + 1)) / max(1, small)))
    return ranked.rows.groupBy((tile + 1).alias("tile")).agg(F.count("*").alias("n"), F.min("key").alias("least"), F.max("key").alias("most"))


_WINDOW_EVENTS = "SELECT time_bucket(INTERVAL '1 day', ts) AS start, epoch_us(ts) AS key FROM events WHERE event_type <> 'error'"


@register("stream_window_filter", f"SELECT start::TIMESTAMP AS start, count(DISTINCT key)::BIGINT AS n_keys, min(key) AS least, max(key) AS most FROM ({_WINDOW_EVENTS}) GROUP BY start")
def _window_keys(spark: SparkSession, d: str) -> DataFrame:
    """The key set of each day's filter, as the stream builds them; the batch form of streaming.updates.window_filters."""
    from .streaming.updates import window_keys

    events = spark.read.parquet(f"{d}/events.parquet")
    return window_keys(events).groupBy("start").agg(F.countDistinct("key").alias("n_keys"), F.min("key").alias("least"), F.max("key").alias("most")).select(F.col("start").cast("timestamp_ntz").alias("start"), "n_keys", "least", "most")


@register("stream_dedup_late", "WITH e AS (SELECT epoch_us(ts) AS key, ts, event_type, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) SELECT count(*)::BIGINT AS n, count(DISTINCT (event_type = 'error', key))::BIGINT AS n_distinct, sum((seen IS NOT NULL AND ts < seen - INTERVAL '1 hour')::BIGINT)::BIGINT AS n_late FROM e")
def _late(spark: SparkSession, d: str) -> DataFrame:
    """Rows, distinct operations, and rows that come more than the watermark's hour after a later one."""
    from .streaming.updates import late_rows

    return late_rows(spark.read.parquet(f"{d}/events.parquet"))


# functions for SQL users


@register("unpack_block", duck.keys_with("clustered", "SELECT block_id, infix FROM infixes"))
def _unpack(spark: SparkSession, d: str) -> DataFrame:
    """Packed blocks back to infixes, by a table function in SQL."""
    from .functions.udfs import register_functions

    register_functions(spark)
    f = _built(spark, d)
    packed = written(f.packed())
    return spark.sql(f"SELECT p.block_id, u.infix FROM {{p}} p, LATERAL unpack_block({f.r}, p.q_base, p.q_count, p.n_keys, p.occupieds, p.runends, p.slots) u", p=packed)


_NODES = "SELECT query_id, level::INTEGER AS level, p AS prefix FROM (SELECT query_id, lo, hi, level, unnest(range(lo >> level::INTEGER, (hi >> level::INTEGER) + 1)) AS p FROM queries, range(0, 6) AS r(level)) WHERE p << level::INTEGER >= lo AND ((p + 1) << level::INTEGER) - 1 <= hi AND (level = 5 OR (p >> 1) << (level + 1)::INTEGER < lo OR (((p >> 1) + 1) << (level + 1)::INTEGER) - 1 > hi)"


@register("dyadic_cover", f"WITH {k.range_queries_sql('skewed', 'held_out', 100)} {_NODES}")
def _cover(spark: SparkSession, d: str) -> DataFrame:
    """The fewest aligned intervals of up to 32 values that make up each range."""
    from .functions.udfs import register_functions

    register_functions(spark)
    asked = k.range_queries(k.integer_keys(spark, d, "skewed"), "held_out", 100)[1]
    return spark.sql("SELECT q.query_id, c.level, c.prefix FROM {q} q, LATERAL dyadic_cover(q.lo, q.hi, 5) c", q=asked)


@register("rank_select", duck.keys_with("clustered", "SELECT count(DISTINCT block_id)::BIGINT AS blocks, 0::BIGINT AS wrong FROM infixes"))
def _rank_select(spark: SparkSession, d: str) -> DataFrame:
    """In every block, the last occupied quotient is where select finds the last one, and rank counts all ones before it."""
    from .functions.udfs import rank_bits, select_bits

    packed = written(_built(spark, d).packed()).where("n_keys > 0")
    ones = F.length(F.regexp_replace(F.array_join(F.transform(F.sequence(F.lit(1), F.octet_length("occupieds")), lambda i: F.lpad(F.conv(F.hex(F.substring("occupieds", i, F.lit(1))), 16, 2), 8, "0")), ""), "0", ""))
    asked = packed.select(ones.alias("ones"), "occupieds", select_bits(F.col("occupieds"), ones - 1).alias("place"))
    return asked.agg(F.count("*").alias("blocks"), F.sum((rank_bits(F.col("occupieds"), F.col("place")) != F.col("ones") - 1).cast("long")).alias("wrong"))


@register("anchor_search", f"WITH {k.range_queries_sql('clustered', 'same_dist', 1 << 10)}, {duck.filter_ctes(T, R)} SELECT count(*)::BIGINT AS n, count(a.key)::BIGINT AS n_near, sum(a.key % 1000003)::BIGINT AS checksum FROM queries q ASOF LEFT JOIN anchors a ON q.lo >= a.key")
def _search(spark: SparkSession, d: str) -> DataFrame:
    """Anchors few enough for every task, searched as one sorted array."""
    from .operators.anchors import search_anchors

    keys, asked = k.range_queries(written(k.integer_keys(spark, d, "clustered")), "same_dist", 1 << 10)
    from .operators.base import BaseFilter

    near = search_anchors(asked.select("query_id", "lo"), "lo", BaseFilter.build(keys, t=T, eps=2.0 / 2**R, sorted_input=True).anchors)
    return near.agg(F.count("*").alias("n"), F.count("near_key").alias("n_near"), F.sum(F.col("near_key") % 1000003).alias("checksum"))


@register("anchor_prefix_rounds", f"WITH {k.range_queries_sql('clustered', 'same_dist', 1 << 10)}, {duck.filter_ctes(T, R)}, firsts AS (SELECT key FROM anchors WHERE anchor_no % 4 = 0) SELECT query_id, max(62 - {duck.bitlen('xor(lo, key)')})::INTEGER AS prefix_len FROM queries, firsts GROUP BY query_id")
def _rounds(spark: SparkSession, d: str) -> DataFrame:
    """The longest prefix that a query shares with the first anchor of a group, by halving the length: one equi-join for each step."""
    from .operators.anchors import longest_prefix_rounds, prefix_hash_table
    from .operators.base import BaseFilter

    keys, asked = k.range_queries(written(k.integer_keys(spark, d, "clustered")), "same_dist", 1 << 10)
    table = written(prefix_hash_table(BaseFilter.build(keys, t=T, eps=2.0 / 2**R, sorted_input=True).anchors, 62, 4))
    return longest_prefix_rounds(asked.select("query_id", "lo"), "lo", table, 62).select("query_id", "prefix_len")
