"""The comparison filters as registered queries: each alone with SQL that replays it, then all together at equal budgets."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines import filters as baselines
from .catalogue import register
from .operators.anchors import Ranked, range_is_empty, rank_keys, with_neighbours
from .operators.base import BaseFilter
from .operators.dynamic import DynamicFilter
from .plans import duck, metrics
from .plans.lineage import released, written
from .sources import keysets as k

#: The four integer key sets of the comparisons.
SETS = ("uniform", "normal", "skewed", "clustered")
LENGTHS = (1, 1 << 5, 1 << 10, 1 << 15, 1 << 20)
SHORT = 1 << 7

# each filter alone: counts over ranges of 128, of which half hold a key


def _head(kind: str = "mixed", length: int = SHORT) -> str:
    return f"{k.range_queries_sql('skewed', kind, length)}, truth AS (SELECT q.*, NOT EXISTS (SELECT 1 FROM keys x WHERE x.key BETWEEN q.lo AND q.hi) AS empty FROM queries q)"


N = "(SELECT count(*) FROM keys)"
COUNTS = "SELECT count(*)::BIGINT AS n_queries, sum(empty::BIGINT)::BIGINT AS n_empty, sum((empty AND positive)::BIGINT)::BIGINT AS false_positives, sum((NOT empty AND NOT positive)::BIGINT)::BIGINT AS false_negatives FROM verdicts"


def _sql(ctes: str, positive: str, kind: str = "mixed", length: int = SHORT) -> str:
    """ctes: tables of the filter and, as `hit`, the query_id of its positive answers."""
    return f"WITH {_head(kind, length)}, {ctes}, verdicts AS (SELECT t.*, {positive} AS positive FROM truth t) {COUNTS}"


HIT = "query_id IN (SELECT query_id FROM hit)"


def _h(*parts: str) -> str:
    """md5 prefix of the parts joined by #; SQL expressions as text, fixed strings quoted."""
    return k.h60_duck(" || '#' || ".join(p if p.startswith("'") else f"({p})::VARCHAR" for p in parts))


def _trie_sql(more: int = 0, tag_bits: int = 0) -> str:
    """more: real bits beyond those that tell a key from its neighbours; tag_bits: hashed ones, which refine points."""
    tag = lambda x: f"{_h(repr('suffix'), x)} % {1 << tag_bits}"
    fits = f" AND (lo <> hi OR tag = {tag('lo')})" if tag_bits else ""
    return _sql(
        f"""near AS (SELECT key, lag(key) OVER (ORDER BY key) AS p, lead(key) OVER (ORDER BY key) AS q FROM keys),
deep AS (SELECT key, least(62, greatest(coalesce(62 - {duck.bitlen('xor(key, p)')}, -1), coalesce(62 - {duck.bitlen('xor(key, q)')}, -1)) + 1 + {more})::INTEGER AS depth FROM near),
kept AS (SELECT (key >> (62 - depth)) << (62 - depth) AS first, ((key >> (62 - depth)) << (62 - depth)) + (1::BIGINT << (62 - depth)) - 1 AS last, {tag('key') if tag_bits else 0} AS tag FROM deep),
hit AS (SELECT DISTINCT query_id FROM queries JOIN kept ON first <= hi AND last >= lo{fits})""",
        HIT, "mixed", 1 if tag_bits else SHORT,
    )


def _levels_sql(size: str, place: Callable[[int], str], bitmap: str) -> str:
    """Bloom filters of all prefixes of up to seven bits less: a point is a hit if its whole chain of prefixes is."""
    levels = SHORT.bit_length() - 1
    inside = " AND ".join(f"({bitmap}, {place(i)}) IN (SELECT (b, p) FROM bits)" for i in range(2))
    return _sql(
        f"""whole AS (SELECT greatest(64, {N} * 16) AS whole), sizes AS (SELECT level, whole, {size.format(levels=levels)} AS size FROM whole, range({levels + 1}) AS r(level)),
stored AS (SELECT DISTINCT level, key >> level::INTEGER AS prefix FROM keys, range({levels + 1}) AS r(level)),
bits AS (SELECT DISTINCT b, p FROM (SELECT {bitmap} AS b, unnest([{place(0)}, {place(1)}]) AS p FROM stored JOIN sizes USING (level))),
points AS (SELECT query_id, unnest(range(lo, hi + 1)) AS x FROM queries),
asked AS (SELECT DISTINCT level, x >> level::INTEGER AS prefix FROM points, range({levels + 1}) AS r(level)),
good AS (SELECT level, prefix FROM asked JOIN sizes USING (level) WHERE {inside}),
hit AS (SELECT DISTINCT query_id FROM (SELECT query_id, x FROM points JOIN good ON prefix = x >> level::INTEGER GROUP BY query_id, x HAVING count(*) = {levels + 1}))""",
        HIT,
    )


_BIT = lambda i: f"{_h(repr(f'bit{i}'), 'level', 'prefix')} % size"
_WORD = lambda i: f"{_h(repr(f'word{i}'), 'level', 'prefix >> 6')} % greatest(1, whole // 64) * 64 + prefix % 64"


def _spline_sql(gaps: int = 0) -> str:
    scale = max(1, round(1 / 2 ** -(16 - 2.4)))
    place = f"CASE WHEN x IS NULL THEN -1 ELSE rank * {scale} + (least(pt - x, x2 - x)::HUGEINT * (rank2 - rank) * {scale} // (x2 - x))::BIGINT END"
    placed = lambda source, column: f"SELECT s.*, {place} AS place FROM (SELECT *, {column} AS pt FROM {source}) s ASOF LEFT JOIN segments g ON s.pt >= g.x"
    wide = f"""spans AS (SELECT key AS after, lead(key) OVER (ORDER BY key) - key - 1 AS width FROM keys), widest AS (SELECT * FROM spans WHERE width > 0 ORDER BY width DESC, after LIMIT {gaps}),
hit AS (SELECT query_id FROM near WHERE NOT EXISTS (SELECT 1 FROM widest WHERE near.lo > after AND near.hi <= after + width))"""
    return _sql(
        f"""ranked AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS rank, count(*) OVER () - 1 AS last FROM keys),
knots AS (SELECT key AS x, rank FROM ranked WHERE rank % 64 = 0 OR rank = last),
segments AS (SELECT x, rank, coalesce(lead(x) OVER (ORDER BY x), x + 1) AS x2, coalesce(lead(rank) OVER (ORDER BY x), rank) AS rank2 FROM knots),
places AS (SELECT DISTINCT place FROM ({placed('keys', 'key')})),
low AS ({placed('queries', 'lo')}), high AS ({placed('queries', 'hi')}),
near AS (SELECT l.query_id, l.lo, l.hi FROM low l JOIN high h USING (query_id) WHERE EXISTS (SELECT 1 FROM places p WHERE p.place BETWEEN l.place AND h.place)),
{wide if gaps else 'hit AS (SELECT query_id FROM near)'}""",
        HIT,
    )


RING = f"greatest(2, {N} * {2**14})"
_CODE = lambda x: f"({_h(repr('ring'), f'{x} // ring')} % ring + {x} % ring) % ring"
RING_SQL = _sql(
    f"""size AS (SELECT {RING} AS ring), codes AS (SELECT DISTINCT {_CODE('key')} AS code FROM keys, size),
pieces AS (SELECT query_id, ring, lo AS x, CASE WHEN lo // ring = hi // ring THEN hi ELSE (hi // ring) * ring - 1 END AS y FROM queries, size
  UNION ALL SELECT query_id, ring, (hi // ring) * ring, hi FROM queries, size WHERE lo // ring <> hi // ring),
coded AS (SELECT query_id, ring, {_CODE('x')} AS c, y - x AS w FROM pieces),
spans AS (SELECT query_id, c AS a, least(c + w, ring - 1) AS b FROM coded UNION ALL SELECT query_id, 0, c + w - ring FROM coded WHERE c + w >= ring),
hit AS (SELECT DISTINCT query_id FROM spans JOIN codes ON code BETWEEN a AND b)""",
    HIT,
)


def _table_ctes(extra: int, bpk: float = 16, length: int = SHORT, source: str = "queries") -> str:
    s = math.ceil(math.log2(length))
    width = max(0, math.floor(bpk * 0.95 - 3.125 - extra) - s)
    finger = lambda x: f"{_h(repr('prefix'), x)} % (1::BIGINT << a)"
    return f"""bits AS (SELECT least(59, greatest(1, ceil(log2(greatest(2, {N})))::INTEGER + {width})) AS a),
stored AS (SELECT DISTINCT {finger(f'key >> {s}')} AS f, key & {(1 << s) - 1} AS suffix FROM keys, bits),
tails AS (SELECT query_id, lo, hi, unnest(range(lo >> {s}, (hi >> {s}) + 1)) AS x FROM {source}),
probed AS (SELECT query_id, {finger('x')} AS f, CASE WHEN x = lo >> {s} THEN lo & {(1 << s) - 1} ELSE 0 END AS l, CASE WHEN x = hi >> {s} THEN hi & {(1 << s) - 1} ELSE {(1 << s) - 1} END AS h FROM tails, bits),
hit AS (SELECT DISTINCT query_id FROM probed JOIN stored USING (f) WHERE suffix BETWEEN l AND h)"""


_K = max(1, round(16 * math.log(2)))
BLOOM_SQL = _sql(
    f"""bits AS (SELECT DISTINCT unnest([{', '.join(f"{_h(repr(f'point{i}'), 'key')} % ({N} * 16)" for i in range(_K))}]) AS p FROM keys),
hit AS (SELECT query_id FROM queries WHERE {' AND '.join(f"{_h(repr(f'point{i}'), 'lo')} % ({N} * 16) IN (SELECT p FROM bits)" for i in range(_K))})""",
    HIT, "mixed", 1,
)
_FINGER = math.floor(16 * 0.95)
CUCKOO_SQL = _sql(
    f"""size AS (SELECT greatest(1, ceil({N} / (4 * 0.95::DOUBLE))::BIGINT) AS buckets),
stored AS (SELECT DISTINCT {_h(repr('bucket'), 'key')} % buckets AS b, {_h(repr('finger'), 'key')} % {1 << _FINGER} AS f FROM keys, size),
asked AS (SELECT query_id, buckets, {_h(repr('bucket'), 'lo')} % buckets AS first, {_h(repr('finger'), 'lo')} % {1 << _FINGER} AS f FROM queries, size),
both_ AS (SELECT query_id, f, first AS b FROM asked UNION ALL SELECT query_id, f, ((({_h(repr('pair'), 'f')} % buckets - first) % buckets) + buckets) % buckets FROM asked),
hit AS (SELECT DISTINCT query_id FROM both_ JOIN stored USING (b, f))""",
    HIT, "mixed", 1,
)

ALONE: dict[str, tuple[Callable[[DataFrame], object], str | None, int]] = {
    "base_truncated_trie": (baselines.TruncatedTrie.build, _trie_sql(), SHORT),
    "base_truncated_trie_real": (lambda keys: baselines.TruncatedTrie.build(keys, 4), _trie_sql(4), SHORT),
    "base_truncated_trie_hashed": (lambda keys: baselines.TruncatedTrie.build(keys, 4, "hashed"), _trie_sql(0, 4), 1),
    "base_dyadic_bloom": (baselines.DyadicBloom.build, _levels_sql("CASE WHEN level = 0 THEN whole // 2 ELSE greatest(64, (whole - whole // 2) // {levels}) END", _BIT, "level"), SHORT),
    "base_shared_bitmap": (baselines.SharedDyadicBitmap.build, _levels_sql("whole", _BIT, "0"), SHORT),
    "base_prefix_hash_bitmap": (baselines.PrefixHashBitmap.build, _levels_sql("whole", _WORD, "0"), SHORT),
    "base_spline_bitmap": (baselines.SplineBitmap.build, _spline_sql(), SHORT),
    "base_pruned_spline": (baselines.PrunedSplineBitmap.build, _spline_sql(64), SHORT),
    "base_local_hash": (baselines.LocalHashSet.build, RING_SQL, SHORT),
    "base_prefix_suffix": (baselines.PrefixSuffixTable.build, _sql(_table_ctes(0), HIT), SHORT),
    "base_prefix_suffix_extra": (baselines.PrefixSuffixTableExtraBit.build, _sql(_table_ctes(1), HIT), SHORT),
    "base_point_bloom": (baselines.PointBloom.build, BLOOM_SQL, 1),
    "base_point_cuckoo": (baselines.PointCuckoo.build, CUCKOO_SQL, 1),
    "exact": (baselines.ExactRange.build, _sql("hit AS (SELECT query_id FROM truth WHERE NOT empty)", HIT), SHORT),
    "no_filter": (baselines.NoFilter.build, _sql("hit AS (SELECT query_id FROM queries)", HIT), SHORT),
}

for _name, (_make, _oracle, _length) in ALONE.items():

    @register(_name, _oracle)
    def _alone(spark: SparkSession, d: str, make: Callable = _make, length: int = _length) -> DataFrame:
        keys, asked = k.range_queries(written(k.integer_keys(spark, d, "skewed")), "mixed", length)
        return metrics.fpr(range_is_empty(asked, keys).join(make(keys).probe(asked), "query_id"))


HYBRID_LONG = 1 << 12
_EPS = 0.01
_HYBRID_BPK = (3.125 + math.log2(SHORT / _EPS)) / 0.95


def _hybrid_sql(intersect: bool) -> str:
    every = k.range_queries_sql("skewed", "mixed", 64)
    long = k.range_queries_sql("skewed", "mixed", HYBRID_LONG).split("queries AS (", 1)[1]
    head = every.replace("queries AS (", "short AS (", 1) + f", long AS ({long}, queries AS (SELECT 2 * query_id AS query_id, lo, hi, kind FROM short UNION ALL SELECT 2 * query_id + 1, lo, hi, kind FROM long)"
    base = f"{duck.filter_ctes(1024, 8)}, {duck.verdict_ctes(1024, 8)}".replace("verdicts AS", "judged AS")
    small = "narrow AS (SELECT * FROM queries WHERE hi - lo + 1 <= 128)"
    both = f"{HIT} AND cause IN ('anchor', 'infix')" if intersect else HIT
    return f"WITH {head}, {small}, {_table_ctes(0, _HYBRID_BPK, SHORT, 'narrow')}, {base}, verdicts AS (SELECT query_id, empty, CASE WHEN hi - lo + 1 <= {SHORT} THEN {both} ELSE cause IN ('anchor', 'infix') END AS positive FROM judged) {COUNTS}"


for _name, _intersect in (("hybrid_probe", False), ("hybrid_intersect", True)):

    @register(_name, _hybrid_sql(_intersect))
    def _hybrid(spark: SparkSession, d: str, intersect: bool = _intersect) -> DataFrame:
        """Ranges of 64 go to the table, or to both filters, ranges of 4,096 to the base filter."""
        all_keys = written(k.integer_keys(spark, d, "skewed"))
        keys, short = k.range_queries(all_keys, "mixed", 64)
        _, long = k.range_queries(all_keys, "mixed", HYBRID_LONG)
        asked = short.withColumn("query_id", 2 * F.col("query_id")).union(long.withColumn("query_id", 2 * F.col("query_id") + 1))
        return metrics.fpr(range_is_empty(asked, keys).join(baselines.HybridFilter.build(keys, SHORT, _EPS, intersect=intersect).probe(asked), "query_id"))


@register("base_tuned_trie_bloom")
def _tuned(spark: SparkSession, d: str) -> DataFrame:
    """Tuned on ranges near keys, asked there and, as a shift, anywhere."""
    keys, sample = k.range_queries(k.integer_keys(spark, d, "normal"), "same_dist", SHORT)
    f = baselines.TunedTrieBloom.build(keys, sample=sample)
    out = None
    for kind in ("same_dist", "uniform_ends"):
        asked = k.range_queries(k.integer_keys(spark, d, "normal"), kind, SHORT)[1]
        part = metrics.fpr(range_is_empty(asked, keys).join(f.probe(asked), "query_id")).select(F.lit(kind).alias("kind"), "*")
        out = part if out is None else out.union(part)
    return out


# all filters together, at equal budgets

#: Those that every experiment on integers builds, with what they get: keys and bits per key.
CONTESTANTS: dict[str, Callable[[DataFrame | Ranked, float], object]] = {
    "base": lambda keys, bpk: BaseFilter.build(keys, t=1024, bpk=bpk, sorted_input=True),
    "truncated_trie": lambda keys, bpk: baselines.TruncatedTrie.build(keys, bpk=bpk),
    "dyadic_bloom": lambda keys, bpk: baselines.DyadicBloom.build(keys, bpk, SHORT),
    "shared_bitmap": lambda keys, bpk: baselines.SharedDyadicBitmap.build(keys, bpk, SHORT),
    "spline_bitmap": lambda keys, bpk: baselines.SplineBitmap.build(keys, bpk),
    "pruned_spline": lambda keys, bpk: baselines.PrunedSplineBitmap.build(keys, bpk),
    "local_hash": lambda keys, bpk: baselines.LocalHashSet.build(keys, bpk),
    "prefix_suffix": lambda keys, bpk: baselines.PrefixSuffixTable.build(keys, bpk, SHORT),
}
FEW = ("base", "truncated_trie", "spline_bitmap", "local_hash", "prefix_suffix")


def stored_bits(f: object) -> int:
    bits = f.bits()
    return int(bits if isinstance(bits, int) else bits.agg(F.sum("bits")).first()[0])


def lengths_of(keys: DataFrame, kind: str, lengths: tuple[int, ...]) -> tuple[Ranked, DataFrame]:
    """(key set, ranked and with neighbours, queries of all lengths with range_length and empty), both written: every filter gets and is asked the same."""
    kept, out = None, None
    for n in lengths:
        kept, asked = k.range_queries(keys, kind, n)
        part = asked.select("lo", "hi", F.lit(n).cast("long").alias("range_length"))
        out = part if out is None else out.union(part)
    ranked = with_neighbours(rank_keys(kept))
    # the written table fixes the ids
    return ranked, written(range_is_empty(out, ranked.rows.select("key"), ranked.bounds).withColumn("query_id", F.monotonically_increasing_id()))


def _contestant(name: str, bpk: float, kept: Ranked, asked: DataFrame) -> list[tuple]:
    began = time.perf_counter()
    try:
        f = CONTESTANTS[name](kept, bpk)
    except baselines.Infeasible:
        return [(name, float(bpk), None, None, None, None, None, None, None, None)]
    size = stored_bits(f) / max(kept.n, 1)
    built = time.perf_counter() - began
    began = time.perf_counter()
    # one row for each length
    found = metrics.fpr(asked.join(f.probe(asked.select("query_id", "lo", "hi")), "query_id"), ("range_length",)).collect()
    per_query = (time.perf_counter() - began) * 1e6 / max(1, sum(r["n_queries"] for r in found))
    return [(name, float(bpk), r["range_length"], r["n_queries"], r["n_empty"], r["false_positives"], r["false_negatives"], round(size, 3), round(built, 3), round(per_query, 2)) for r in found]


def contest(spark: SparkSession, keys: DataFrame, kind: str, names: tuple[str, ...], budgets: tuple[float, ...], lengths: tuple[int, ...]) -> DataFrame:
    """A row for each filter, budget and range length; a filter that the budget is too small for has one row without counts.

    The key set is sorted once for all; build_seconds begin with it.
    """
    kept, asked = lengths_of(written(keys), kind, lengths)
    rows = []
    for name in names:
        for bpk in budgets:
            # what one filter wrote is of no use to the next
            with released(spark):
                rows += _contestant(name, bpk, kept, asked)
    return spark.createDataFrame(rows, "filter string, bpk double, range_length long, n_queries long, n_empty long, false_positives long, false_negatives long, stored_bpk double, build_seconds double, us_per_query double")


for _set in SETS:

    @register(f"exp1_{_set}")
    def _exp1(spark: SparkSession, d: str, name: str = _set) -> DataFrame:
        """False positives by range length at 10 and 16 bits per key."""
        return contest(spark, k.integer_keys(spark, d, name), "held_out", tuple(CONTESTANTS), (10, 16), LENGTHS)

    @register(f"exp2_{_set}")
    def _exp2(spark: SparkSession, d: str, name: str = _set) -> DataFrame:
        """False positives by memory, ranges of 1,024."""
        return contest(spark, k.integer_keys(spark, d, name), "held_out", FEW, (8, 12, 16, 20), (1 << 10,))


@register("exp4")
def _exp4(spark: SparkSession, d: str) -> DataFrame:
    """Time of non-empty queries by budget and length."""
    return contest(spark, k.integer_keys(spark, d, "uniform"), "non_empty", FEW, (10, 16), (1, 1 << 10))


@register("exp4m")
def _exp4m(spark: SparkSession, d: str) -> DataFrame:
    """Time of queries of which half are empty."""
    return contest(spark, k.integer_keys(spark, d, "uniform"), "mixed", FEW, (16,), (1, 1 << 10))


@register("exp5")
def _exp5(spark: SparkSession, d: str) -> DataFrame:
    """Construction time as the number of keys grows, 16 bits per key."""
    keys, rows = written(k.integer_keys(spark, d, "uniform")), []
    for part in (16, 4, 1):
        some = written(keys.where(k.h60(F.col("key").cast("string")) % part == 0))
        n = some.count()
        for name in FEW:
            began = time.perf_counter()
            try:
                size = stored_bits(CONTESTANTS[name](some, 16))
            except baselines.Infeasible:
                continue
            rows.append((name, n, round(size / n, 3), round(time.perf_counter() - began, 3)))
    return spark.createDataFrame(rows, "filter string, n long, stored_bpk double, seconds double")


# growth and deletes: from 1/64 of the keys, doubling by doubling

STEPS = 6


def doublings(keys: DataFrame) -> DataFrame:
    """keys with step: 0 for the first 1/64 by hash, then 1 to 6, each as many as all before."""
    place = k.h60(F.concat(F.lit("grow"), F.col("key").cast("string"))) % 64
    return keys.withColumn("step", F.when(place == 0, 0).otherwise(F.floor(F.log2(place.cast("double"))).cast("int") + 1))


class Growing:
    """One interface for what grows: the dynamic base filter, and the comparison filters that can insert."""

    def __init__(self, name: str, first: DataFrame, final: int, bounds: list):
        self.name = name
        if name == "base":
            self.f = DynamicFilter.build(first, t=64, r=8, bounds=bounds)
        elif name == "spline_bitmap":
            self.f = baselines.SplineBitmap.build(first, 16)
        elif name == "prefix_suffix":
            self.f = baselines.PrefixSuffixTable.build(first, 16, SHORT)
        else:
            # fingerprints long enough for the final size
            self.f = baselines.PrefixSuffixTableExtraBit.build(first, 16 + math.log2(max(1, final)), SHORT)

    def insert(self, df: DataFrame) -> None:
        self._keep(self.f.insert(df))

    def delete(self, df: DataFrame) -> None:
        self._keep(self.f.delete(df))

    def _keep(self, f: object) -> None:
        if self.name == "base":
            f.state = written(f.state)
        else:
            f.rows = written(f.rows)
        self.f = f

    def bits(self) -> int:
        if self.name == "base":
            s = self.f.stats().agg(F.sum("bits")).first()[0] if "bits" in self.f.stats().columns else None
            return int(s) if s is not None else 0
        return stored_bits(self.f)


def grow(spark: SparkSession, d: str, name: str, filters: tuple[str, ...], deletes: bool) -> DataFrame:
    from .operators.anchors import shard_bounds

    all_keys = written(doublings(k.integer_keys(spark, d, name)))
    held = k.h60(F.concat(F.lit("held"), F.col("key").cast("string"))) % 16 == 0
    kept, rows = written(all_keys.where(~held)), []
    ranges = all_keys.where(held).select(F.col("key").alias("query_id"), F.col("key").alias("lo"), (F.col("key") + 1023).alias("hi"))
    leaves = k.h60(F.concat(F.lit("gone"), F.col("key").cast("string"))) % 16
    bounds = shard_bounds(kept.select("key"), shards=8)
    final = kept.count()
    for which in filters:
        f = Growing(which, kept.where("step = 0").select("key"), final, bounds)
        for step in range(1, STEPS + 1):
            began = time.perf_counter()
            f.insert(kept.where(F.col("step") == step).select("key"))
            inserted = time.perf_counter() - began
            deleted, living = 0.0, kept.where(F.col("step") <= step)
            if deletes:
                # each step takes another sixteenth of what has come so far
                began = time.perf_counter()
                f.delete(living.where(((leaves == step) & (F.col("step") <= step)) | ((leaves < step) & (F.col("step") == step))).select("key"))
                deleted = time.perf_counter() - began
                living = living.where(leaves > step)
            living = living.select("key")
            points = living.select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
            missed = f.f.probe(points).where("not positive").count()
            asked = range_is_empty(ranges, living)
            found = metrics.fpr(asked.join(f.f.probe(ranges), "query_id")).first()
            rows.append((which, step, living.count(), found["n_empty"], found["false_positives"], missed + found["false_negatives"], round(inserted, 3), round(deleted, 3)))
    return spark.createDataFrame(rows, "filter string, doubling int, n_keys long, n_empty long, false_positives long, false_negatives long, insert_seconds double, delete_seconds double")


GROW_SQL = """
WITH placed AS (SELECT key, {grow} % 64 AS p, {held} % 16 = 0 AS held, {gone} % 16 AS leaves FROM ({keys})),
stepped AS (SELECT *, CASE WHEN p = 0 THEN 0 ELSE floor(log2(p::DOUBLE))::INTEGER + 1 END AS step FROM placed)
SELECT f AS filter, s::INTEGER AS doubling, (SELECT count(*) FROM stepped WHERE NOT held AND step <= s{alive})::BIGINT AS n_keys, 0::BIGINT AS false_negatives FROM range(1, 7) AS r(s), (VALUES {filters}) AS v(f)
"""


def _grow_sql(name: str, filters: tuple[str, ...], deletes: bool) -> str:
    salted = lambda s: k.h60_duck(f"'{s}' || key::VARCHAR")
    return GROW_SQL.format(grow=salted("grow"), held=salted("held"), gone=salted("gone"), keys=k.integer_sql(name), alive=" AND leaves > s" if deletes else "", filters=", ".join(f"('{f}')" for f in filters))


GROWING, SHRINKING = ("base", "spline_bitmap", "prefix_suffix", "prefix_suffix_extra"), ("base", "spline_bitmap", "prefix_suffix", "prefix_suffix_extra")


@register("exp6")
def _exp6(spark: SparkSession, d: str) -> DataFrame:
    """False positives, false negatives and insert time, doubling by doubling."""
    return grow(spark, d, "skewed", GROWING, deletes=False)


@register("exp8", _grow_sql("skewed", SHRINKING, True))
def _exp8(spark: SparkSession, d: str) -> DataFrame:
    """What is left after deletes at each doubling is never missed."""
    return grow(spark, d, "skewed", SHRINKING, deletes=True).select("filter", "doubling", "n_keys", "false_negatives")


@register("exp7")
def _exp7(spark: SparkSession, d: str) -> DataFrame:
    """Throughput of inserts, and of half inserts and half queries, as the number of shards that work side by side grows."""
    from .operators.anchors import shard_bounds

    keys, rows = written(doublings(k.integer_keys(spark, d, "skewed"))), []
    first, late = keys.where("step < 5").select("key"), written(keys.where("step >= 5").select("key"))
    n = late.count()
    for shards in (1, 2, 4, 8):
        f = DynamicFilter.build(first, t=64, r=8, bounds=shard_bounds(keys.select("key"), shards=shards) if shards > 1 else [])
        f.state = written(f.state)
        began = time.perf_counter()
        after = f.insert(late)
        after.state = written(after.state)
        rows.append(("insert", shards, n, round(n / (time.perf_counter() - began), 1)))
        began = time.perf_counter()
        points = late.select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
        half = k.h60(F.col("key").cast("string")) % 2
        more = f.insert(late.where(half == 0))
        more.state = written(more.state)
        more.probe(points.where(k.h60(F.col("lo").cast("string")) % 2 == 1)).agg(F.sum(F.col("positive").cast("long"))).first()
        rows.append(("mixed", shards, n, round(n / (time.perf_counter() - began), 1)))
    return spark.createDataFrame(rows, "workload string, shards int, n long, operations_per_second double")
