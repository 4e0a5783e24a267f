"""The registered queries of the range-filter library and the SQL that they must agree with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import geometry as g
from .functions.entropy import Codebook, bisection_codes, compression_ratio, entropy_bits, symbol_counts
from .operators.anchors import pick_anchors, prepare_keys, range_is_empty, rank_keys, shard_bounds
from .operators.base import BaseFilter
from .operators.dynamic import DynamicFilter
from .operators.enhanced import EnhancedFilter
from .plans import duck, metrics
from .plans.lineage import written
from .sources import keysets as k

Query = Callable[[SparkSession, str], DataFrame]
T, R = 64, 8
LENGTHS = {"r0": 1, "r5": 1 << 5, "r10": 1 << 10, "r20": 1 << 20}
PRIME = 1_000_003

_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        _queries[name] = f
        if sql is not None:
            _oracles[name] = sql
        return f

    return put


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_oracles)


# key sets and query sets

for _name in k.INTEGER_SETS:

    @register(f"keys_{_name}", f"SELECT count(*)::BIGINT AS n, min(key) AS least, max(key) AS most, sum(key % {PRIME})::BIGINT AS checksum FROM ({k.integer_sql(_name)})")
    def _keys(spark: SparkSession, d: str, name: str = _name) -> DataFrame:
        return k.integer_keys(spark, d, name).agg(F.count("*").alias("n"), F.min("key").alias("least"), F.max("key").alias("most"), F.sum(F.col("key") % PRIME).alias("checksum"))


for _name in ("words", "emails", "urls", "names"):

    @register(f"keys_{_name}", f"WITH s AS ({k.string_sql(_name)}) SELECT count(*)::BIGINT AS n, min(key) AS least, max(key) AS most, sum({k.h60_duck('key')} % {PRIME})::BIGINT AS checksum FROM s")
    def _skeys(spark: SparkSession, d: str, name: str = _name) -> DataFrame:
        return k.string_keys(spark, d, name).agg(F.count("*").alias("n"), F.min("key").alias("least"), F.max("key").alias("most"), F.sum(k.h60(F.col("key")) % PRIME).alias("checksum"))


for _kind in ("held_out", "point", "uniform_ends", "same_dist", "adversarial", "mixed"):

    @register(f"queries_{_kind}", f"WITH {k.range_queries_sql('skewed', _kind, 1 << 10)} SELECT count(*)::BIGINT AS n, sum((NOT EXISTS (SELECT 1 FROM keys x WHERE x.key BETWEEN q.lo AND q.hi))::BIGINT)::BIGINT AS n_empty, sum(lo % {PRIME})::BIGINT AS checksum FROM queries q")
    def _made(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        keys, asked = k.range_queries(k.integer_keys(spark, d, "skewed"), kind, 1 << 10)
        return range_is_empty(asked, keys).agg(F.count("*").alias("n"), F.sum(F.col("empty").cast("long")).alias("n_empty"), F.sum(F.col("lo") % PRIME).alias("checksum"))


@register("queries_adjacent", f"WITH allkeys AS ({k.WORDS_DUCK}), {k.ADJACENT_DUCK} SELECT count(*)::BIGINT AS n, 0::BIGINT AS n_not_empty, sum({k.h60_duck('lo')} % {PRIME})::BIGINT AS checksum FROM chosen")
def _adjacent(spark: SparkSession, d: str) -> DataFrame:
    keys, asked = k.adjacent_pairs(k.string_keys(spark, d, "words"))
    binary = lambda df, *c: df.select(*(F.col(x).cast("binary").alias(x) if x in c else F.col(x) for x in df.columns))
    judged = range_is_empty(binary(asked, "lo", "hi"), binary(keys, "key"))
    return judged.agg(F.count("*").alias("n"), F.sum((~F.col("empty")).cast("long")).alias("n_not_empty"), F.sum(k.h60(F.col("lo").cast("string")) % PRIME).alias("checksum"))


# the static base filter

def _built(spark: SparkSession, d: str, name: str = "clustered", t: int = T, r: int = R, **options) -> BaseFilter:
    return BaseFilter.build(k.integer_keys(spark, d, name), t=t, eps=2.0 / 2**r, **options)


@register("anchors_every_t", duck.keys_with("clustered", "SELECT anchor_no, key, is_sentinel FROM anchors"))
def _anchors(spark: SparkSession, d: str) -> DataFrame:
    keys = prepare_keys(k.integer_keys(spark, d, "clustered"))
    return pick_anchors(rank_keys(keys), T)


@register("block_geometry", duck.keys_with("clustered", "SELECT block_id, pred, succ, shared, redundant FROM blocks"))
def _geometry(spark: SparkSession, d: str) -> DataFrame:
    return _built(spark, d).blocks


@register("infixes_static", duck.keys_with("clustered", "SELECT block_id, infix FROM infixes"))
def _infixes(spark: SparkSession, d: str) -> DataFrame:
    return _built(spark, d).infixes


@register("infixes_keep_redundant", duck.keys_with("clustered", "SELECT block_id, infix FROM infixes", drop_redundant=False))
def _infixes_kept(spark: SparkSession, d: str) -> DataFrame:
    return _built(spark, d, drop_redundant=False).infixes


@register("rebuild_roundtrip", duck.keys_with("clustered", "SELECT count(*)::BIGINT AS n, 0::BIGINT AS mismatches FROM infixes"))
def _rebuild(spark: SparkSession, d: str) -> DataFrame:
    f = _built(spark, d)
    rows = f.keyed.join(f.blocks.select("block_id", "pred"), "block_id")
    back = g.derive_infix(g.rebuild_prefix(F.col("infix"), F.col("pred"), F.col("shared"), F.col("redundant"), f.m), F.col("shared"), F.col("redundant"), f.m)
    return rows.agg(F.count("*").alias("n"), F.sum((back != F.col("infix")).cast("long")).alias("mismatches"))


@register("quotient_runs", duck.keys_with("clustered", f"SELECT block_id, infix >> {R} AS quotient, count(*)::BIGINT AS run_length FROM infixes GROUP BY ALL"))
def _runs(spark: SparkSession, d: str) -> DataFrame:
    return metrics.runs(_built(spark, d).infixes, R)


@register("run_length_hist", duck.keys_with("uniform", f"SELECT run_length, count(*)::BIGINT AS n FROM (SELECT count(*)::BIGINT AS run_length FROM infixes GROUP BY block_id, infix >> {R}) GROUP BY ALL"))
def _run_hist(spark: SparkSession, d: str) -> DataFrame:
    return metrics.runs(_built(spark, d, "uniform").infixes, R).groupBy("run_length").agg(F.count("*").alias("n"))


@register("identical_infix_share", duck.keys_with("skewed", "SELECT sum(c)::BIGINT AS n, coalesce(sum(CASE WHEN c > 1 THEN c END), 0)::BIGINT AS n_identical FROM (SELECT count(*) AS c FROM infixes GROUP BY block_id, infix)"))
def _identical(spark: SparkSession, d: str) -> DataFrame:
    return metrics.identical_share(_built(spark, d, "skewed").infixes)


@register("uniformity_bins", duck.keys_with("uniform", f"SELECT infix >> {R + 6 - 4} AS bin, count(*)::BIGINT AS n FROM infixes GROUP BY ALL"))
def _bins(spark: SparkSession, d: str) -> DataFrame:
    f = _built(spark, d, "uniform")
    return metrics.uniformity(f.infixes, f.m)


def _judged(spark: SparkSession, d: str, name: str, kind: str, length: int, t: int = T, r: int = R) -> DataFrame:
    keys, asked = k.range_queries(written(k.integer_keys(spark, d, name)), kind, length)
    f = BaseFilter.build(keys, t=t, eps=2.0 / 2**r, sorted_input=True)
    return range_is_empty(asked, keys, f.bounds).join(f.probe(asked), "query_id")


@register("probe_cause", duck.verdicts_with("normal", "mixed", 1 << 10, "SELECT cause, count(*)::BIGINT AS n, sum(empty::BIGINT)::BIGINT AS n_empty FROM verdicts GROUP BY cause"))
def _cause(spark: SparkSession, d: str) -> DataFrame:
    return _judged(spark, d, "normal", "mixed", 1 << 10).groupBy("cause").agg(F.count("*").alias("n"), F.sum(F.col("empty").cast("long")).alias("n_empty"))


for _label, _length in LENGTHS.items():

    @register(f"probe_range_{_label}", duck.verdicts_with("clustered", "held_out", _length, "SELECT query_id, empty, cause IN ('anchor', 'infix') AS positive FROM verdicts"))
    def _probe(spark: SparkSession, d: str, length: int = _length) -> DataFrame:
        return _judged(spark, d, "clustered", "held_out", length).select("query_id", "empty", "positive")


def _union_sql(parts: list[tuple[str, str]]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({sql})" for _, sql in parts)


@register("fpr_by_r", _union_sql([(x, duck.verdicts_with("normal", "held_out", n, f"SELECT {n}::BIGINT AS range_length, {duck.COUNTS} FROM verdicts")) for x, n in LENGTHS.items()]))
def _fpr_by_r(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for n in LENGTHS.values():
        part = metrics.fpr(_judged(spark, d, "normal", "held_out", n)).select(F.lit(n).cast("long").alias("range_length"), "*")
        out = part if out is None else out.union(part)
    return out


@register("fpr_by_bpk", _union_sql([("", duck.verdicts_with("uniform", "held_out", 1 << 10, f"SELECT {r}::BIGINT AS remainder_bits, {duck.COUNTS} FROM verdicts", r=r)) for r in (4, 6, 8, 10)]))
def _fpr_by_bpk(spark: SparkSession, d: str) -> DataFrame:
    parts = [metrics.fpr(_judged(spark, d, "uniform", "held_out", 1 << 10, r=r)).select(F.lit(r).cast("long").alias("remainder_bits"), "*") for r in (4, 6, 8, 10)]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@register("fpr_by_t", _union_sql([("", duck.verdicts_with("skewed", "held_out", 1 << 10, f"SELECT {t}::BIGINT AS t, {duck.COUNTS} FROM verdicts", t=t)) for t in (16, 64, 256, 1024)]))
def _fpr_by_t(spark: SparkSession, d: str) -> DataFrame:
    parts = [metrics.fpr(_judged(spark, d, "skewed", "held_out", 1 << 10, t=t)).select(F.lit(t).cast("long").alias("t"), "*") for t in (16, 64, 256, 1024)]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@register("no_false_negatives", duck.verdicts_with("skewed", "non_empty", 1 << 10, "SELECT count(*)::BIGINT AS n_queries, 0::BIGINT AS false_negatives FROM verdicts WHERE NOT empty"))
def _no_fn(spark: SparkSession, d: str) -> DataFrame:
    return _judged(spark, d, "skewed", "non_empty", 1 << 10).where("not empty").agg(F.count("*").alias("n_queries"), F.sum((~F.col("positive")).cast("long")).alias("false_negatives"))


@register("packed_equals_relational", duck.verdicts_with("clustered", "mixed", 1 << 10, "SELECT count(*)::BIGINT AS n_queries, 0::BIGINT AS mismatches FROM verdicts"))
def _packed(spark: SparkSession, d: str) -> DataFrame:
    keys, asked = k.range_queries(k.integer_keys(spark, d, "clustered"), "mixed", 1 << 10)
    f = BaseFilter.build(keys, t=T, eps=2.0 / 2**R, sorted_input=True)
    both = f.probe(asked).join(f.probe_packed(asked).select("query_id", F.col("positive").alias("p")), "query_id")
    return both.agg(F.count("*").alias("n_queries"), F.sum((F.col("positive") != F.col("p")).cast("long")).alias("mismatches"))


@register("bpk_report", duck.keys_with("uniform", f"SELECT 'runends' AS component, count(*)::BIGINT AS bits FROM infixes UNION ALL SELECT 'slots', {R} * count(*)::BIGINT FROM infixes UNION ALL SELECT 'anchors', 160 * (SELECT count(*) FROM anchors)::BIGINT UNION ALL SELECT 'occupieds', (SELECT sum(({duck.infix_sql('succ', R + 6)} >> {R}) - ({duck.infix_sql('pred', R + 6)} >> {R}) + 1) FROM blocks)::BIGINT"))
def _bpk(spark: SparkSession, d: str) -> DataFrame:
    return _built(spark, d, "uniform").bits()


@register("gap_table", f"WITH keys AS ({k.integer_sql('clustered')}) SELECT after, width FROM (SELECT key AS after, lead(key) OVER (ORDER BY key) - key - 1 AS width FROM keys) WHERE width > 0")
def _gaps(spark: SparkSession, d: str) -> DataFrame:
    keys = k.integer_keys(spark, d, "clustered")
    return metrics.gaps(keys, shard_bounds(keys))


@register("topk_gaps", f"WITH keys AS ({k.integer_sql('skewed')}) SELECT after, width FROM (SELECT key AS after, lead(key) OVER (ORDER BY key) - key - 1 AS width FROM keys) WHERE width > 0 ORDER BY width DESC, after LIMIT 20")
def _top_gaps(spark: SparkSession, d: str) -> DataFrame:
    keys = k.integer_keys(spark, d, "skewed")
    return metrics.gaps(keys, shard_bounds(keys)).orderBy(F.desc("width"), "after").limit(20)


# the entropy code and the enhanced filter

for _k in (0, 1):
    _ctx = "''" if _k == 0 else "CASE WHEN i = 1 THEN '' ELSE substr(h, 2 * i - 3, 2) END"

    @register(f"symbol_counts_k{_k}", f"SELECT {_ctx} AS context, substr(h, 2 * i - 1, 2) AS symbol, count(*)::BIGINT AS freq FROM (SELECT h, unnest(range(1, length(h) // 2 + 1)) AS i FROM (SELECT hex(encode(key)) AS h FROM ({k.string_sql('urls')}))) GROUP BY ALL")
    def _symbols(spark: SparkSession, d: str, order: int = _k) -> DataFrame:
        return symbol_counts(k.string_keys(spark, d, "urls"), order)


@register("bisection_codes_k0")
def _codes(spark: SparkSession, d: str) -> DataFrame:
    freqs = sorted((int(r["symbol"], 16), r["freq"]) for r in symbol_counts(k.string_keys(spark, d, "words"), 0).collect())
    codes = bisection_codes(freqs)
    return spark.createDataFrame([(s, f, codes[s], float(entropy_bits(freqs))) for s, f in freqs], "symbol int, freq long, code string, entropy double")


@register("compression_by_order")
def _compression(spark: SparkSession, d: str) -> DataFrame:
    keys = written(k.string_keys(spark, d, "urls"))
    rows = [(o, float(compression_ratio(keys, book := Codebook.build(keys, o))), book.bits()) for o in range(4)]
    return spark.createDataFrame(rows, "context_bytes int, ratio double, codebook_bits long")


VARIANTS = {"base": (None, False), "base_code": (2, False), "base_tries": (None, True), "enhanced": (2, True)}


@register("ablation_16bpk")
def _ablation(spark: SparkSession, d: str) -> DataFrame:
    """False positives of adjacent empty ranges for the base filter, either addition, and both."""
    out = None
    for name in ("words", "urls"):
        keys, asked = k.adjacent_pairs(written(k.string_keys(spark, d, name)))
        keys, asked = written(keys), written(asked)
        book = Codebook.build(keys, 2)
        for variant, (order, tries) in VARIANTS.items():
            f = EnhancedFilter.build(keys, t=T, bpk=16, k=order, tries=tries, book=book if order else None)
            part = f.probe(asked).agg(F.count("*").alias("n_queries"), F.sum(F.col("positive").cast("long")).alias("false_positives")).select(F.lit(name).alias("key_set"), F.lit(variant).alias("variant"), "*")
            out = part if out is None else out.union(part)
    return out


@register("trie_formats")
def _formats(spark: SparkSession, d: str) -> DataFrame:
    f = EnhancedFilter.build(k.string_keys(spark, d, "urls"), t=T, bpk=16, k=2)
    return f.tries.where("n_keys > 1").groupBy("format").agg(F.count("*").alias("n"), F.sum("code_bits").alias("code_bits"), F.sum("n_nodes").alias("n_nodes"), F.sum(F.col("has_prefix").cast("long")).alias("with_prefix_nodes"), F.max("longest_path").alias("longest_path"))


@register("enhanced_no_false_negatives")
def _enhanced_fn(spark: SparkSession, d: str) -> DataFrame:
    keys = k.string_keys(spark, d, "words")
    asked = keys.select((k.h60(F.col("key"))).alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
    return EnhancedFilter.build(keys, t=T, bpk=16).probe(asked).agg(F.count("*").alias("n_queries"), F.sum((~F.col("positive")).cast("long")).alias("false_negatives"))


# the dynamic filter

def _grown(spark: SparkSession, d: str, delete: bool = False) -> tuple[DynamicFilter, DataFrame, DataFrame]:
    keys, asked = k.range_queries(k.integer_keys(spark, d, "skewed"), "held_out", 1 << 10)
    late = k.h60(F.concat(F.lit("late"), F.col("key").cast("string"))) % 8
    f = DynamicFilter.build(keys.where(late == 0), t=T, r=R, bounds=shard_bounds(keys, shards=8)).insert(keys.where(late != 0))
    if delete:
        gone = keys.where(late == 3)
        f, keys = f.delete(gone), keys.where(late != 3)
    return f, keys, asked


for _label, _delete in (("insert", False), ("delete", True)):
    _kept = f"SELECT key FROM keys WHERE {k.h60_duck(chr(39) + 'late' + chr(39) + ' || key::VARCHAR')} % 8 <> 3" if _delete else "SELECT key FROM keys"

    @register(f"dyn_{_label}", f"WITH {k.range_queries_sql('skewed', 'held_out', 1 << 10)} SELECT count(*)::BIGINT AS n_keys, 0::BIGINT AS false_negatives FROM ({_kept})")
    def _dynamic(spark: SparkSession, d: str, delete: bool = _delete) -> DataFrame:
        f, keys, _ = _grown(spark, d, delete)
        points = keys.select(F.col("key").alias("query_id"), F.col("key").alias("lo"), F.col("key").alias("hi"))
        return f.probe(points).agg(F.count("*").alias("n_keys"), F.sum((~F.col("positive")).cast("long")).alias("false_negatives"))


@register("dyn_fpr")
def _dynamic_fpr(spark: SparkSession, d: str) -> DataFrame:
    f, keys, asked = _grown(spark, d)
    return metrics.fpr(range_is_empty(asked, keys).join(f.probe(asked), "query_id"))


@register("dyn_stretch")
def _stretch(spark: SparkSession, d: str) -> DataFrame:
    return _grown(spark, d)[0].stats()


@register("dyn_length_mix")
def _lengths(spark: SparkSession, d: str) -> DataFrame:
    return _grown(spark, d)[0].lengths()


# the comparison filters, the generic operators and the formulas register themselves
from . import contests as _contests  # noqa: E402, F401
from . import generic as _generic  # noqa: E402, F401
from . import endtoend as _endtoend  # noqa: E402, F401
from . import formulas as _formulas  # noqa: E402, F401
