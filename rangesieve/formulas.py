"""Formulas as registered queries, each over the keys of a given table: lineitem's rows as ranges and keys, dealt to a filter for each line number, and orders as they come in."""

from __future__ import annotations

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from .catalogue import register
from .functions import theory
from .operators.dynamic import duplicate_void
from .plans import metrics
from .sources import keysets as k

#: A filter for each line number: its keys, the bits of the greatest one, and ranges as long as the mean gap.
PARTS_DUCK = "parts AS (SELECT l_linenumber AS part, count(*)::BIGINT AS n, length(bin(max(l_orderkey)))::BIGINT AS key_bits, (max(l_orderkey) - min(l_orderkey)) // count(*) + 1 AS len FROM lineitem GROUP BY l_linenumber), rates AS (SELECT e FROM range(2, 13) AS t(e))"
RATES = range(2, 13)
#: A range for each row of lineitem.
_SPAN = "CAST(floor(l_extendedprice / 10) AS BIGINT) + 1"


def parts(spark: SparkSession, d: str) -> list[Row]:
    """(part, n, key_bits, len), as many rows as an order has lines at most."""
    at = F.col("l_orderkey")
    by = k.table(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("part"))
    return by.agg(F.count("*").alias("n"), F.length(F.bin(F.max(at))).alias("key_bits"), F.expr("(max(l_orderkey) - min(l_orderkey)) div count(*) + 1").alias("len")).collect()


@register("goal_matrix", f"""
WITH goals AS (SELECT * FROM (VALUES
  ('truncated_trie', false, false, true, true, false), ('dyadic_bloom', true, true, false, false, false), ('shared_dyadic_bitmap', false, false, false, false, false),
  ('prefix_hash_bitmap', false, false, false, false, false), ('tuned_trie_bloom', false, false, false, false, false), ('spline_bitmap', false, true, true, false, false),
  ('pruned_spline_bitmap', false, true, true, false, false), ('local_hash_set', true, true, false, false, false), ('prefix_suffix_table', true, true, false, false, true),
  ('prefix_suffix_table_extra_bit', true, true, false, false, true), ('base_filter', false, true, true, true, true), ('enhanced_filter', false, true, true, true, true)
) AS v(filter, robust, semi_robust, any_length_queries, any_length_keys, dynamic)),
asked AS (SELECT count(*) AS every, sum(({_SPAN} <= 1024)::BIGINT) AS short, sum((length(concat(l_orderkey, '#', l_linenumber)) <= 8)::BIGINT) AS narrow, sum((l_linenumber > 1)::BIGINT) AS late FROM lineitem)
SELECT goals.*, (CASE WHEN any_length_queries THEN every ELSE short END)::BIGINT AS ranges_taken, (CASE WHEN any_length_keys THEN every ELSE narrow END)::BIGINT AS keys_taken, (CASE WHEN dynamic THEN late ELSE 0 END)::BIGINT AS inserts_taken FROM goals, asked""")
def _goals(spark: SparkSession, d: str) -> DataFrame:
    """Which filter gives which guarantee, and what it takes of lineitem: ranges of any length or up to 1,024, text keys of any length or up to 8 bytes, later lines as inserts."""
    count = lambda c, name: F.sum(F.expr(c).cast("long")).alias(name)
    asked = k.table(spark, d, "lineitem").agg(F.count("*").alias("every"), count(f"{_SPAN} <= 1024", "short"), count("length(concat(l_orderkey, '#', l_linenumber)) <= 8", "narrow"), count("l_linenumber > 1", "late"))
    either = lambda flag, a, b, name: F.when(F.col(flag), a).otherwise(b).alias(name)
    # one row
    return metrics.goal_matrix(spark).join(F.broadcast(asked)).select(
        "filter", "robust", "semi_robust", "any_length_queries", "any_length_keys", "dynamic",
        either("any_length_queries", F.col("every"), F.col("short"), "ranges_taken"), either("any_length_keys", F.col("every"), F.col("narrow"), "keys_taken"), either("dynamic", F.col("late"), F.lit(0).cast("long"), "inserts_taken"),
    )


@register("max_range_lengths", f"SELECT b::INTEGER AS bpk, max_length, (SELECT count(*) FROM lineitem WHERE {_SPAN} <= max_length)::BIGINT AS n_ranges FROM (SELECT b, 1::BIGINT << greatest(0, floor(log2(0.01 * pow(2, b))))::INTEGER AS max_length FROM range(8, 21) AS t(b))")
def _max_range(spark: SparkSession, d: str) -> DataFrame:
    """The longest range for which a robust filter holds 1 % within a budget, and how many of lineitem's ranges are no longer."""
    longest = {b: theory.max_range(b, 0.01) for b in range(8, 21)}
    span = F.expr(_SPAN)
    r = k.table(spark, d, "lineitem").agg(*(F.sum((span <= n).cast("long")).alias(str(b)) for b, n in longest.items())).first()
    return spark.createDataFrame([(b, n, r[str(b)]) for b, n in longest.items()], "bpk int, max_length long, n_ranges long")


@register("theory_bpk", f"WITH {PARTS_DUCK} SELECT part::INTEGER AS part, n, e::INTEGER AS log2_inverse_eps, round(3.09 + key_bits / 1024.0 + e, 6)::DOUBLE AS static_bpk, round(1.09 + key_bits / 1024.0 + (2 + e) / (0.95 * 0.95), 6)::DOUBLE AS dynamic_bpk FROM parts, rates")
def _theory(spark: SparkSession, d: str) -> DataFrame:
    rows = [(p["part"], p["n"], e, round(theory.static_bpk(2.0**-e, p["key_bits"]), 6), round(theory.dynamic_bpk(2.0**-e, p["key_bits"]), 6)) for p in parts(spark, d) for e in RATES]
    return spark.createDataFrame(rows, "part int, n long, log2_inverse_eps int, static_bpk double, dynamic_bpk double")


@register("lower_bounds", f"WITH {PARTS_DUCK} SELECT part::INTEGER AS part, len::BIGINT AS max_length, e::INTEGER AS log2_inverse_eps, round(log2(len) + e, 6)::DOUBLE AS data_aware, e::DOUBLE AS data_oblivious, round(log2(len) + 2 * e, 6)::DOUBLE AS combined FROM parts, rates")
def _bounds(spark: SparkSession, d: str) -> DataFrame:
    rows = [(p["part"], p["len"], e, *(round(theory.lower_bound(x, 2.0**-e, p["len"]), 6) for x in ("data_aware", "data_oblivious", "combined"))) for p in parts(spark, d) for e in RATES]
    return spark.createDataFrame(rows, "part int, max_length long, log2_inverse_eps int, data_aware double, data_oblivious double, combined double")


_MEMORY = {
    "dyadic_bloom": "1.44 * r", "prefix_hash_bitmap": "1.2 * r", "spline_bitmap": "2.4 + e", "pruned_spline_bitmap": "2.4 + e", "local_hash_set": "2 + r", "prefix_suffix_table": "(3.125 + r) / 0.95",
    "prefix_suffix_table_extra_bit": "(4.125 + r) / 0.95", "base_static": "3.19 + e", "base_dynamic": "1.19 + (2 + e) / 0.9025", "enhanced_static": "3.19 + e", "enhanced_dynamic": "1.19 + (2 + e) / 0.9025",
}


@register("theory_memory", f"WITH {PARTS_DUCK}, sized AS (SELECT part, n, e, log2(len) + e AS r FROM parts, rates) " + " UNION ALL ".join(f"SELECT '{x}' AS filter, part::INTEGER AS part, n, e::INTEGER AS log2_inverse_eps, round(({f})::DOUBLE, 6) AS bpk FROM sized" for x, f in _MEMORY.items()))
def _memory(spark: SparkSession, d: str) -> DataFrame:
    """Bits per key of every filter over every part, at ranges as long as the part's mean gap."""
    rows = [(x, p["part"], p["n"], e, round(theory.bpk(x, 2.0**-e, p["len"]), 6)) for p in parts(spark, d) for x in _MEMORY for e in RATES]
    return spark.createDataFrame(rows, "filter string, part int, n long, log2_inverse_eps int, bpk double")


@register("infix_probability", f"WITH {PARTS_DUCK} SELECT part::INTEGER AS part, n, round(n * p * power(1 - p, n - 1), 10) AS one, round(n * (n - 1) / 2 * p * p * power(1 - p, n - 2), 10) AS two FROM (SELECT part, n, 0.01::DOUBLE / (2 * n) AS p FROM parts)")
def _probability(spark: SparkSession, d: str) -> DataFrame:
    """Chance that one or two of a part's keys fall on one infix, were they uniform."""
    rows = [(p["part"], p["n"], *(round(theory.infix_probability(0.01, p["n"], i), 10) for i in (1, 2))) for p in parts(spark, d)]
    return spark.createDataFrame(rows, "part int, n long, one double, two double")


@register("dyn_bound", "SELECT month, n::BIGINT AS n, round(0.01 * (log2(n) + 2) / 2, 8) AS point, round(0.01 * (log2(n) + 2), 8) AS range_, round(0.01, 8)::DOUBLE AS static_point, round(0.02, 8)::DOUBLE AS static_range FROM (SELECT month, sum(c) OVER (ORDER BY month) AS n FROM (SELECT strftime(CAST(o_orderdate AS DATE), '%Y-%m') AS month, count(*) AS c FROM orders GROUP BY ALL))")
def _dyn_bound(spark: SparkSession, d: str) -> DataFrame:
    """The bounds after each month's orders are inserted."""
    months = k.table(spark, d, "orders").groupBy(F.date_format(F.col("o_orderdate").cast("date"), "yyyy-MM").alias("month")).agg(F.count("*").alias("c")).collect()
    rows, n = [], 0
    for r in sorted(months, key=lambda r: r["month"]):
        n += r["c"]
        rows.append((r["month"], n, *(round(x, 8) for x in (theory.dynamic_bound(0.01, n, 1), theory.dynamic_bound(0.01, n, 2), theory.static_bound(0.01, 1), theory.static_bound(0.01, 2)))))
    return spark.createDataFrame(rows, "month string, n long, point double, range_ double, static_point double, static_range double")


@register("dyn_duplicates", "SELECT m::INTEGER AS missing, i::INTEGER AS value, ((i << m::INTEGER) + j)::BIGINT AS quotient, n FROM (SELECT o_orderkey % 4 AS m, o_orderkey // 4 % 64 AS i, count(*)::BIGINT AS n FROM orders GROUP BY ALL), range(0, 8) AS c(j) WHERE j < (1 << m::INTEGER)")
def _duplicates(spark: SparkSession, d: str) -> DataFrame:
    """The quotients that stand for an infix whose last `missing` quotient bits are gone, and the orders behind it: the low key bits are read as what is gone and what is left."""
    found = k.table(spark, d, "orders").groupBy(F.expr("o_orderkey % 4").alias("m"), F.expr("o_orderkey div 4 % 64").alias("i")).agg(F.count("*").alias("n")).collect()
    return spark.createDataFrame([(r["m"], r["i"], q, r["n"]) for r in found for q in duplicate_void(r["i"], r["m"])], "missing int, value int, quotient long, n long")
