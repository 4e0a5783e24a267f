"""DuckDB SQL of the base filter: the filter is a function of the key set, so SQL can replay its every verdict."""

from __future__ import annotations

import math

from ..sources.keysets import integer_sql, range_queries_sql

BITLEN = "(CASE WHEN {x} = 0 THEN 0 ELSE length(bin({x})) END)"


def bitlen(x: str) -> str:
    return BITLEN.format(x=f"({x})")


def infix_sql(k: str, m: int) -> str:
    rest = f"(CASE WHEN lft >= {m - 1} THEN ({k} >> greatest(lft - {m - 1}, 0)::INTEGER) & {(1 << (m - 1)) - 1} ELSE ({k} & ((1::BIGINT << lft::INTEGER) - 1)) << greatest({m - 1} - lft, 0)::INTEGER END)"
    return f"(((({k} >> fst::INTEGER) & 1) << {m - 1}) | {rest})"


def filter_ctes(t: int, r: int, drop_redundant: bool = True) -> str:
    """anchors, blocks, infixes of the CTE `keys`."""
    m = r + math.ceil(math.log2(t))
    xor = "xor(pred, succ)"
    below = f"({bitlen(xor)} - 1)"
    both = f"(pred & ~succ & ((1::BIGINT << {below}::INTEGER) - 1))"
    red = f"({below} - {bitlen(f'~{both} & ((1::BIGINT << {below}::INTEGER) - 1)')})" if drop_redundant else "0"
    return f"""ranked AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS rank, count(*) OVER () - 1 AS last FROM keys),
anchors AS (SELECT ((rank + {t - 1}) // {t})::BIGINT AS anchor_no, key, rank % {t} <> 0 AS is_sentinel FROM ranked WHERE rank % {t} = 0 OR rank = last),
bare AS (SELECT * FROM (SELECT anchor_no AS block_id, key AS pred, lead(key) OVER (ORDER BY key) AS succ FROM anchors) WHERE succ IS NOT NULL),
blocks AS (SELECT *, fst - redundant AS lft FROM (SELECT *, (62 - {bitlen(xor)})::INTEGER AS shared, {red}::INTEGER AS redundant, {below} AS fst FROM bare)),
infixes AS (SELECT b.*, key, {infix_sql('key', m)} AS infix FROM ranked JOIN blocks b ON block_id = rank // {t} WHERE rank % {t} <> 0 AND key < succ)"""


def verdict_ctes(t: int, r: int) -> str:
    m = r + math.ceil(math.log2(t))
    return f"""truth AS (SELECT q.*, NOT EXISTS (SELECT 1 FROM keys k WHERE k.key BETWEEN q.lo AND q.hi) AS empty FROM queries q),
routed AS (SELECT q.*, b.* FROM truth q ASOF LEFT JOIN blocks b ON q.hi >= b.pred),
asked AS (SELECT *, CASE WHEN pred IS NULL THEN 'outside' WHEN pred >= lo THEN 'anchor' WHEN succ BETWEEN lo AND hi THEN 'anchor' WHEN lo > succ THEN 'outside' ELSE 'block' END AS route FROM routed),
ends AS (SELECT *, CASE WHEN route = 'block' THEN {infix_sql('lo', m)} END AS il, CASE WHEN route = 'block' THEN {infix_sql('hi', m)} END AS ih FROM asked),
verdicts AS (SELECT query_id, lo, hi, kind, empty, CASE WHEN route <> 'block' THEN route WHEN EXISTS (SELECT 1 FROM infixes i WHERE i.block_id = e.block_id AND i.infix BETWEEN il AND ih) THEN 'infix' ELSE 'none' END AS cause FROM ends e)"""


def keys_with(name: str, body: str, t: int = 64, r: int = 8, drop_redundant: bool = True) -> str:
    return f"WITH keys AS ({integer_sql(name)}), {filter_ctes(t, r, drop_redundant)} {body}"


def verdicts_with(name: str, kind: str, length: int, body: str, t: int = 64, r: int = 8) -> str:
    return f"WITH {range_queries_sql(name, kind, length)}, {filter_ctes(t, r)}, {verdict_ctes(t, r)} {body}"


COUNTS = "count(*)::BIGINT AS n_queries, sum(empty::BIGINT)::BIGINT AS n_empty, sum((empty AND cause IN ('anchor', 'infix'))::BIGINT)::BIGINT AS false_positives, sum((NOT empty AND cause NOT IN ('anchor', 'infix'))::BIGINT)::BIGINT AS false_negatives"
