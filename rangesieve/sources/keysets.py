"""Key sets and query sets over the given tables, one expression each, which Spark and DuckDB compute alike.

Hashes are md5 prefixes and arithmetic is on integers, so that both engines agree to the last key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.lineage import written

MORTON = "(({x} & 1) | (({x} & 2) << 1) | (({x} & 4) << 2) | (({x} & 8) << 3) | (({x} & 16) << 4) | (({x} & 32) << 5) | (({x} & 64) << 6) | (({x} & 128) << 7) | (({x} & 256) << 8) | (({x} & 512) << 9) | (({x} & 1024) << 10) | (({x} & 2048) << 11) | (({x} & 4096) << 12) | (({x} & 8192) << 13) | (({x} & 16384) << 14) | (({x} & 32768) << 15))"
INTEGER_SETS = ("uniform", "normal", "skewed", "clustered", "timeline", "dense", "money")
STRING_SETS = ("words", "emails", "urls", "names", "str_smooth")
HOSTS, SEGMENTS = 2000, 400


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def h60(text: Column) -> Column:
    """The first 60 bits of the md5 of a text."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def h60_duck(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 15))::BIGINT)"


def skew(h: Column, n: Column | int) -> Column:
    """A place below n, small ones far more often: the cube of a 20-bit uniform number, scaled."""
    a = h % F.lit(1 << 20)
    return F.shiftright(F.shiftright(a * a * a, 40) * n, 20)


def skew_duck(h: str, n: str) -> str:
    a = f"({h} % 1048576)"
    return f"((({a} * {a} * {a} >> 40) * {n}) >> 20)"


def _cents(column: str) -> str:
    return f"CAST(floor({column} * 100 + 0.5) AS BIGINT)"


def _spread(x: str) -> str:
    return MORTON.format(x=x)


def _integer_sql(name: str, duck: bool) -> str:
    h = h60_duck if duck else (lambda t: f"CAST(conv(substr(md5({t}), 1, 15), 16, 10) AS BIGINT)")
    days = "CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT)" if duck else "CAST(datediff(CAST(o_orderdate AS DATE), DATE '1995-01-01') AS BIGINT)"
    micros = "epoch_us(ts)" if duck else "unix_micros(CAST(ts AS TIMESTAMP))"
    t = (lambda n: n) if duck else (lambda n: "{" + n + "}")
    return {
        "uniform": f"SELECT DISTINCT {h('concat(l_orderkey, chr(35), l_linenumber)')} AS key FROM {t('lineitem')}",
        "normal": f"SELECT DISTINCT CAST(floor((CAST(v AS DOUBLE) + 1) * 288230376151711744) AS BIGINT) AS key FROM (SELECT {'unnest' if duck else 'explode'}(embedding) AS v FROM {t('embeddings')}) e",
        "skewed": f"SELECT DISTINCT ({_cents('value')} << 20) + event_id AS key FROM {t('events')}",
        "clustered": f"SELECT DISTINCT ({_spread('d')} << 1) | {_spread('c')} AS key FROM (SELECT {days} & 65535 AS d, ({_cents('o_totalprice')} >> 10) & 65535 AS c FROM {t('orders')}) o",
        "timeline": f"SELECT DISTINCT {micros} AS key FROM {t('events')}",
        "dense": f"SELECT DISTINCT o_orderkey AS key FROM {t('orders')}",
        "money": f"SELECT DISTINCT {_cents('l_extendedprice')} AS key FROM {t('lineitem')}",
    }[name]


_TABLES = {"uniform": "lineitem", "normal": "embeddings", "skewed": "events", "clustered": "orders", "timeline": "events", "dense": "orders", "money": "lineitem"}


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct lower-case letter runs of the documents."""
    runs = F.regexp_extract_all(F.lower("text"), F.lit("\\p{L}+"), F.lit(0))
    return table(spark, sf_dir, "documents").select(F.explode(runs).alias("key")).distinct()


WORDS_DUCK = "SELECT DISTINCT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS key FROM documents"


def _short(w: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(place, host), (place, segment): words of 3 to 8 letters in hash order; HOSTS and SEGMENTS rows at most."""
    short = w.where(F.length("key").between(3, 8)).orderBy(h60(F.concat(F.lit("short"), "key")), "key").limit(HOSTS + SEGMENTS)
    placed = short.withColumn("place", F.row_number().over(Window.orderBy(h60(F.concat(F.lit("short"), "key")), "key")) - 1)
    return placed.where(F.col("place") < HOSTS).select(F.col("place").alias("hp"), F.col("key").alias("host")), placed.select((F.col("place") % SEGMENTS).alias("sp"), F.col("key").alias("segment"), "place").where(F.col("place") < SEGMENTS).drop("place")


_SHORT_DUCK = """words AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS key FROM documents),
placed AS (SELECT key, row_number() OVER (ORDER BY HS, key) - 1 AS place FROM words WHERE length(key) BETWEEN 3 AND 8),
hosts AS (SELECT place AS hp, key AS host FROM placed WHERE place < 2000),
segments AS (SELECT place AS sp, key AS segment FROM placed WHERE place < 400)""".replace("HS", h60_duck("'short' || key"))


def string_keys(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A string key set, distinct, as `key` STRING; str_smooth is BINARY."""
    if name == "words":
        return words(spark, sf_dir)
    if name == "names":
        t = lambda n: table(spark, sf_dir, n)
        return t("customer").select(F.col("c_name").alias("key")).union(t("conversations").select(F.concat_ws("/", "role", "conv_id", "turn"))).union(t("benchmark").select(F.substring("text", 1, 40))).distinct()
    if name == "str_smooth":
        smooth = integer_keys(spark, sf_dir, "normal")
        tail = F.repeat(F.md5(F.col("key").cast("string")), 8)
        size = 8 * (1 + h60(F.concat(F.lit("len"), F.col("key").cast("string"))) % 32)
        head = F.unhex(F.lpad(F.hex("key"), 16, "0"))
        return smooth.select(F.substring(F.concat(head, tail.cast("binary")), F.lit(1), size.cast("int")).alias("key"))
    # read by hosts, segments and the keys themselves
    w = written(words(spark, sf_dir))
    hosts, segments = (F.broadcast(x) for x in _short(w))  # HOSTS + SEGMENTS rows
    salted = lambda s: h60(F.concat(F.lit(s), "key"))
    tld = F.element_at(F.array(*map(F.lit, ("com", "net", "org", "edu"))), (skew(salted("tld"), F.lit(4)) + 1).cast("int"))
    if name == "emails":
        made = w.where(salted("email") % 4 == 0).withColumn("hp", skew(salted("dom"), F.lit(HOSTS)).cast("int")).join(hosts, "hp")
        address = F.regexp_extract_all("text", F.lit("[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\\.[A-Za-z0-9-]+)+"), F.lit(0))
        real = table(spark, sf_dir, "documents").where(F.contains("text", F.lit("@"))).select(F.explode(address).alias("a"))
        turned = F.concat(F.array_join(F.reverse(F.split(F.substring_index("a", "@", -1), "\\.")), "."), F.lit("@"), F.substring_index("a", "@", 1))
        return made.select(F.concat(tld, F.lit("."), "host", F.lit("@"), "key").alias("key")).union(real.select(turned)).distinct()
    if name == "urls":
        made = w.where(salted("url") % 3 == 0).withColumn("hp", skew(salted("dom"), F.lit(HOSTS)).cast("int")).join(hosts, "hp")
        depth = salted("depth") % 4
        for k in range(3):
            made = made.join(segments.select(F.col("sp").alias(f"sp{k}"), F.col("segment").alias(f"g{k}")), skew(salted(f"seg{k}"), F.lit(SEGMENTS)).cast("int") == F.col(f"sp{k}"))
        path = F.concat(*(F.when(depth > k, F.concat(F.lit("/"), F.col(f"g{k}"))).otherwise("") for k in range(3)))
        return made.select(F.concat(F.lit("http://www."), "host", F.lit(".example."), tld, path, F.lit("/"), "key").alias("key")).union(table(spark, sf_dir, "pages").select("url")).distinct()
    raise KeyError(name)


def string_sql(name: str) -> str:
    """DuckDB SQL of a string key set."""
    salted = lambda s: h60_duck(f"'{s}' || key")
    tld = f"(['com', 'net', 'org', 'edu'])[{skew_duck(salted('tld'), '4')} + 1]"
    if name == "words":
        return WORDS_DUCK
    if name == "names":
        return "SELECT DISTINCT key FROM (SELECT c_name AS key FROM customer UNION ALL SELECT concat_ws('/', role, conv_id, turn) FROM conversations UNION ALL SELECT substr(text, 1, 40) FROM benchmark)"
    if name == "emails":
        real = "SELECT unnest(regexp_extract_all(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\\.[A-Za-z0-9-]+)+')) AS a FROM documents"
        turned = "array_to_string(list_reverse(string_split(split_part(a, '@', 2), '.')), '.') || '@' || split_part(a, '@', 1)"
        return f"WITH {_SHORT_DUCK} SELECT DISTINCT key FROM (SELECT {tld} || '.' || host || '@' || key AS key FROM words JOIN hosts ON hp = {skew_duck(salted('dom'), '2000')} WHERE {salted('email')} % 4 = 0 UNION ALL SELECT {turned} FROM ({real}))"
    if name == "urls":
        joins = " ".join(f"JOIN (SELECT sp AS sp{k}, segment AS g{k} FROM segments) ON sp{k} = {skew_duck(salted(f'seg{k}'), '400')}" for k in range(3))
        path = " || ".join(f"CASE WHEN {salted('depth')} % 4 > {k} THEN '/' || g{k} ELSE '' END" for k in range(3))
        return f"WITH {_SHORT_DUCK} SELECT DISTINCT key FROM (SELECT 'http://www.' || host || '.example.' || {tld} || {path} || '/' || key AS key FROM words JOIN hosts ON hp = {skew_duck(salted('dom'), '2000')} {joins} WHERE {salted('url')} % 3 = 0 UNION ALL SELECT url FROM pages)"
    raise KeyError(name)


def integer_keys(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """An integer key set, distinct, as `key` BIGINT."""
    source = _TABLES[name]
    return spark.sql(_integer_sql(name, duck=False).replace("{" + source + "}", "{src}"), src=table(spark, sf_dir, source))


def integer_sql(name: str) -> str:
    return _integer_sql(name, duck=True)


def split_off(keys: DataFrame, salt: str = "held", one_in: int = 16) -> tuple[DataFrame, DataFrame]:
    """(kept, held out) keys, by hash."""
    out = h60(F.concat(F.lit(salt), F.col("key").cast("string"))) % one_in == 0
    return keys.where(~out), keys.where(out)


def range_queries(keys: DataFrame, kind: str, length: int, one_in: int = 16) -> tuple[DataFrame, DataFrame]:
    """(key set, queries(query_id, lo, hi, kind)) of one kind; emptiness is not enforced here.

    held_out: ranges at keys that are then left out; same_dist: near keys, by hash; uniform_ends: anywhere in the key span;
    point: held out, of length one; non_empty: around a key; mixed: half non-empty, half held out; adversarial: next to a stored key.
    """
    text = F.col("key").cast("string")
    kept, held = split_off(keys, "held", one_in)
    salted = lambda s: h60(F.concat(F.lit(s), text))
    if kind in ("held_out", "point"):
        n = 1 if kind == "point" else length
        return kept, held.select(F.col("key").alias("query_id"), F.col("key").alias("lo"), (F.col("key") + (n - 1)).alias("hi"), F.lit(kind).alias("kind"))
    sample = kept.where(salted(kind) % one_in == 0)
    if kind == "same_dist":
        lo = F.col("key") + 1 + salted("jitter") % (1 << 20)
    elif kind == "non_empty":
        lo = F.greatest(F.lit(0), F.col("key") - salted("back") % length)
    elif kind == "adversarial":
        lo = F.col("key") + 1
    elif kind == "uniform_ends":
        span = keys.agg(F.min("key").alias("a"), F.max("key").alias("b"))
        spread = sample.join(F.broadcast(span)).withColumn("lo", F.col("a") + (salted("u") % (1 << 20)) * F.floor((F.col("b") - F.col("a")) / (1 << 20)))
        return kept, spread.select(F.col("key").alias("query_id"), "lo", (F.col("lo") + (length - 1)).alias("hi"), F.lit(kind).alias("kind"))
    elif kind == "mixed":
        a, b = range_queries(keys, "non_empty", length, one_in)[1], range_queries(keys, "held_out", length, one_in)[1]
        return kept, a.union(b).withColumn("kind", F.lit(kind))
    else:
        raise KeyError(kind)
    return kept, sample.select(F.col("key").alias("query_id"), lo.alias("lo"), (lo + (length - 1)).alias("hi"), F.lit(kind).alias("kind"))


def range_queries_sql(name: str, kind: str, length: int, one_in: int = 16) -> str:
    """DuckDB CTEs `allkeys`, `keys` and `queries` for range_queries of an integer key set."""
    salted = lambda s: h60_duck(f"'{s}' || key::VARCHAR")
    head = f"allkeys AS ({integer_sql(name)}), keys AS (SELECT key FROM allkeys WHERE {salted('held')} % {one_in} <> 0)"
    n = 1 if kind == "point" else length
    held = f"SELECT key AS query_id, key AS lo, key + {n - 1} AS hi, '{kind}' AS kind FROM allkeys WHERE {salted('held')} % {one_in} = 0"
    los = {"same_dist": f"key + 1 + {salted('jitter')} % 1048576", "non_empty": f"greatest(0, key - {salted('back')} % {length})", "adversarial": "key + 1"}
    near = lambda k, label: f"SELECT query_id, lo, lo + {length - 1} AS hi, '{label}' AS kind FROM (SELECT key AS query_id, {los[k]} AS lo FROM keys WHERE {salted(k)} % {one_in} = 0)"
    if kind in ("held_out", "point"):
        body = held
    elif kind == "uniform_ends":
        body = f"SELECT key AS query_id, lo, lo + {length - 1} AS hi, '{kind}' AS kind FROM (SELECT key, a + ({salted('u')} % 1048576) * ((b - a) // 1048576) AS lo FROM keys, (SELECT min(key) AS a, max(key) AS b FROM allkeys) WHERE {salted(kind)} % {one_in} = 0)"
    elif kind == "mixed":
        body = near("non_empty", kind) + " UNION ALL " + held
    else:
        body = near(kind, kind)
    return f"{head}, queries AS ({body})"


def adjacent_pairs(keys: DataFrame, one_in: int = 16) -> tuple[DataFrame, DataFrame]:
    """(key set, queries): adjacent string keys are removed in pairs, each pair is the ends of an empty range.

    The neighbours come from a window inside ranges of the first byte pair, so that no task sees all keys.
    """
    part = F.substring("key", 1, 2)
    order = Window.partitionBy("_p").orderBy("key")
    pairs = keys.withColumn("_p", part).withColumn("hi", F.lead("key").over(order)).withColumn("_n", F.row_number().over(order) - 1)
    chosen = pairs.where((F.col("_n") % 2 == 0) & F.col("hi").isNotNull() & (h60(F.concat(F.lit("pair"), F.col("key").cast("string"))) % one_in == 0)).select(F.col("key").alias("lo"), "hi")
    gone = chosen.select(F.explode(F.array("lo", "hi")).alias("key"))
    kept = keys.join(gone, "key", "left_anti")
    return kept, chosen.select(F.monotonically_increasing_id().alias("query_id"), "lo", "hi", F.lit("adjacent_pairs").alias("kind"))


ADJACENT_DUCK = """pairs AS (
  SELECT key AS lo, lead(key) OVER (PARTITION BY substr(key, 1, 2) ORDER BY key) AS hi, row_number() OVER (PARTITION BY substr(key, 1, 2) ORDER BY key) - 1 AS n FROM allkeys
), chosen AS (
  SELECT lo, hi FROM pairs WHERE n % 2 = 0 AND hi IS NOT NULL AND HP % 16 = 0
), keys AS (
  SELECT key FROM allkeys WHERE key NOT IN (SELECT lo FROM chosen) AND key NOT IN (SELECT hi FROM chosen)
)""".replace("HP", h60_duck("'pair' || lo"))
