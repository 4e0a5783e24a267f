"""Positions of regular-expression matches with SQL functions alone, in code points.

Spark has no function that gives the places of all matches.  But splitting a text at the matches gives the stretches between them, so
a running sum over stretch and match lengths gives every place.  Patterns must not match the empty string, and must not repeat groups
greedily, as Java recurses there: possessive repetition does the same without.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

_ITEM = "array<struct<kind:string,i:int,skip:int,found:string,before:string,after:string>>"


def pieces(kind: str, pattern: str, gate: Column, text: str = "text", context: int = 0) -> Column:
    """The matches of one pattern in order, each with the length of the stretch before it; null where `gate` is false.

    gate: a cheap condition that every text with a match fulfils.
    """
    between = F.split(F.col(text), pattern, -1)
    found = F.regexp_extract_all(F.col(text), F.lit(pattern), F.lit(0))
    zipped = F.arrays_zip(found.alias("m"), between.alias("s"), F.slice(between, 2, 1 << 30).alias("t"))
    near = lambda x: (F.right(x["s"], F.lit(context)), F.left(x["t"], F.lit(1))) if context else (F.lit(None).cast("string"),) * 2
    one = lambda x, i: F.struct(F.lit(kind).alias("kind"), i.alias("i"), F.length(x["s"]).alias("skip"), x["m"].alias("found"), near(x)[0].alias("before"), near(x)[1].alias("after"))
    return F.when(gate & F.col(text).rlike(pattern), F.filter(F.transform(zipped, one), lambda x: x["found"].isNotNull()).cast(_ITEM))


def all_pieces(parts: Iterable[Column]) -> Column:
    empty = F.array().cast(_ITEM)
    return F.concat(*(F.coalesce(p, empty) for p in parts))


def placed(texts: DataFrame, key: str, column: str) -> DataFrame:
    """(key, kind, found, before, after, start, end) of the pieces in `column`; one row of texts for each key."""
    rows = texts.select(key, F.explode(column).alias("p")).select(key, "p.*")
    order = Window.partitionBy(key, "kind").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    end = F.sum(F.col("skip") + F.length("found")).over(order)
    return rows.withColumn("end", end).withColumn("start", F.col("end") - F.length("found")).select(key, "kind", "found", "before", "after", "start", "end")


def joined_spans(spans: Column) -> Column:
    """kind:start:end of an array of structs with these fields, comma-joined in the array's order."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
