"""Functions for SQL users: bitmap ranks, packed probes, unpacked blocks, dyadic covers and codes; register_functions puts them all in a session."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..operators.blocks import Block, rank, select
from .entropy import Codebook, to_bytes


def _bits(raw: bytes) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8)).astype(bool)


@pandas_udf(T.IntegerType())
def rank_bits(bits: pd.Series, place: pd.Series) -> pd.Series:
    """Ones before a place of a bitmap, most significant bit first."""
    return pd.Series([None if b is None or pd.isna(p) else rank(_bits(b), int(p)) for b, p in zip(bits, place, strict=True)], dtype="Int32")


@pandas_udf(T.IntegerType())
def select_bits(bits: pd.Series, number: pd.Series) -> pd.Series:
    """Place of the number-th one, from 0; the length of the bitmap if there are fewer."""
    return pd.Series([None if b is None or pd.isna(i) else select(_bits(b), int(i)) for b, i in zip(bits, number, strict=True)], dtype="Int32")


@pandas_udf(T.BooleanType())
def range_maybe(r: pd.Series, q_base: pd.Series, q_count: pd.Series, n_keys: pd.Series, occupieds: pd.Series, runends: pd.Series, slots: pd.Series, low: pd.Series, high: pd.Series) -> pd.Series:
    """Whether a packed block may hold an infix from low to high."""
    rows = zip(r, q_base, q_count, n_keys, occupieds, runends, slots, low, high, strict=True)
    return pd.Series([Block.from_bytes(int(a), int(b), int(c), int(n), o, e, s).probe(int(x), int(y)) != "none" for a, b, c, n, o, e, s, x, y in rows])


@udtf(returnType=T.StructType([T.StructField("infix", T.LongType())]))
class UnpackBlock:
    """The infixes of a packed block, in order."""

    def eval(self, r: int, q_base: int, q_count: int, n_keys: int, occupieds: bytes, runends: bytes, slots: bytes) -> Iterator[tuple[int]]:
        for x in Block.from_bytes(r, q_base, q_count, n_keys, bytes(occupieds), bytes(runends), bytes(slots)).infixes():
            yield (int(x),)


def dyadic_nodes(lo: int, hi: int, depth: int) -> Iterator[tuple[int, int]]:
    """(level, prefix) of the fewest aligned intervals of up to 2**depth values that make up [lo, hi], from left to right."""
    while lo <= hi:
        level = min(depth, (lo & -lo).bit_length() - 1 if lo else depth)
        while lo + (1 << level) - 1 > hi:
            level -= 1
        yield level, lo >> level
        lo += 1 << level


@udtf(returnType=T.StructType([T.StructField("level", T.IntegerType()), T.StructField("prefix", T.LongType())]))
class DyadicCover:
    """The fewest aligned intervals that make up a range."""

    def eval(self, lo: int, hi: int, depth: int) -> Iterator[tuple[int, int]]:
        yield from dyadic_nodes(lo, hi, depth)


def encoder(book: Codebook):
    """A function of byte strings that gives their codes, zero-padded to bytes, in a codebook of bounded size."""

    @pandas_udf(T.BinaryType())
    def encode_key(key: pd.Series) -> pd.Series:
        return key.map(lambda x: None if x is None else to_bytes(book.encode(x.encode() if isinstance(x, str) else bytes(x))))

    return encode_key


def register_functions(spark: SparkSession, book: Codebook | None = None) -> None:
    """Names in SQL: rank_bits, select_bits, range_maybe, unpack_block, dyadic_cover, and encode_key with a codebook."""
    spark.udf.register("rank_bits", rank_bits)
    spark.udf.register("select_bits", select_bits)
    spark.udf.register("range_maybe", range_maybe)
    spark.udtf.register("unpack_block", UnpackBlock)
    spark.udtf.register("dyadic_cover", DyadicCover)
    if book is not None:
        spark.udf.register("encode_key", encoder(book))
