"""The comparison filters, each as rows that Spark joins: build(keys), probe(queries), size in bits.

Keys come as a DataFrame, or as Ranked rows with neighbours (`anchors.with_neighbours`), which several filters share.  Rows that cost an
exchange are written once, since bits() and probe() both read them.

All are one-sided.  Hashes are md5 prefixes, so that SQL can replay them.  A probe returns (query_id, positive).  Rows that several keys
share carry the number of these keys, so that deleting one of them leaves the row to the others; bits() counts what is stored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.geometry import WIDTH, bit_length, shift_left, shift_right
from ..functions.md5 import h60_numbers
from ..operators.anchors import Ranked, predecessors, range_is_empty, rank_keys, shard_bounds, shard_of, with_neighbours
from ..plans.lineage import written
from ..sources.keysets import h60


class Infeasible(ValueError):
    """The budget is below what the filter needs."""


class NotSupported(NotImplementedError):
    """The filter has no such operation."""


def salted(*parts: Column | str) -> Column:
    return h60(F.concat_ws("#", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts)))


def int_div(a: Column, b: int | Column) -> Column:
    """Exact division of non-negative integers, rounded down; `/` alone would pass through DOUBLE."""
    return F.call_function("div", a.cast("long"), F.lit(b).cast("long") if isinstance(b, int) else b.cast("long"))


def wide_div(a: Column, b: Column) -> Column:
    """The same beyond 64 bits."""
    b = b.cast("decimal(20,0)")
    a = a.cast("decimal(32,0)")
    return ((a - a % b) / b).cast("long")


def keys_of(keys: DataFrame | Ranked) -> tuple[DataFrame, int]:
    """(keys, their number)."""
    return (keys.rows.select("key"), keys.n) if isinstance(keys, Ranked) else (keys, keys.count())


def _verdict(queries: DataFrame, hits: DataFrame) -> DataFrame:
    """positive for the queries whose id is in hits."""
    found = hits.select("query_id").distinct().withColumn("_hit", F.lit(True))
    return queries.select("query_id").join(found, "query_id", "left").select("query_id", F.coalesce("_hit", F.lit(False)).alias("positive"))


#: Prefixes that a probe looks up for one range; a range with more is answered positive, as a filter may.
CAP = 64


def counted(df: DataFrame) -> DataFrame:
    """The distinct rows of df with the number of copies."""
    return df.groupBy(*df.columns).agg(F.count("*").alias("copies"))


def changed(rows: DataFrame, df: DataFrame, sign: int) -> DataFrame:
    """Counted rows after the rows of df have come (sign 1) or gone (sign -1)."""
    columns = [c for c in rows.columns if c != "copies"]
    step = counted(df.select(*columns)).withColumn("copies", sign * F.col("copies"))
    return rows.select(*columns, "copies").unionByName(step).groupBy(*columns).agg(F.sum("copies").alias("copies")).where("copies > 0")


def set_bits(rows: DataFrame, universe: int) -> int:
    """Bits of a sorted list of the counted rows' places below `universe`: two and the spare low bits for each."""
    n = rows.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    return int(n * (2 + max(0, math.ceil(math.log2(max(1.0, universe / max(n, 1)))))))


@dataclass
class RowFilter:
    """Base of filters whose content is one table of rows."""

    rows: DataFrame
    n: int
    options: dict = field(default_factory=dict)

    def insert(self, df: DataFrame) -> RowFilter:
        raise NotSupported(type(self).__name__)

    def delete(self, df: DataFrame) -> RowFilter:
        raise NotSupported(type(self).__name__)


class ExactRange(RowFilter):
    """Ground truth: the keys themselves."""

    @classmethod
    def build(cls, keys: DataFrame, **_) -> ExactRange:
        return cls(keys, keys.count())

    def probe(self, queries: DataFrame) -> DataFrame:
        return range_is_empty(queries, self.rows).select("query_id", (~F.col("empty")).alias("positive"))

    def insert(self, df: DataFrame) -> ExactRange:
        return ExactRange(self.rows.union(df.select("key")).distinct(), self.n)

    def delete(self, df: DataFrame) -> ExactRange:
        return ExactRange(self.rows.join(df.select("key"), "key", "left_anti"), self.n)

    def bits(self) -> int:
        return self.n * 64


class NoFilter(RowFilter):
    """Always positive."""

    @classmethod
    def build(cls, keys: DataFrame, **_) -> NoFilter:
        return cls(keys.limit(0), 0)

    def probe(self, queries: DataFrame) -> DataFrame:
        return queries.select("query_id", F.lit(True).alias("positive"))

    def bits(self) -> int:
        return 0


class TruncatedTrie(RowFilter):
    """Shortest distinguishing prefixes, each with up to m more real bits, or m hashed bits that refine points only."""

    @classmethod
    def build(cls, keys: DataFrame | Ranked, m: int | None = 0, suffix: str = "real", bpk: float | None = None) -> TruncatedTrie:
        """With bpk, m is what the budget leaves beside the trie; if that is less than nothing, the filter is infeasible."""
        ranked = keys if isinstance(keys, Ranked) else with_neighbours(rank_keys(keys))
        n, near = ranked.n, ranked.rows.select("key", "p", "q")
        shared = lambda c: F.coalesce(WIDTH - bit_length(F.col("key").bitwiseXOR(F.col(c))), F.lit(-1))
        bare = F.greatest(shared("p"), shared("q")) + 1
        # a key's byte prefixes are new below the one that it shares with the key before
        fresh = F.greatest(F.shiftright(bare - 1, 3), F.lit(0)) - F.shiftright(shared("p"), 3)
        inner = near.agg(F.coalesce(F.sum(fresh), F.lit(0))).first()[0]
        if bpk is not None:
            least = 10 * (n + inner) / max(1, n)
            m = math.floor(bpk - least)
            if m < 0:
                raise Infeasible(f"{least:.1f} bits per key are the least")
        depth = F.least(bare + (m if suffix == "real" else 0), F.lit(WIDTH))
        kept = near.withColumn("depth", depth.cast("int")).withColumn("lo", shift_left(shift_right(F.col("key"), WIDTH - F.col("depth")), WIDTH - F.col("depth")))
        kept = kept.withColumn("hi", F.col("lo") + shift_left(F.lit(1), WIDTH - F.col("depth")) - 1)
        if suffix == "hashed":
            kept = kept.withColumn("tag", salted("suffix", F.col("key")) % (1 << m))
        return cls(kept.drop("key", "p", "q"), n, {"m": m, "suffix": suffix, "bounds": ranked.bounds, "inner": inner})

    def probe(self, queries: DataFrame) -> DataFrame:
        # kept intervals are disjoint: the last one that starts at or before hi decides
        payload = ["hi", "depth", *(["tag"] if self.options["suffix"] == "hashed" else [])]
        near = predecessors(queries, "hi", self.rows.withColumnRenamed("lo", "first"), "first", payload, self.options["bounds"])
        hit = F.col("near_hi") >= F.col("lo")
        if self.options["suffix"] == "hashed":
            hit = hit & ((F.col("lo") != F.col("hi")) | (F.col("near_tag") == salted("suffix", F.col("lo")) % (1 << self.options["m"])))
        return near.select("query_id", F.coalesce(hit, F.lit(False)).alias("positive"))

    def bits(self) -> int:
        """Ten for each leaf and each inner node of the byte trie, and the suffix bits."""
        return 10 * (self.n + self.options["inner"]) + self.options["m"] * self.n


def coarse_prefixes(queries: DataFrame, levels: int) -> DataFrame:
    """(query_id, lo, hi, prefix): the level-`levels` prefixes that a range meets, where these are few; finer levels are checked where they hit."""
    first, last = (shift_right(F.col(c), F.lit(levels)) for c in ("lo", "hi"))
    return queries.where(last - first < CAP).select("query_id", "lo", "hi", F.explode(F.sequence(first, last)).alias("prefix"))


def _word() -> Column:
    return F.shiftright("place", 6)


def _mask() -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.col("place").bitwiseAND(F.lit(63)).cast("int"))


#: Bits of bitmaps that a task may hold at once, 128 MB; larger ones stay rows that joins meet.
PACKED_BITS = 1 << 30
#: Words of 64 bits in a row of packed bitmaps; tasks that set bits, each with the whole bitmaps; ranges that a task walks side by side.
CHUNK, SETTERS, POOL = 1 << 13, 32, 1 << 14


class DyadicBloom(RowFilter):
    """A Bloom filter per prefix level; a hit must be confirmed by hits on all finer levels.

    Bitmaps of up to PACKED_BITS are rows of (chunk, bits), sent whole to the tasks, which walk each range's prefixes up to the first point
    whose prefixes are all set.  Larger ones are rows of (bitmap, word, bits), which all prefixes of a level meet in a join.
    """

    SHARED = False

    @classmethod
    def build(cls, keys: DataFrame | Ranked, bpk: float = 16, length: int = 128, hashes: int = 2) -> DyadicBloom:
        only, n = keys_of(keys)
        levels = max(0, math.ceil(math.log2(length)))
        # the finest level gets half the bits, each coarser one an equal share of the rest; all alike in one bitmap
        whole = max(64, int(n * bpk))
        fine = whole if cls.SHARED or not levels else whole // 2
        coarse = whole if cls.SHARED else max(64, (whole - fine) // max(1, levels))
        made = cls(only, n, {"levels": levels, "fine": fine, "coarse": coarse, "hashes": hashes, "whole": whole})
        made.packed = made._layout().words * 64 <= PACKED_BITS
        if made.packed:
            tasks, layout = min(SETTERS, only.sparkSession.sparkContext.defaultParallelism), made._layout()
            parts = only.where("key IS NOT NULL").coalesce(tasks).mapInArrow(lambda b: _set_bits(b, layout), "chunk long, bits binary")
            made.rows = written(parts.groupBy("chunk").applyInArrow(_join_bits, "chunk long, bits binary"))
            return made
        every, prefix = F.explode(F.sequence(F.lit(0), F.lit(levels))).alias("level"), shift_right(F.col("key"), F.col("level"))
        if isinstance(keys, Ranked):
            # the key before tells whether a prefix is new
            at = keys.rows.select("key", "p", every).where(F.col("p").isNull() | (shift_right(F.col("p"), F.col("level")) < prefix)).select("level", prefix.alias("prefix"))
        else:
            at = only.select("key", every).select("level", prefix.alias("prefix")).distinct()
        places = at.select(made._bitmap(F.col("level")).alias("bitmap"), F.explode(made._places(F.col("level"), F.col("prefix"))).alias("place"))
        made.rows = written(places.groupBy("bitmap", _word().alias("word")).agg(F.bit_or(_mask()).alias("bits")))
        return made

    def _bitmap(self, level: Column) -> Column:
        return F.lit(0) if self.SHARED else level

    def _layout(self) -> Layout:
        o = self.options
        return Layout(o["levels"], o["hashes"], o["fine"], o["coarse"], self.SHARED)

    def _places(self, level: Column, prefix: Column) -> Column:
        size = F.when(level == 0, self.options["fine"]).otherwise(self.options["coarse"])
        return F.array(*(salted(f"bit{i}", level, prefix) % size for i in range(self.options["hashes"])))

    def probe(self, queries: DataFrame) -> DataFrame:
        if self.packed:
            layout, spark = self._layout(), queries.sparkSession
            bits = np.zeros(layout.words, np.uint64)
            # at most PACKED_BITS
            for r in self.rows.toLocalIterator():
                part = np.frombuffer(r["bits"], np.uint64)
                bits[r["chunk"] * CHUNK : r["chunk"] * CHUNK + len(part)] = part
            held = spark.sparkContext.broadcast(bits)
            return queries.select("query_id", "lo", "hi").mapInArrow(lambda b: _walk_ranges(b, layout, held), T.StructType([queries.schema["query_id"], T.StructField("positive", T.BooleanType())]))
        levels, k = self.options["levels"], self.options["hashes"]
        wide = queries.where(shift_right(F.col("hi"), F.lit(levels)) - shift_right(F.col("lo"), F.lit(levels)) >= CAP).select("query_id")
        now = coarse_prefixes(queries, levels)
        for level in range(levels, -1, -1):
            asked = now.select("query_id", "lo", "hi", "prefix", self._bitmap(F.lit(level)).alias("bitmap"), F.explode(self._places(F.lit(level), F.col("prefix"))).alias("place"))
            held = self.rows.select(F.col("bitmap").alias("_b"), "word", "bits")
            hits = asked.join(held, (F.col("bitmap") == F.col("_b")) & (_word() == F.col("word")) & (F.col("bits").bitwiseAND(_mask()) != 0), "left_semi").groupBy("query_id", "lo", "hi", "prefix").agg(F.count("*").alias("c"))
            now = hits.where(F.col("c") == k).drop("c")
            if level:
                children = F.sequence(F.greatest(F.col("prefix") * 2, shift_right(F.col("lo"), F.lit(level - 1))), F.least(F.col("prefix") * 2 + 1, shift_right(F.col("hi"), F.lit(level - 1))))
                now = now.select("query_id", "lo", "hi", F.explode(children).alias("prefix"))
        return _verdict(queries, now.select("query_id").union(wide))

    def bits(self) -> int:
        o = self.options
        return o["whole"] if self.SHARED else o["fine"] + o["coarse"] * o["levels"]


class SharedDyadicBitmap(DyadicBloom):
    """The same levels, all in one bitmap."""

    SHARED = True


class PrefixHashBitmap(SharedDyadicBitmap):
    """One bitmap; a level's place keeps the low bits of the prefix inside a hashed word, so that neighbours are co-located."""

    def _layout(self) -> Layout:
        return replace(super()._layout(), near=True)

    def _places(self, level: Column, prefix: Column) -> Column:
        words = max(1, self.options["whole"] // 64)
        return F.array(*(salted(f"word{i}", level, shift_right(prefix, F.lit(6))) % words * 64 + prefix % 64 for i in range(self.options["hashes"])))


@dataclass(frozen=True)
class Layout:
    """Where the packed bitmaps of a dyadic filter keep the bits of a prefix: level 0 comes first, then each coarser one, in whole words."""

    levels: int
    hashes: int
    fine: int
    coarse: int
    shared: bool
    near: bool = False

    @property
    def words(self) -> int:
        return -(-self.fine // 64) + (0 if self.shared else self.levels * -(-self.coarse // 64))

    def place(self, i: int, level: np.ndarray, prefix: np.ndarray) -> np.ndarray:
        """The place of the i-th bit, as `_places` has it, from the start of all bitmaps."""
        if self.near:
            return h60_numbers(f"word{i}", level, prefix >> 6) % max(1, self.fine // 64) * 64 + (prefix & 63)
        at = h60_numbers(f"bit{i}", level, prefix) % np.where(level == 0, self.fine, self.coarse)
        return at if self.shared else at + np.where(level == 0, 0, -(-self.fine // 64) + (level - 1) * -(-self.coarse // 64)) * 64

    def holds(self, bits: np.ndarray, level: np.ndarray, prefix: np.ndarray) -> np.ndarray:
        """Whether all bits of each prefix are set."""
        left = np.arange(len(prefix))
        for i in range(self.hashes):
            at = self.place(i, level[left], prefix[left])
            left = left[bits[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1) != 0]
        out = np.zeros(len(prefix), bool)
        out[left] = True
        return out


def _set_bits(batches: Iterator[pa.RecordBatch], layout: Layout) -> Iterator[pa.RecordBatch]:
    bits = np.zeros(layout.words, np.uint64)
    for b in batches:
        keys = b.column(0).to_numpy()
        for level in range(layout.levels + 1):
            prefix = keys >> level
            # sorted keys have equal prefixes side by side
            prefix = prefix[np.concatenate([[True], prefix[1:] != prefix[:-1]])] if len(prefix) else prefix
            for i in range(layout.hashes):
                at = layout.place(i, np.full(len(prefix), level), prefix)
                np.bitwise_or.at(bits, at >> 6, np.uint64(1) << (at & 63).astype(np.uint64))
    for chunk in range(-(-layout.words // CHUNK)):
        part = bits[chunk * CHUNK : (chunk + 1) * CHUNK]
        if part.any():
            yield pa.RecordBatch.from_arrays([pa.array([chunk], pa.int64()), pa.array([part.tobytes()], pa.binary())], names=["chunk", "bits"])


def _join_bits(parts: pa.Table) -> pa.Table:
    """One row for all rows of a chunk, of which each task made at most one."""
    bits = np.bitwise_or.reduce([np.frombuffer(x, np.uint64) for x in parts.column("bits").to_pylist()])
    return pa.table({"chunk": parts.column("chunk").slice(0, 1), "bits": pa.array([bits.tobytes()], pa.binary())})


def walk(lo: np.ndarray, hi: np.ndarray, layout: Layout, holds: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """Which ranges have a point that `holds` on all its levels, or meet CAP coarsest prefixes.

    A walk in key order through the tree of prefixes: below a hit, past a miss, and no further than the first point found.
    """
    levels = layout.levels
    out = (lo <= hi) & ((hi >> levels) - (lo >> levels) >= CAP)
    waiting = np.flatnonzero(~out & (lo <= hi))
    at = prefix = level = np.zeros(0, np.int64)
    while len(at) or len(waiting):
        if len(waiting) and len(at) <= POOL // 2:
            more, waiting = waiting[: POOL - len(at)], waiting[POOL - len(at) :]
            at, prefix, level = np.concatenate([at, more]), np.concatenate([prefix, lo[more] >> levels]), np.concatenate([level, np.full(len(more), levels)])
        hit = holds(level, prefix)
        found = hit & (level == 0)
        out[at[found]] = True
        # past a miss comes the coarsest prefix that starts where the missed one ends
        past = prefix + 1
        up = np.minimum(np.bitwise_count((past & -past).view(np.uint64) - np.uint64(1)).astype(np.int64), levels - level)
        finer = np.maximum(level - 1, 0)
        prefix = np.where(hit, np.maximum(prefix * 2, lo[at] >> finer), past >> up)
        level = np.where(hit, finer, level + up)
        live = ~found & ((prefix << level) <= hi[at])
        at, prefix, level = at[live], prefix[live], level[live]
    return out


def _walk_ranges(batches: Iterator[pa.RecordBatch], layout: Layout, held: Broadcast) -> Iterator[pa.RecordBatch]:
    bits = held.value
    waiting, n = [], 0

    def answered() -> pa.RecordBatch:
        # a range without both ends is empty
        lo, hi = (np.concatenate([b.column(c).fill_null(none).to_numpy(zero_copy_only=False) for b in waiting]) for c, none in ((1, 2**63 - 1), (2, -(2**63))))
        positive = walk(lo, hi, layout, lambda level, prefix: layout.holds(bits, level, prefix))
        return pa.RecordBatch.from_arrays([pa.concat_arrays([b.column(0) for b in waiting]), pa.array(positive)], names=["query_id", "positive"])

    for b in batches:
        waiting, n = [*waiting, b], n + b.num_rows
        # the last ranges of a walk are few at a time
        if n >= 8 * POOL:
            yield answered()
            waiting, n = [], 0
    if n:
        yield answered()


class TunedTrieBloom(RowFilter):
    """Existence of coarse prefixes, and a Bloom filter of finer ones; both lengths tuned on sample queries."""

    @classmethod
    def build(cls, keys: DataFrame, bpk: float = 16, sample: DataFrame | None = None, depths: tuple[int, ...] = (10, 14), fines: tuple[int, ...] = (30, 40, 50), hashes: int = 2) -> TunedTrieBloom:
        n, best = keys.count(), None
        for d1 in depths:
            for d2 in fines:
                made = cls._make(keys, n, bpk, d1, d2, hashes)
                rate = made.probe(sample).agg(F.avg(F.col("positive").cast("double"))).first()[0] if sample is not None else 1.0
                if best is None or (rate or 0.0) < best[0]:
                    best = (rate or 0.0, made)
        return best[1]

    @classmethod
    def _make(cls, keys: DataFrame, n: int, bpk: float, d1: int, d2: int, hashes: int) -> TunedTrieBloom:
        top = keys.select(shift_right(F.col("key"), F.lit(WIDTH - d1)).alias("prefix")).distinct()
        size = max(64, int(n * bpk) - 20 * 2**d1 // 8)
        fine = keys.select(shift_right(F.col("key"), F.lit(WIDTH - d2)).alias("prefix")).distinct()
        places = fine.select(F.explode(F.array(*(salted(f"fine{i}", F.col("prefix")) % size for i in range(hashes)))).alias("place")).distinct()
        out = cls(places, n, {"d1": d1, "d2": d2, "size": size, "hashes": hashes})
        out.top = top
        return out

    def probe(self, queries: DataFrame, cap: int = 64) -> DataFrame:
        d1, d2, size, k = (self.options[x] for x in ("d1", "d2", "size", "hashes"))
        first, last = (shift_right(F.col(c), F.lit(WIDTH - d2)) for c in ("lo", "hi"))
        wide = queries.where(last - first >= cap)
        asked = queries.where(last - first < cap).select("query_id", F.explode(F.sequence(first, last)).alias("p"))
        asked = asked.join(self.top, shift_right(F.col("p"), F.lit(d2 - d1)) == F.col("prefix"), "left_semi")
        spread = asked.select("query_id", "p", F.explode(F.array(*(salted(f"fine{i}", F.col("p")) % size for i in range(k)))).alias("place"))
        hits = spread.join(self.rows, "place", "left_semi").groupBy("query_id", "p").agg(F.count("*").alias("c")).where(F.col("c") == k)
        # a range of more than `cap` fine prefixes is answered by the coarse ones
        coarse = range_is_empty(wide.select("query_id", *(shift_right(F.col(c), F.lit(WIDTH - d1)).alias(c) for c in ("lo", "hi"))), self.top.select(F.col("prefix").alias("key"))).where("not empty")
        return _verdict(queries, hits.select("query_id").union(coarse.select("query_id")))

    def bits(self) -> int:
        return self.options["size"] + 20 * 2 ** self.options["d1"] // 8


class SplineBitmap(RowFilter):
    """Keys on a monotone line-segment map to bit positions; a range is positive if a set bit lies between its ends' positions."""

    @classmethod
    def build(cls, keys: DataFrame | Ranked, bpk: float = 16, per_knot: int = 64, gaps: int = 0) -> SplineBitmap:
        eps = 2 ** -(bpk - 2.4)
        scale = max(1, round(1 / eps))
        ranked = keys if isinstance(keys, Ranked) else rank_keys(keys)
        n, bounds = ranked.n, ranked.bounds
        last = n - 1
        knots = ranked.rows.where((F.col("rank") % per_knot == 0) | (F.col("rank") == last)).select(F.col("key").alias("x"), "rank")
        order = Window.partitionBy("_s").orderBy("x")
        dealt = knots.withColumn("_s", shard_of(F.col("x"), bounds))
        firsts = dealt.groupBy("_s").agg(F.min(F.struct("x", "rank")).alias("f"))
        after = firsts.select("_s", F.lead("f").over(Window.orderBy("_s")).alias("_after"))
        segments = dealt.join(F.broadcast(after), "_s").select("x", "rank", F.coalesce(F.lead(F.struct("x", "rank")).over(order), F.col("_after")).alias("n"))
        # one row in per_knot keys
        segments = written(segments.select("x", "rank", F.coalesce("n.x", F.col("x") + 1).alias("x2"), F.coalesce("n.rank", F.col("rank")).alias("rank2")))
        out = cls(segments, n, {"scale": scale, "bounds": bounds, "bpk": bpk, "per_knot": per_knot})
        out.segments = segments
        out.options["last"] = last
        # a key's rank tells its segment
        near = segments.where(F.col("rank") % per_knot == 0).select(int_div(F.col("rank"), per_knot).alias("_no"), F.col("x").alias("near_key"), F.col("rank").alias("near_rank"), F.col("x2").alias("near_x2"), F.col("rank2").alias("near_rank2"))
        placed = ranked.rows.select("key", int_div(F.col("rank"), per_knot).alias("_no")).join(near, "_no")
        out.rows = written(counted(placed.select(out._position("key").alias("key"))))
        out.gaps = None
        if gaps:
            from ..plans.metrics import gaps as widest

            wide = keys.rows.where("q IS NOT NULL").select(F.col("key").alias("after"), (F.col("q") - F.col("key") - 1).alias("width")).where("width > 0") if isinstance(keys, Ranked) else widest(keys, bounds)
            out.gaps = wide.orderBy(F.desc("width"), "after").limit(gaps)
        return out

    def _places(self, keys: DataFrame) -> DataFrame:
        return self._place(keys.select(F.col("key").alias("query_id"), "key"), "key").select(F.col("place").alias("key"))

    def _place(self, df: DataFrame, at: str) -> DataFrame:
        """df with the position of `at`, by integer interpolation; below the first key -1."""
        near = predecessors(df, at, self.segments, "x", ["rank", "x2", "rank2"], self.options["bounds"])
        return near.withColumn("place", F.coalesce(self._position(at), F.lit(-1))).drop("near_key", "near_rank", "near_x2", "near_rank2")

    def _position(self, at: str) -> Column:
        s = self.options["scale"]
        whole = lambda c: F.col(c).cast("decimal(19,0)")
        inside = F.least(whole(at) - whole("near_key"), whole("near_x2") - whole("near_key"))
        step = wide_div(inside * (F.col("near_rank2") - F.col("near_rank")).cast("decimal(4,0)") * F.lit(s).cast("decimal(8,0)"), whole("near_x2") - whole("near_key"))
        # in whole numbers of 64 bits where all products fit: the ranks' share first, then the scale's
        width = F.col("near_x2") - F.col("near_key")
        part = F.least(F.col(at) - F.col("near_key"), width) * (F.col("near_rank2") - F.col("near_rank"))
        short = int_div(part, width) * s + int_div((part % width) * s, width)
        fits = (F.col("near_key") >= 0) & (F.col("near_x2") < 1 << 62) & (F.col(at) < 1 << 62) & (width < (1 << 62) // max(s, self.options["per_knot"]))
        return F.col("near_rank") * s + F.when(fits, short).otherwise(step)

    def probe(self, queries: DataFrame) -> DataFrame:
        both = self._place(self._place(queries.select("query_id", "lo", "hi"), "lo").withColumnRenamed("place", "_l"), "hi").withColumnRenamed("place", "_h")
        asked = both.select("query_id", F.col("_l").alias("lo"), F.col("_h").alias("hi"))
        hit = range_is_empty(asked, self.rows, self._cuts()).where("not empty").select("query_id")
        if self.gaps is not None:
            # the list of widest gaps has a fixed length
            inside = queries.join(F.broadcast(self.gaps), (F.col("lo") > F.col("after")) & (F.col("hi") <= F.col("after") + F.col("width"))).select("query_id")
            hit = hit.join(inside, "query_id", "left_anti")
        return _verdict(queries, hit)

    def _cuts(self) -> list:
        """Places in proportion to ranks: equal steps hold equally many keys of those that the map was fitted to."""
        whole, shards = (self.options["last"] + 1) * self.options["scale"], max(len(self.options["bounds"]) + 1, self.rows.sparkSession.sparkContext.defaultParallelism)
        return sorted({whole * i // shards for i in range(1, shards)})

    def insert(self, df: DataFrame) -> SplineBitmap:
        """New positions under the old map: the model isn't fitted again."""
        out = SplineBitmap(changed(self.rows, self._places(df), 1), self.n, self.options)
        out.segments, out.gaps = self.segments, None
        return out

    def delete(self, df: DataFrame) -> SplineBitmap:
        out = SplineBitmap(changed(self.rows, self._places(df), -1), self.n, self.options)
        out.segments, out.gaps = self.segments, self.gaps
        return out

    def bits(self) -> int:
        """The positions, and two numbers for each knot and each listed gap."""
        pairs = self.segments.count() + (self.gaps.count() if self.gaps is not None else 0)
        return set_bits(self.rows, (self.options["last"] + 1) * self.options["scale"]) + 128 * pairs


class PrunedSplineBitmap(SplineBitmap):
    """The same, and queries inside one of the widest empty gaps are negative; static."""

    @classmethod
    def build(cls, keys: DataFrame | Ranked, bpk: float = 16, per_knot: int = 64, gaps: int = 64) -> PrunedSplineBitmap:
        return super().build(keys, bpk, per_knot, gaps)

    def insert(self, df: DataFrame) -> RowFilter:
        raise NotSupported("static")

    def delete(self, df: DataFrame) -> RowFilter:
        raise NotSupported("static")


class LocalHashSet(RowFilter):
    """Keys hash to a ring of N R / eps codes such that neighbours stay neighbours; a range becomes at most two ranges of codes."""

    @classmethod
    def build(cls, keys: DataFrame | Ranked, bpk: float = 16, length: int = 1024) -> LocalHashSet:
        only, n = keys_of(keys)
        ring = max(2, int(n * 2 ** max(1, bpk - 2)))
        codes = written(counted(only.select(cls._code(F.col("key"), ring).alias("key"))))
        return cls(codes, n, {"ring": ring, "bpk": bpk})

    @staticmethod
    def _code(key: Column, ring: int) -> Column:
        return (salted("ring", int_div(key, ring)) % ring + key % ring) % ring

    def probe(self, queries: DataFrame) -> DataFrame:
        ring = self.options["ring"]
        long = queries.where(F.col("hi") - F.col("lo") + 1 >= ring).select("query_id")
        q = queries.where(F.col("hi") - F.col("lo") + 1 < ring)
        a, b = int_div(F.col("lo"), ring), int_div(F.col("hi"), ring)
        # a range that crosses a multiple of the ring is two pieces, and a piece that wraps around is two again
        pieces = q.select("query_id", F.explode(F.when(a == b, F.array(F.struct(F.col("lo").alias("x"), F.col("hi").alias("y")))).otherwise(F.array(F.struct(F.col("lo").alias("x"), (b * ring - 1).alias("y")), F.struct((b * ring).alias("x"), F.col("hi").alias("y"))))).alias("p"))
        coded = pieces.select("query_id", self._code(F.col("p.x"), ring).alias("x"), (F.col("p.y") - F.col("p.x")).alias("w"))
        spans = coded.select("query_id", F.explode(F.when(F.col("x") + F.col("w") < ring, F.array(F.struct(F.col("x").alias("lo"), (F.col("x") + F.col("w")).alias("hi")))).otherwise(F.array(F.struct(F.col("x").alias("lo"), F.lit(ring - 1).cast("long").alias("hi")), F.struct(F.lit(0).cast("long").alias("lo"), (F.col("x") + F.col("w") - ring).alias("hi"))))).alias("s")).select("query_id", "s.*")
        hit = range_is_empty(spans, self.rows, shard_bounds(self.rows)).where("not empty").select("query_id")
        return _verdict(queries, hit.union(long))

    def bits(self) -> int:
        return set_bits(self.rows.withColumn("copies", F.lit(1)), self.options["ring"])


class PrefixSuffixTable(RowFilter):
    """Fingerprints of key prefixes with the log2(R) suffix bits beside; the end prefixes of a range compare suffixes."""

    EXTRA = 0

    @classmethod
    def build(cls, keys: DataFrame | Ranked, bpk: float = 16, length: int = 128, load: float = 0.95) -> PrefixSuffixTable:
        only, n = keys_of(keys)
        s = max(0, math.ceil(math.log2(length)))
        width = math.floor(bpk * load - 3.125 - cls.EXTRA) - s
        # fingerprints address a table of n places, so their length counts on top of log2 n
        a = max(1, math.ceil(math.log2(max(2, n))) + max(0, width))
        out = cls(only, n, {"s": s, "a": min(a, 59), "width": max(0, width), "load": load})
        out.rows = written(counted(out._rows(only)))
        return out

    def _rows(self, keys: DataFrame) -> DataFrame:
        s = self.options["s"]
        return keys.select(self._finger(shift_right(F.col("key"), F.lit(s))).alias("f"), F.col("key").bitwiseAND(F.lit((1 << s) - 1)).alias("suffix"))

    def _finger(self, prefix: Column) -> Column:
        return salted("prefix", prefix) % (1 << self.options["a"])

    def probe(self, queries: DataFrame, cap: int = 16) -> DataFrame:
        s = self.options["s"]
        p, q = shift_right(F.col("lo"), F.lit(s)), shift_right(F.col("hi"), F.lit(s))
        long = queries.where(q - p >= cap).select("query_id")
        asked = queries.where(q - p < cap).select("query_id", "lo", "hi", F.explode(F.sequence(p, q)).alias("x"))
        low = F.when(F.col("x") == shift_right(F.col("lo"), F.lit(s)), F.col("lo").bitwiseAND(F.lit((1 << s) - 1))).otherwise(0)
        high = F.when(F.col("x") == shift_right(F.col("hi"), F.lit(s)), F.col("hi").bitwiseAND(F.lit((1 << s) - 1))).otherwise((1 << s) - 1)
        ends = asked.select("query_id", self._finger(F.col("x")).alias("_f"), low.alias("_l"), high.alias("_h"))
        hit = ends.join(self.rows, (F.col("_f") == F.col("f")) & F.col("suffix").between(F.col("_l"), F.col("_h")), "left_semi").select("query_id")
        return _verdict(queries, hit.union(long))

    def insert(self, df: DataFrame) -> PrefixSuffixTable:
        return type(self)(changed(self.rows, self._rows(df), 1), self.n, self.options)

    def delete(self, df: DataFrame) -> PrefixSuffixTable:
        return type(self)(changed(self.rows, self._rows(df), -1), self.n, self.options)

    def doubled(self, keys: DataFrame) -> PrefixSuffixTable:
        """A table of twice the places for the same keys: fingerprints address one bit more, the rate per place stays."""
        out = type(self)(keys, 2 * self.n, self.options | {"a": min(self.options["a"] + 1, 59)})
        out.rows = counted(out._rows(keys))
        return out

    def bits(self) -> int:
        """Each key's remainder of the fingerprint, its suffix and the table's marks, at the table's load."""
        o = self.options
        n = self.rows.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
        return int(n * (o["width"] + o["s"] + 3.125 + self.EXTRA) / o["load"])


class PrefixSuffixTableExtraBit(PrefixSuffixTable):
    """The same with one more bit per key."""

    EXTRA = 1


class PointBloom(RowFilter):
    """A Bloom filter of whole keys: points only, every longer range is positive."""

    @classmethod
    def build(cls, keys: DataFrame, bpk: float = 16) -> PointBloom:
        n = keys.count()
        size, k = max(64, int(n * bpk)), max(1, round(bpk * math.log(2)))
        rows = keys.select(F.explode(F.array(*(salted(f"point{i}", F.col("key")) % size for i in range(k)))).alias("place")).distinct()
        return cls(rows, n, {"size": size, "k": k})

    def probe(self, queries: DataFrame) -> DataFrame:
        size, k = self.options["size"], self.options["k"]
        asked = queries.where("lo = hi").select("query_id", F.explode(F.array_distinct(F.array(*(salted(f"point{i}", F.col("lo")) % size for i in range(k))))).alias("place"))
        missing = asked.join(self.rows, "place", "left_anti").select("query_id")
        return _verdict(queries, queries.select("query_id").join(missing, "query_id", "left_anti"))

    def bits(self) -> int:
        return self.options["size"]


class PointCuckoo(PointBloom):
    """Fingerprints in one of two buckets of four: a point matches a fingerprint in either of its buckets; longer ranges are positive."""

    @classmethod
    def build(cls, keys: DataFrame, bpk: float = 16) -> PointCuckoo:
        n = keys.count()
        buckets, f = max(1, math.ceil(n / (4 * 0.95))), max(2, math.floor(bpk * 0.95))
        out = cls(keys, n, {"buckets": buckets, "f": f})
        out.rows = counted(keys.select(salted("bucket", F.col("key")).alias("h"), out._finger(F.col("key")).alias("f")).select((F.col("h") % buckets).alias("b"), "f"))
        return out

    def _finger(self, key: Column) -> Column:
        return salted("finger", key) % (1 << self.options["f"])

    def probe(self, queries: DataFrame) -> DataFrame:
        buckets = self.options["buckets"]
        points = queries.where("lo = hi")
        first, finger = salted("bucket", F.col("lo")) % buckets, self._finger(F.col("lo"))
        # a stored key may have moved to the bucket that its fingerprint pairs with its first one
        asked = points.select("query_id", finger.alias("f"), F.explode(F.array(first, F.pmod(salted("pair", finger) % buckets - first, F.lit(buckets)))).alias("b"))
        hit = asked.join(self.rows, ["b", "f"], "left_semi").select("query_id")
        return _verdict(queries, hit.union(queries.where("lo <> hi").select("query_id")))

    def bits(self) -> int:
        return self.options["buckets"] * 4 * self.options["f"]


@dataclass
class HybridFilter:
    """A robust filter for ranges up to R and the base filter for longer ones; or both must agree."""

    short: PrefixSuffixTable
    base: object
    length: int
    intersect: bool = False

    @classmethod
    def build(cls, keys: DataFrame, length: int = 128, eps: float = 0.01, t: int = 1024, intersect: bool = False) -> HybridFilter:
        from ..operators.base import BaseFilter

        return cls(PrefixSuffixTable.build(keys, (3.125 + math.log2(length / eps)) / 0.95, length), BaseFilter.build(keys, t=t, eps=eps), length, intersect)

    def probe(self, queries: DataFrame) -> DataFrame:
        size = F.col("hi") - F.col("lo") + 1
        near, far = queries.where(size <= self.length), queries.where(size > self.length)
        a, b = self.short.probe(near), self.base.probe(far).select("query_id", "positive")
        if self.intersect:
            other = self.base.probe(near).select("query_id", F.col("positive").alias("_p"))
            a = a.join(other, "query_id").select("query_id", (F.col("positive") & F.col("_p")).alias("positive"))
        return a.union(b)

    def bits(self) -> int:
        return self.short.bits() + self.base.bits().agg(F.sum("bits")).first()[0]


CLASSES = {
    "base_truncated_trie": TruncatedTrie, "base_dyadic_bloom": DyadicBloom, "base_shared_bitmap": SharedDyadicBitmap, "base_prefix_hash_bitmap": PrefixHashBitmap,
    "base_spline_bitmap": SplineBitmap, "base_pruned_spline": PrunedSplineBitmap, "base_local_hash": LocalHashSet, "base_prefix_suffix": PrefixSuffixTable,
    "base_prefix_suffix_extra": PrefixSuffixTableExtraBit, "base_point_bloom": PointBloom, "base_point_cuckoo": PointCuckoo,
}
