"""The static base filter, in two equal forms: rows of infixes that joins probe, and packed blocks that a kernel probes."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..plans.lineage import written
from .anchors import Ranked, block_bounds, pick_anchors, predecessors, prepare_keys, rank_keys
from .blocks import Block

PACKED = "block_id long, pred long, succ long, shared int, redundant int, q_base long, q_count int, n_keys int, occupieds binary, runends binary, slots binary"


@dataclass
class BaseFilter:
    """anchors(anchor_no, key, is_sentinel); blocks(block_id, pred, succ, shared, redundant); infixes(block_id, infix)."""

    anchors: DataFrame
    blocks: DataFrame
    infixes: DataFrame
    bounds: list
    t: int
    r: int
    drop_redundant: bool = True
    binary: bool = False

    @property
    def m(self) -> int:
        return self.r + math.ceil(math.log2(self.t))

    @classmethod
    def build(cls, df: DataFrame | Ranked, key: str = "key", t: int = 1024, eps: float | None = None, bpk: float | None = None, key_bits: int = 64, drop_redundant: bool = True, sorted_input: bool = False) -> BaseFilter:
        """Every t-th key is an anchor; eps, or the rate that bpk bits per key allow, sets the remainder length.  Keys that are ranked already are not sorted again."""
        keys = df.rows.select("key") if isinstance(df, Ranked) else prepare_keys(df, key, sorted_input)
        binary = dict(keys.dtypes)["key"] in ("binary", "string")
        if binary:
            keys = keys.select(F.col("key").cast("binary").alias("key"))
        eps = g.eps_for_bpk(16 if bpk is None else bpk, key_bits, t) if eps is None else eps
        r = g.remainder_len(eps)
        ranked = df if isinstance(df, Ranked) else rank_keys(keys)
        anchors = pick_anchors(ranked, t)
        # one row in t keys, used by routing, infixes and packing alike
        blocks = written(cls._geometry(block_bounds(anchors, ranked.bounds), binary, drop_redundant))
        inner = ranked.rows.where(F.col("rank") % t != 0).select(F.floor(F.col("rank") / t).cast("long").alias("block_id"), "key").join(blocks, "block_id").where("key < succ")
        out = cls(anchors, blocks, keys, ranked.bounds, t, r, drop_redundant, binary)
        out.keyed = inner.select("block_id", "key", "shared", "redundant", out._infix(F.col("key")).alias("infix"))
        out.infixes = out.keyed.select("block_id", "infix")
        return out

    @staticmethod
    def _geometry(blocks: DataFrame, binary: bool, drop_redundant: bool) -> DataFrame:
        if binary:
            return blocks.mapInArrow(lambda b: _binary_geometry(b, drop_redundant), "block_id long, pred binary, succ binary, shared int, redundant int")
        red = g.redundant_bits(F.col("pred"), F.col("succ")) if drop_redundant else F.lit(0)
        return blocks.withColumns({"shared": g.shared_bits(F.col("pred"), F.col("succ")), "redundant": red})

    def _infix(self, key):
        derive = g.derive_binary_infix if self.binary else g.derive_infix
        return derive(key, F.col("shared"), F.col("redundant"), self.m)

    def route(self, queries: DataFrame) -> DataFrame:
        """queries with cause "anchor" (an anchor lies inside), "outside" (beyond all anchors) or "block", and the block's columns."""
        q = queries.select(*(F.col(c).cast("binary").alias(c) if self.binary and c in ("lo", "hi") else F.col(c) for c in queries.columns))
        near = predecessors(q, "hi", self.blocks, "pred", ["block_id", "succ", "shared", "redundant"], self.bounds)
        near = near.withColumnsRenamed({"near_key": "pred", "near_block_id": "block_id", "near_succ": "succ", "near_shared": "shared", "near_redundant": "redundant"})
        cause = F.when(F.col("pred").isNull(), "outside").when(F.col("pred") >= F.col("lo"), "anchor").when((F.col("succ") >= F.col("lo")) & (F.col("succ") <= F.col("hi")), "anchor").when(F.col("lo") > F.col("succ"), "outside").otherwise("block")
        return near.withColumn("route", cause)

    def probe(self, queries: DataFrame) -> DataFrame:
        """(query_id, positive, cause) with relational joins: does the block hold an infix in [infix(lo), infix(hi)]?"""
        routed = self.route(queries)
        asked = routed.where("route = 'block'").select("query_id", F.col("block_id").alias("_b"), self._infix(F.col("lo")).alias("_l"), self._infix(F.col("hi")).alias("_h"))
        hit = self.infixes.where("block_id IS NOT NULL")
        found = asked.join(hit, (F.col("_b") == F.col("block_id")) & (F.col("infix") >= F.col("_l")) & (F.col("infix") <= F.col("_h")), "left_semi").select("query_id", F.lit(True).alias("_hit"))
        out = routed.select("query_id", "route").join(found, "query_id", "left")
        return out.select("query_id", (F.coalesce("_hit", F.lit(False)) | (F.col("route") == "anchor")).alias("positive"), F.when(F.col("route") == "block", F.when(F.col("_hit"), "infix").otherwise("none")).otherwise(F.col("route")).alias("cause"))

    def point(self, df: DataFrame, column: str) -> DataFrame:
        """The rows of df whose key may be in the set."""
        marked = df.withColumn("query_id", F.monotonically_increasing_id()).withColumn("lo", F.col(column)).withColumn("hi", F.col(column))
        asked = marked.select("query_id", "lo", "hi")
        return marked.join(self.probe(asked).where("positive"), "query_id", "left_semi").drop("query_id", "lo", "hi")

    def packed(self) -> DataFrame:
        """PACKED rows: one for each block."""
        schema = PACKED.replace("pred long, succ long", "pred binary, succ binary") if self.binary else PACKED
        lows = self.blocks.select("*", self._infix(F.col("pred")).alias("low"), self._infix(F.col("succ")).alias("high"))
        lists = self.infixes.groupBy("block_id").agg(F.sort_array(F.collect_list("infix")).alias("infixes"))  # at most t infixes
        r = self.r
        return lows.join(lists, "block_id", "left").select("block_id", "pred", "succ", "shared", "redundant", "low", "high", F.coalesce("infixes", F.array().cast("array<bigint>")).alias("infixes")).mapInArrow(lambda b: _pack(b, r), schema)

    def probe_packed(self, queries: DataFrame) -> DataFrame:
        """(query_id, positive, cause) from the packed blocks; equal to probe(), with the run that answered as cause."""
        routed = self.route(queries)
        asked = routed.where("route = 'block'").select("query_id", F.col("block_id").alias("_b"), self._infix(F.col("lo")).alias("_l"), self._infix(F.col("hi")).alias("_h"))
        r = self.r
        # queries of one block share its packed row
        joined = asked.join(self.packed().select("block_id", "q_base", "q_count", "n_keys", "occupieds", "runends", "slots"), F.col("_b") == F.col("block_id"))
        answered = joined.select("query_id", "_l", "_h", "q_base", "q_count", "n_keys", "occupieds", "runends", "slots").mapInArrow(lambda b: _probe(b, r), "query_id long, cause string")
        out = routed.where("route <> 'block'").select("query_id", "route").union(answered)
        return out.select("query_id", F.col("route").isin("anchor", "single", "middle", "left", "right").alias("positive"), F.when(F.col("route") == "outside", "outside").otherwise(F.col("route")).alias("cause"))

    def bits(self) -> DataFrame:
        """(component, bits): anchors with their metadata, occupieds, runends, slots."""
        span = F.shiftright(self._infix(F.col("succ")), self.r) - F.shiftright(self._infix(F.col("pred")), self.r) + 1
        # one row on either side
        p = self.blocks.agg(F.coalesce(F.sum(span), F.lit(0)).alias("occupieds")).join(F.broadcast(self.infixes.agg(F.count("*").alias("runends"))))
        size = F.octet_length("key") * 8 if self.binary else F.lit(64)
        a = self.anchors.agg(F.coalesce(F.sum(size + g.ANCHOR_BITS), F.lit(0)).alias("anchors"))
        return p.join(F.broadcast(a)).select(F.explode(F.array(*(F.struct(F.lit(n).alias("component"), v.cast("long").alias("bits")) for n, v in (("anchors", F.col("anchors")), ("occupieds", F.col("occupieds")), ("runends", F.col("runends")), ("slots", F.col("runends") * self.r))))).alias("e")).select("e.*")


def _binary_geometry(batches: Iterator[pa.RecordBatch], drop_redundant: bool) -> Iterator[pa.RecordBatch]:
    for b in batches:
        shared, redundant = [], []
        for p, s in zip(b.column("pred").to_pylist(), b.column("succ").to_pylist(), strict=True):
            width = 8 * max(len(p), len(s))
            geo = g.Geometry(g.bytes_to_int(p, width), g.bytes_to_int(s, width), width, 1)
            shared.append(geo.shared)
            redundant.append(geo.redundant if drop_redundant else 0)
        yield pa.RecordBatch.from_arrays([b.column("block_id"), b.column("pred"), b.column("succ"), pa.array(shared, pa.int32()), pa.array(redundant, pa.int32())], names=["block_id", "pred", "succ", "shared", "redundant"])


def _pack(batches: Iterator[pa.RecordBatch], r: int) -> Iterator[pa.RecordBatch]:
    for b in batches:
        blocks = [Block.pack(np.array(x, dtype=np.int64), low, high, r) for x, low, high in zip(b.column("infixes").to_pylist(), b.column("low").to_pylist(), b.column("high").to_pylist(), strict=True)]
        parts = [x.to_bytes() for x in blocks]
        yield pa.RecordBatch.from_arrays(
            [*(b.column(c) for c in ("block_id", "pred", "succ", "shared", "redundant")), pa.array([x.q_base for x in blocks], pa.int64()), pa.array([len(x.occupieds) for x in blocks], pa.int32()), pa.array([len(x.slots) for x in blocks], pa.int32()), *(pa.array([p[i] for p in parts], pa.binary()) for i in range(3))],
            names=["block_id", "pred", "succ", "shared", "redundant", "q_base", "q_count", "n_keys", "occupieds", "runends", "slots"],
        )


def _probe(batches: Iterator[pa.RecordBatch], r: int) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = zip(*(b.column(c).to_pylist() for c in ("_l", "_h", "q_base", "q_count", "n_keys", "occupieds", "runends", "slots")), strict=True)
        out = [Block.from_bytes(r, base, count, n, o, e, s).probe(low, high) for low, high, base, count, n, o, e, s in rows]
        yield pa.RecordBatch.from_arrays([b.column("query_id"), pa.array(out, pa.string())], names=["query_id", "cause"])
