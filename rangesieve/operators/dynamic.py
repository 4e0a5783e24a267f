"""The dynamic base filter: blocks that stretch and split, remainders of any length, duplicates for lost bits, deletes and merges.

A stored infix is (value, bits): the leading `bits` bits of a full m-bit infix.  The missing ones are wildcards.  At rest a block is one
row: an occupieds bitmap, and for every slot a run end and a padded remainder, each run at or near its home slot, empty slots zero.  The
rows of a shard are one unit of work: updates of a shard are applied in order by one task, shards never touch each other, and the shard's
outer bounds are sentinels that are never deleted, so that a merge stays inside.
"""

from __future__ import annotations

import bisect
import hashlib
import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.geometry import ANCHOR_BITS, WIDTH, Geometry
from .anchors import prepare_keys, shard_bounds, shard_of
from .blocks import pack_bits, unpack_bits
from .shardarrays import ShardArrays

STATE = "shard int, version long, block int, pred long, succ long, extra int, n_slots int, stretches int, void long, copied long, moved long, n_inserted long, n_built long, edge boolean, occupieds binary, runends binary, slots binary"
_COLUMNS = [c.split()[0] for c in STATE.split(", ")]


def pad_remainder(value: int, bits: int, width: int) -> int:
    """A remainder of `bits` bits in a slot of `width`: the bits, a one, zeros."""
    return ((value << 1) | 1) << (width - bits - 1)


def unpad_remainder(slot: int, width: int) -> tuple[int, int]:
    """(value, bits) of a padded slot."""
    zeros = (slot & -slot).bit_length() - 1
    return slot >> (zeros + 1), width - zeros - 1


def duplicate_void(value: int, missing: int) -> list[int]:
    """All completions of an infix by `missing` quotient bits."""
    return [(value << missing) | i for i in range(1 << missing)]


@dataclass
class DynamicBlock:
    """Between two anchors; entries are sorted (value left-aligned to m bits, known bits)."""

    geo: Geometry
    r: int
    entries: list[tuple[int, int]] = field(default_factory=list)
    n_slots: int = 0
    stretches: int = 0
    #: Keys, at most, that entries without remainder bits stand for; such entries are shared.
    void: int = 0
    #: Entries that were made for missing quotient bits, beyond the first of each group.
    copied: int = 0

    def quotient_bits(self) -> int:
        return self.geo.m - self.r

    def add(self, value: int, bits: int) -> int:
        """Stores an infix whose known bits may fall short of a quotient; how many copies that took."""
        q = self.quotient_bits()
        if bits > q:
            bisect.insort(self.entries, (value, bits))
            return 1
        self.void += 1
        lo, hi = self.geo.low >> self.r, self.geo.high >> self.r
        known = value >> (self.geo.m - bits) if bits else 0
        n = 0
        for full in duplicate_void(known, q - bits):
            at = bisect.bisect_left(self.entries, entry := (full << self.r, q))
            if lo <= full <= hi and (at == len(self.entries) or self.entries[at] != entry):
                self.entries.insert(at, entry)
                n += 1
        self.copied += max(0, n - 1)
        return n

    def fill(self) -> None:
        """Overprovisions the slots so that the block is 5 % free."""
        self.n_slots = max(self.n_slots, math.ceil(len(self.entries) / 0.95) or 1)

    def insert(self, key: int, factor: float, at: float, expansion: str) -> None:
        self.add(self.geo.infix(key), self.geo.m)
        while len(self.entries) > at * self.n_slots:
            self.n_slots = self.n_slots * 2 or 1 if expansion == "double" else max(self.n_slots + 1, math.ceil(self.n_slots * factor))
            self.stretches += 1

    def compact(self, factor: float = 1.05) -> None:
        """The inverse of a stretch, while 10 % and more of the slots are free."""
        while self.n_slots > 1 and len(self.entries) <= 0.9 * self.n_slots / factor:
            self.n_slots = max(1, math.floor(self.n_slots / factor))

    def layout(self) -> list[int]:
        """Slot of each entry: runs at their home slots, pushed right by what is there, and back left at the end."""
        lo = self.geo.low >> self.r
        count = (self.geo.high >> self.r) - lo + 1
        slots, last = [], -1
        for value, _ in self.entries:
            last = max(last + 1, min((((value >> self.r) - lo) * self.n_slots) // count, self.n_slots - 1))
            slots.append(last)
        limit = self.n_slots
        for i in range(len(slots) - 1, -1, -1):
            limit = slots[i] = min(slots[i], limit - 1)
        return slots

    def packed(self) -> tuple[bytes, bytes, bytes]:
        """(occupieds, runends, slots): the entries where the layout puts them."""
        lo, q = self.geo.low >> self.r, self.quotient_bits()
        occupieds = np.zeros((self.geo.high >> self.r) - lo + 1, dtype=bool)
        runends, slots = np.zeros(self.n_slots, dtype=bool), np.zeros(self.n_slots, dtype=np.int64)
        places = self.layout()
        for i, ((value, bits), at) in enumerate(zip(self.entries, places, strict=True)):
            home = value >> self.r
            occupieds[home - lo] = True
            runends[at] = i + 1 == len(places) or self.entries[i + 1][0] >> self.r != home
            known = bits - q
            slots[at] = pad_remainder((value & ((1 << self.r) - 1)) >> (self.r - known), known, self.r + 1)
        return np.packbits(occupieds).tobytes(), np.packbits(runends).tobytes(), pack_bits(slots, self.r + 1)

    def unpack(self, occupieds: bytes, runends: bytes, slots: bytes) -> None:
        """The entries of packed(): the i-th run belongs to the i-th occupied quotient, and a slot without a delimiter is empty."""
        lo, q = self.geo.low >> self.r, self.quotient_bits()
        homes = np.flatnonzero(np.unpackbits(np.frombuffer(occupieds, np.uint8), count=(self.geo.high >> self.r) - lo + 1))
        ends = np.unpackbits(np.frombuffer(runends, np.uint8), count=self.n_slots) if self.n_slots else np.zeros(0, np.uint8)
        run, self.entries = 0, []
        for end, slot in zip(ends.tolist(), unpack_bits(slots, self.n_slots, self.r + 1).tolist(), strict=True):
            if slot:
                rest, known = unpad_remainder(slot, self.r + 1)
                self.entries.append((((int(homes[run]) + lo) << self.r) | (rest << (self.r - known)), q + known))
                run += end

    def delete(self, key: int, clean_copies: bool = False) -> bool:
        """Removes the longest stored infix that matches the key; clean_copies also drops duplicates that no key needs any more."""
        full = self.geo.infix(key)
        match = [(b, i) for i, (v, b) in enumerate(self.entries) if v >> (self.geo.m - b) == full >> (self.geo.m - b)]
        if not match:
            return False
        bits, i = max(match)
        if bits > self.quotient_bits():
            self.entries.pop(i)
            return True
        # a shared entry stays until no key can stand behind any of them
        self.void -= 1
        if clean_copies and self.void <= 0:
            self.entries = [e for e in self.entries if e[1] > self.quotient_bits()]
            self.copied = 0
        return True

    def positive(self, low: int, high: int) -> bool:
        """Whether an entry's interval meets [low, high]."""
        m = self.geo.m
        end = bisect.bisect_right(self.entries, (high, m + 1))
        return any(v | ((1 << (m - b)) - 1) >= low for v, b in reversed(self.entries[:end])) if end else False

    def bits(self) -> int:
        count = (self.geo.high >> self.r) - (self.geo.low >> self.r) + 1
        return count + self.n_slots * (1 + self.r + 1)


def carry_over(old: DynamicBlock, new: DynamicBlock, value: int, bits: int) -> tuple[int, int]:
    """An entry of an old block in a new block's geometry: its known key bits, less or more of the prefix, cut to m bits."""
    key, known = old.geo.rebuild(value)
    known -= old.geo.m - bits
    start = new.geo.shared
    if known <= start:
        return 0, 0
    infix = new.geo.infix(key)
    have = known - start
    have = 1 if have <= 1 + new.geo.redundant else have - new.geo.redundant
    have = min(have, new.geo.m)
    return infix >> (new.geo.m - have) << (new.geo.m - have), have


@dataclass
class ShardFilter:
    """All blocks between two sentinels."""

    t: int
    r: int
    width: int
    anchors: list[int]
    blocks: list[DynamicBlock]
    seed: int = 0
    promotion: str = "hash"
    factor: float = 1.05
    at: float = 0.95
    expansion: str = "stretch"
    n_inserted: int = 0
    n_built: int = 0
    moved: int = 0
    #: "per_doubling": blocks that are made anew get a remainder bit more for each doubling of the keys, which holds the rate.
    widening: str = "none"
    #: The sentinels that are keys themselves.
    edge: set[int] = field(default_factory=set)

    @property
    def m(self) -> int:
        return self.r + math.ceil(math.log2(self.t))

    @classmethod
    def build(cls, keys: list[int], low: int, high: int, t: int, r: int, width: int = WIDTH, **options) -> ShardFilter:
        """Sorted keys strictly between the sentinels; every t-th is an anchor."""
        keys = sorted(set(keys) - {low, high})
        anchors = [low, *keys[t - 1 :: t], high]
        out = cls(t, r, width, anchors, [], n_built=len(keys), **options)
        for a, b in zip(anchors, anchors[1:], strict=False):
            block = out._block(a, b)
            inner = keys[bisect.bisect_right(keys, a) : bisect.bisect_left(keys, b)]
            for k in inner:
                block.add(block.geo.infix(k), block.geo.m)
            block.fill()
            out.blocks.append(block)
        return out

    def _block(self, a: int, b: int, extra: int | None = None) -> DynamicBlock:
        if extra is None:
            extra = max(0, math.floor(math.log2((self.n_built + self.n_inserted) / max(1, self.n_built)))) if self.widening == "per_doubling" and self.n_inserted else 0
        return DynamicBlock(Geometry(a, b, self.width, self.m + extra), self.r + extra)

    def promotes(self, key: int) -> bool:
        """Whether a new key becomes an anchor: by hash with probability 1/t, or every t-th one, which an adversary can exploit."""
        if self.promotion == "counter":
            return self.n_inserted % self.t == 0
        return int(hashlib.md5(f"{self.seed}#{key}".encode()).hexdigest()[:15], 16) % self.t == 0

    def insert(self, key: int) -> None:
        i = bisect.bisect_right(self.anchors, key) - 1
        if self.anchors[i] == key:
            return
        self.n_inserted += 1
        if self.promotes(key):
            self.split(i, key)
        else:
            self.blocks[i].insert(key, self.factor, self.at, self.expansion)

    def split(self, i: int, key: int) -> None:
        """Block i becomes two at the new anchor; an entry that may belong to both goes to both."""
        old = self.blocks[i]
        left, right = self._block(old.geo.pred, key), self._block(key, old.geo.succ)
        for value, bits in old.entries:
            base, known = old.geo.rebuild(value)
            known -= old.geo.m - bits
            span = (1 << (self.width - known)) - 1 if known < self.width else 0
            base &= ~span
            for part in (left, right):
                lo, hi = max(base, part.geo.pred + 1), min(base | span, part.geo.succ - 1)
                if lo > hi:
                    continue
                # the entry narrowed to this side: the bits on which its possible keys agree
                agree = self.width - (lo ^ hi).bit_length()
                have = max(0, max(known, min(agree, known)) - part.geo.shared)
                if have == 0:
                    part.add(0, 0)
                else:
                    have = 1 if have <= 1 + part.geo.redundant else have - part.geo.redundant
                    have = min(have, part.geo.m)
                    part.add(part.geo.infix(lo) >> (part.geo.m - have) << (part.geo.m - have), have)
                self.moved += 1
        for part in (left, right):
            part.void += old.void
            part.fill()
        self.anchors.insert(i + 1, key)
        self.blocks[i : i + 1] = [left, right]

    def delete(self, key: int, clean_copies: bool = False) -> bool:
        i = bisect.bisect_right(self.anchors, key) - 1
        if self.anchors[i] == key and 0 < i < len(self.anchors) - 1:
            self.merge(i)
            return True
        return self.blocks[min(i, len(self.blocks) - 1)].delete(key, clean_copies)

    def merge(self, i: int) -> None:
        """Anchor i goes; its neighbours' entries get the bits that the longer prefixes had taken over, and m bits at most."""
        left, right = self.blocks[i - 1], self.blocks[i]
        whole = self._block(left.geo.pred, right.geo.succ)
        for part in (left, right):
            for value, bits in part.entries:
                carried, known = carry_over(part, whole, value, bits)
                if bits <= part.quotient_bits():
                    # several keys may stand behind it: bits that the prefix gives back would make it a single key's, which one delete removes
                    known = min(known, whole.quotient_bits())
                    carried = carried >> (whole.geo.m - known) << (whole.geo.m - known)
                whole.add(carried, known)
            whole.void += part.void
        whole.fill()
        del self.anchors[i]
        self.blocks[i - 1 : i + 1] = [whole]

    def positive(self, lo: int, hi: int) -> bool:
        i = bisect.bisect_right(self.anchors, hi) - 1
        if i < 0:
            return False
        # sentinels are no keys
        inside = [a for a in self.anchors[max(1, bisect.bisect_left(self.anchors, lo)) : i + 1] if a != self.anchors[-1]]
        if inside:
            return True
        if i >= len(self.blocks):
            i -= 1
            hi = self.anchors[-1] - 1
        lo = max(lo, self.anchors[i] + 1)
        hi = min(hi, self.anchors[i + 1] - 1)
        if lo > hi:
            return False
        b = self.blocks[i]
        return b.positive(b.geo.infix(lo), b.geo.infix(hi))

    def rows(self, shard: int, version: int) -> pd.DataFrame:
        """STATE rows, one for each block; edge: whether the sentinel at pred, or in the last row also the one at succ, is a key."""
        out = []
        for i, b in enumerate(self.blocks):
            out.append((shard, version, i, b.geo.pred, b.geo.succ, b.r - self.r, b.n_slots, b.stretches, b.void, b.copied, self.moved if not i else 0, self.n_inserted if not i else 0, self.n_built if not i else 0, b.geo.pred in self.edge, *b.packed()))
        # the upper sentinel is a row without slots
        out.append((shard, version, len(self.blocks), self.anchors[-1], self.anchors[-1], 0, 0, 0, 0, 0, 0, 0, 0, self.anchors[-1] in self.edge, b"", b"", b""))
        return pd.DataFrame(out, columns=_COLUMNS)

    @classmethod
    def from_rows(cls, rows: pd.DataFrame, t: int, r: int, width: int = WIDTH, **options) -> ShardFilter:
        rows = rows.sort_values("block")
        anchors = [int(a) for a in rows["pred"]]
        out = cls(t, r, width, anchors, [], n_inserted=int(rows["n_inserted"].sum()), n_built=int(rows["n_built"].sum()), moved=int(rows["moved"].sum()), **options)
        out.edge = {a for a, e in zip(anchors, rows["edge"], strict=True) if e and a in (anchors[0], anchors[-1])}
        for x in rows.iloc[:-1].itertuples(index=False):
            block = out._block(int(x.pred), int(x.succ), int(x.extra))
            block.n_slots, block.stretches, block.void, block.copied = int(x.n_slots), int(x.stretches), int(x.void), int(x.copied)
            block.unpack(x.occupieds, x.runends, x.slots)
            out.blocks.append(block)
        return out

    def stats(self) -> dict[str, float]:
        slots, used = sum(b.n_slots for b in self.blocks), sum(len(b.entries) for b in self.blocks)
        return {
            "blocks": len(self.blocks), "anchors": len(self.anchors), "entries": used, "slots": slots, "stretches": sum(b.stretches for b in self.blocks),
            "moved": self.moved, "copied": sum(b.copied for b in self.blocks), "inserted": self.n_inserted,
            "bits": sum(b.bits() for b in self.blocks) + (self.width + ANCHOR_BITS) * len(self.anchors),
        }


@dataclass
class DynamicFilter:
    """STATE rows, one for each block; an update rewrites only the shards that it touches.  options: those of ShardFilter."""

    state: DataFrame
    bounds: list
    t: int
    r: int
    options: dict = field(default_factory=dict)

    @classmethod
    def build(cls, df: DataFrame, key: str = "key", t: int = 1024, r: int = 8, shards: int = 8, bounds: list | None = None, **options) -> DynamicFilter:
        keys = prepare_keys(df, key)
        bounds = shard_bounds(keys, shards=shards) if bounds is None else bounds
        ends = [-1, *bounds, (1 << WIDTH) - 1]

        def one(pdf: pd.DataFrame) -> pd.DataFrame:
            s = int(pdf["shard"].iloc[0])
            shard = ShardFilter.build([int(k) for k in pdf["key"].dropna()], max(0, ends[s] - 1) if s else 0, ends[s + 1], t, r, seed=s, **options)
            return _with_first(shard, pdf).rows(s, 0)

        # every shard exists, also without keys
        every = keys.sparkSession.range(len(bounds) + 1).select(F.col("id").cast("int").alias("shard"), F.lit(None).cast("long").alias("key"))
        dealt = keys.select(shard_of(F.col("key"), bounds).alias("shard"), F.col("key").cast("long").alias("key")).union(every)
        return cls(dealt.groupBy("shard").applyInPandas(one, STATE), bounds, t, r, options)

    def _loader(self, form: type[ShardFilter] | type[ShardArrays] = ShardFilter):
        t, r, options = self.t, self.r, self.options

        def load(rows: pd.DataFrame) -> ShardFilter | ShardArrays:
            return form.from_rows(rows, t, r, width=WIDTH, seed=int(rows["shard"].iloc[0]), **options)

        return load

    def apply(self, ops: DataFrame, clean_copies: bool = False) -> DynamicFilter:
        """ops(op "insert" or "delete", key, seq): applied by seq inside each shard."""
        dealt = ops.select(shard_of(F.col("key"), self.bounds).alias("shard"), "op", F.col("key").cast("long").alias("key"), "seq")
        load = self._loader()

        def one(state: pd.DataFrame, todo: pd.DataFrame) -> pd.DataFrame:
            if not len(todo):
                return state
            shard = load(state)
            for op, key in todo.sort_values(["seq", "key"])[["op", "key"]].itertuples(index=False):
                _change(shard, op, int(key), clean_copies)
            return shard.rows(int(state["shard"].iloc[0]), int(state["version"].iloc[0]) + 1)

        return DynamicFilter(self.state.groupBy("shard").cogroup(dealt.groupBy("shard")).applyInPandas(one, STATE), self.bounds, self.t, self.r, self.options)

    def compact(self) -> DynamicFilter:
        """The inverse of stretches, where deletes have left slots free."""
        load = self._loader()

        def one(state: pd.DataFrame) -> pd.DataFrame:
            shard = load(state)
            for b in shard.blocks:
                b.compact(shard.factor)
            return shard.rows(int(state["shard"].iloc[0]), int(state["version"].iloc[0]) + 1)

        return DynamicFilter(self.state.groupBy("shard").applyInPandas(one, STATE), self.bounds, self.t, self.r, self.options)

    def insert(self, df: DataFrame, key: str = "key") -> DynamicFilter:
        """Inserts by key inside each shard; those of a shard are applied together."""
        dealt = df.select(shard_of(F.col(key), self.bounds).alias("shard"), F.col(key).cast("long").alias("key"))
        load, load_arrays = self._loader(), self._loader(ShardArrays)

        def one(state: pd.DataFrame, todo: pd.DataFrame) -> pd.DataFrame:
            if not len(todo):
                return state
            at = int(state["shard"].iloc[0]), int(state["version"].iloc[0]) + 1
            keys, ends = np.sort(todo["key"].to_numpy()), state["pred"]
            if keys.dtype == np.int64 and (keys[1:] != keys[:-1]).all() and ends.min() <= keys[0] and keys[-1] <= ends.max():
                arrays = load_arrays(state)
                arrays.insert(keys)
                return arrays.rows(*at, _COLUMNS)
            # keys that come twice
            shard = load(state)
            for x in keys:
                _change(shard, "insert", int(x), False)
            return shard.rows(*at)

        return DynamicFilter(self.state.groupBy("shard").cogroup(dealt.groupBy("shard")).applyInPandas(one, STATE), self.bounds, self.t, self.r, self.options)

    def delete(self, df: DataFrame, key: str = "key", clean_copies: bool = False, audit: DataFrame | None = None) -> DynamicFilter:
        """Only keys that were inserted may be deleted; an audit table of all keys makes sure."""
        keys = df.select(F.col(key).alias("key"))
        keys = keys if audit is None else keys.join(audit.select("key"), "key", "left_semi")
        return self.apply(keys.select(F.lit("delete").alias("op"), "key", F.col("key").alias("seq")), clean_copies)

    def probe(self, queries: DataFrame) -> DataFrame:
        """(query_id, positive)."""
        return self.judged(queries.select("query_id", "lo", "hi")).select("query_id", "positive")

    def judged(self, queries: DataFrame) -> DataFrame:
        """queries with `positive`: a query asks every shard that it meets, and a shard's own bound is a key of the shard above."""
        names = queries.columns
        met = queries.withColumns({"shard": shard_of(F.col("lo"), self.bounds), "_last": shard_of(F.col("hi"), self.bounds)})
        load, schema = self._loader(ShardArrays), T.StructType([*queries.schema.fields, T.StructField("positive", T.BooleanType())])

        def one(state: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
            found = load(state).positive(asked["lo"].to_numpy(np.int64), asked["hi"].to_numpy(np.int64)) if len(state) and len(asked) else np.zeros(len(asked), bool)
            return asked[names].assign(positive=found)

        def answered(parts: DataFrame) -> DataFrame:
            return self.state.groupBy("shard").cogroup(parts.groupBy("shard")).applyInPandas(one, schema)

        inside = answered(met.where(F.col("shard") == F.col("_last")).select(*names, "shard"))
        if not self.bounds:
            return inside
        # only a query that meets several shards has several answers
        across = met.where(F.col("shard") != F.col("_last")).select(*names, F.explode(F.sequence("shard", "_last")).alias("shard"))
        return inside.union(answered(across).groupBy(*names).agg(F.bool_or("positive").alias("positive")))

    def stats(self) -> DataFrame:
        """A row for each shard: blocks, anchors, entries, slots, stretches, entries moved by splits, copies for lost bits, inserts, bits."""
        load, names = self._loader(ShardArrays), ["shard", "version", "blocks", "anchors", "entries", "slots", "stretches", "moved", "copied", "inserted", "bits"]

        def one(state: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame([{"shard": int(state["shard"].iloc[0]), "version": int(state["version"].iloc[0]), **load(state).stats()}], columns=names)

        return self.state.groupBy("shard").applyInPandas(one, "shard int, " + ", ".join(f"{c} long" for c in names[1:]))

    def lengths(self) -> DataFrame:
        """(missing, n): stored infixes by how many of their m bits are gone."""
        load = self._loader()

        def one(state: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"missing": [block.geo.m - b for block in load(state).blocks for _, b in block.entries]}, dtype="int32")

        return self.state.groupBy("shard").applyInPandas(one, "missing int").groupBy("missing").agg(F.count("*").alias("n"))


def _with_first(shard: ShardFilter, pdf: pd.DataFrame) -> ShardFilter:
    """Notes whether the shard's own bound is a key, as sentinels themselves are none."""
    keys = set(pdf["key"].dropna().astype("int64"))
    shard.edge = {e for e in (shard.anchors[0], shard.anchors[-1]) if e in keys}
    return shard


def _change(shard: ShardFilter, op: str, key: int, clean_copies: bool) -> None:
    if key in (shard.anchors[0], shard.anchors[-1]):
        (shard.edge.add if op == "insert" else shard.edge.discard)(key)
    elif op == "insert":
        shard.insert(key)
    else:
        shard.delete(key, clean_copies)


def _ask(shard: ShardFilter, lo: int, hi: int) -> bool:
    return any(lo <= e <= hi for e in shard.edge) or shard.positive(lo, hi)
