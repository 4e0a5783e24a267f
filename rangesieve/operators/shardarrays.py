"""All blocks of a shard of the dynamic filter as arrays: loading, packing, probes and sorted inserts without a step in Python for each key.

Entries and rows are those that `ShardFilter` makes key by key.  Keys come in ascending order, so a split leaves a left block that no later
key meets; the blocks that go on are split together, in as many rounds as one block has new anchors.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable

import numpy as np
import pandas as pd

from ..functions.geometry import ANCHOR_BITS


def mask(bits: np.ndarray) -> np.ndarray:
    return (np.int64(1) << bits) - 1


def bit_length(x: np.ndarray) -> np.ndarray:
    """Of integers from 0 to 2^62; a double holds either half of one."""
    high = x >> 31
    return np.where(high > 0, 31 + np.frexp(high.astype(np.float64))[1], np.frexp((x & 0x7FFFFFFF).astype(np.float64))[1]).astype(np.int64)


def starts_of(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


class Geometries:
    """The geometry of each block; `at` picks a block for each key."""

    def __init__(self, pred: np.ndarray, succ: np.ndarray, m: np.ndarray, width: int):
        self.pred, self.succ, self.m, self.width = pred, succ, m, width
        self.first = bit_length(pred ^ succ) - 1
        ones = mask(self.first)
        self.left = bit_length(~(pred & ~succ) & ones)
        self.redundant = self.first - self.left
        self.shared = width - self.first - 1

    def infix(self, key: np.ndarray, at: np.ndarray | slice = slice(None)) -> np.ndarray:
        first, left, m = self.first[at], self.left[at], self.m[at]
        by, rest = left - m + 1, key & mask(left)
        rest = np.where(by >= 0, rest >> np.maximum(by, 0), rest << np.maximum(-by, 0))
        return ((key >> first) & 1) << (m - 1) | rest

    def rebuild(self, infix: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        first, left, m = self.first[at], self.left[at], self.m[at]
        bit, known = infix >> (m - 1), np.minimum(m - 1, left)
        low = (infix & mask(m - 1)) >> (m - 1 - known)
        run = np.where(bit == 0, mask(self.redundant[at]) << left, 0)
        return self.pred[at] >> (first + 1) << (first + 1) | bit << first | run | low << (left - known), self.width - left + known


class Blocks:
    """Columns of blocks, and their entries (block, value, bits) in order."""

    FIELDS = ("pred", "succ", "extra", "n_slots", "stretches", "void", "copied")

    def __init__(self, columns: dict[str, np.ndarray], block: np.ndarray, value: np.ndarray, bits: np.ndarray):
        self.columns, self.block, self.value, self.bits = columns, block, value, bits

    def __getattr__(self, name: str) -> np.ndarray:
        if name in Blocks.FIELDS:
            return self.columns[name]
        raise AttributeError(name)

    def __len__(self) -> int:
        return len(self.columns["pred"])

    def sizes(self) -> np.ndarray:
        return np.bincount(self.block, minlength=len(self))

    def order(self) -> Blocks:
        by = np.lexsort((self.bits, self.value, self.block))
        return Blocks(self.columns, self.block[by], self.value[by], self.bits[by])

    def take(self, chosen: np.ndarray) -> Blocks:
        """The blocks that a mask chooses."""
        held, number = chosen[self.block], np.cumsum(chosen) - 1
        return Blocks({c: x[chosen] for c, x in self.columns.items()}, number[self.block[held]], self.value[held], self.bits[held])

    @staticmethod
    def concat(parts: list[Blocks]) -> Blocks:
        """Blocks in the order of their keys."""
        offset = starts_of(np.array([len(p) for p in parts]))
        columns = {c: np.concatenate([p.columns[c] for p in parts]) for c in Blocks.FIELDS}
        by = np.argsort(columns["pred"], kind="stable")
        place = np.empty(len(by), np.int64)
        place[by] = np.arange(len(by))
        block = place[np.concatenate([p.block + o for p, o in zip(parts, offset, strict=True)])]
        return Blocks({c: x[by] for c, x in columns.items()}, block, np.concatenate([p.value for p in parts]), np.concatenate([p.bits for p in parts])).order()


def _bits_of(raw: Iterable[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All bits, and where those of each row begin."""
    raw = list(raw)
    return np.unpackbits(np.frombuffer(b"".join(raw), np.uint8)), 8 * starts_of(np.fromiter(map(len, raw), np.int64, len(raw)))


def _rows_of(flat: np.ndarray, sizes: np.ndarray) -> list[bytes]:
    """The bytes of each row of a flat array of bits whose rows begin at whole bytes."""
    raw, ends = np.packbits(flat).tobytes(), np.cumsum(sizes).tolist()
    return [raw[a:b] for a, b in zip([0, *ends], ends, strict=False)]


class ShardArrays:
    def __init__(self, blocks: Blocks, t: int, r: int, width: int, seed: int = 0, promotion: str = "hash", factor: float = 1.05, at: float = 0.95, expansion: str = "stretch", widening: str = "none"):
        self.blocks, self.t, self.r, self.width, self.seed = blocks, t, r, width, seed
        self.promotion, self.factor, self.at, self.expansion, self.widening = promotion, factor, at, expansion, widening
        self.q = math.ceil(math.log2(t))
        self.n_inserted = self.n_built = self.moved = 0
        self.edge: set[int] = set()
        self._searched: tuple[Geometries, np.ndarray, np.ndarray, int] | None = None

    @classmethod
    def from_rows(cls, rows: pd.DataFrame, t: int, r: int, width: int, **options) -> ShardArrays:
        rows = rows.sort_values("block")
        anchors, edge = rows["pred"].to_numpy(np.int64), rows["edge"].to_numpy(bool)
        inner = rows.iloc[:-1]
        out = cls(Blocks({c: inner[c].to_numpy(np.int64) for c in Blocks.FIELDS}, *np.zeros((3, 0), np.int64)), t, r, width, **options)
        out.n_inserted, out.n_built, out.moved = (int(rows[c].sum()) for c in ("n_inserted", "n_built", "moved"))
        out.edge = {int(a) for a in anchors[edge] if a in (anchors[0], anchors[-1])}
        out._unpack(inner)
        return out

    def geometries(self, blocks: Blocks) -> Geometries:
        return Geometries(blocks.pred, blocks.succ, self.q + self.r + blocks.extra, self.width)

    def _unpack(self, rows: pd.DataFrame) -> None:
        blocks, g = self.blocks, self.geometries(self.blocks)
        r = self.r + blocks.extra
        occupied, at_home = _bits_of(rows["occupieds"])
        ends, at_end = _bits_of(rows["runends"])
        slots, at_slot = _bits_of(rows["slots"])
        # the home of the i-th run of a block, after those of the blocks before
        homes = np.flatnonzero(occupied)
        first_home = np.searchsorted(homes, at_home)
        block = np.repeat(np.arange(len(blocks)), blocks.n_slots)
        slot = np.arange(len(block)) - np.repeat(starts_of(blocks.n_slots), blocks.n_slots)
        width = (r + 1)[block]
        from_bit, held = at_slot[block] + slot * width, np.zeros(len(block), np.int64)
        for j in range(int(width.max(initial=0))):
            # a shorter slot stays as it is
            held = np.where(j < width, held << 1 | slots[np.minimum(from_bit + j, max(0, len(slots) - 1))], held)
        end = ends[at_end[block] + slot].astype(np.int64)
        used = held != 0
        block, held, end = block[used], held[used], end[used]
        before = np.cumsum(end) - end
        size = np.bincount(block, minlength=len(blocks))
        begins = starts_of(size)
        run = before - np.repeat(before[begins[size > 0]], size[size > 0])
        home = homes[first_home[block] + run] - at_home[block] + (g.infix(g.pred) >> r)[block]
        zeros = bit_length(held & -held) - 1
        blocks.block, blocks.value, blocks.bits = block, home << r[block] | held >> (zeros + 1) << zeros, self.q + r[block] - zeros

    def rows(self, shard: int, version: int, columns: list[str]) -> pd.DataFrame:
        """STATE rows, one for each block, and the upper sentinel."""
        blocks, g = self.blocks, self.geometries(self.blocks)
        n, r = len(blocks), self.r + blocks.extra
        block, rb = blocks.block, r[blocks.block]
        low, size = g.infix(g.pred) >> r, blocks.sizes()
        count = (g.infix(g.succ) >> r) - low + 1
        home = (blocks.value >> rb) - low[block]
        # runs at their home slots, pushed right by what is there, and back left at the end; a block's numbers are apart from those of others
        number, slots = np.arange(len(block)), blocks.n_slots[block]
        apart = block * (int(blocks.n_slots.max(initial=0)) + len(block) + 1) * 2
        place = np.minimum(home * slots // count[block], slots - 1)
        place = np.maximum.accumulate(place - number + apart) + number - apart
        place = np.minimum(place, slots - (starts_of(size) + size)[block] + number)
        place = np.minimum.accumulate((place - number + apart)[::-1])[::-1] + number - apart
        homes, ends, slot_bytes = -(-count // 8), -(-blocks.n_slots // 8), -(-(blocks.n_slots * (r + 1)) // 8)
        occupied, end, slot = (np.zeros(8 * int(x.sum()), np.uint8) for x in (homes, ends, slot_bytes))
        occupied[8 * starts_of(homes)[block] + home] = 1
        last = np.ones(len(block), bool)
        last[:-1] = (block[1:] != block[:-1]) | (home[1:] != home[:-1])
        end[(8 * starts_of(ends)[block] + place)[last]] = 1
        # padded remainders
        missing = rb - (blocks.bits - self.q)
        padded = ((blocks.value & mask(rb)) >> missing << 1 | 1) << missing
        from_bit = 8 * starts_of(slot_bytes)[block] + place * (rb + 1)
        for j in range(int(rb.max(initial=-1)) + 1):
            held = j <= rb
            slot[(from_bit + j)[held]] = (padded >> np.maximum(rb - j, 0) & 1)[held]
        head = np.arange(n) == 0
        made = {c: x for c, x in blocks.columns.items()}
        made |= {"shard": np.full(n, shard), "version": np.full(n, version), "block": np.arange(n), "edge": np.isin(blocks.pred, list(self.edge))}
        made |= {c: np.where(head, v, 0) for c, v in (("moved", self.moved), ("n_inserted", self.n_inserted), ("n_built", self.n_built))}
        made |= {"occupieds": _rows_of(occupied, homes), "runends": _rows_of(end, ends), "slots": _rows_of(slot, slot_bytes)}
        top = int(blocks.succ[-1])
        upper = dict.fromkeys(columns, 0) | {"shard": shard, "version": version, "block": n, "pred": top, "succ": top, "edge": top in self.edge, "occupieds": b"", "runends": b"", "slots": b""}
        return pd.concat([pd.DataFrame(made)[columns], pd.DataFrame([upper])[columns]], ignore_index=True)

    def positive(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Whether a key may lie in each [lo, hi]: a sentinel that is a key, an anchor inside, or an entry whose interval meets it."""
        blocks = self.blocks
        n = len(blocks)
        out = np.zeros(len(lo), bool)
        for e in self.edge:
            out |= (lo <= e) & (e <= hi)
        anchors = np.append(blocks.pred, blocks.succ[-1])
        i = np.searchsorted(anchors, hi, side="right") - 1
        out |= np.minimum(i + 1, n) > np.maximum(1, np.searchsorted(anchors, lo))
        b = np.clip(i, 0, n - 1)
        low, high = np.maximum(lo, blocks.pred[b] + 1), np.minimum(hi, blocks.succ[b] - 1)
        ask = np.flatnonzero(~out & (i >= 0) & (low <= high))
        if not len(ask) or not len(blocks.block):
            return out
        b = b[ask]
        if self._searched is None:
            g = self.geometries(blocks)
            apart = int(g.m.max())
            missing = g.m[blocks.block] - blocks.bits
            # the farthest end of a block's entries up to each; a block's numbers are above those of the blocks before
            self._searched = g, blocks.block << apart | blocks.value, np.maximum.accumulate(blocks.block << apart | blocks.value | mask(missing)), apart
        g, values, farthest, apart = self._searched
        end = np.searchsorted(values, b << apart | g.infix(high[ask], b), side="right")
        out[ask] = (end > 0) & (farthest[np.maximum(end - 1, 0)] >= (b << apart | g.infix(low[ask], b)))
        return out

    def stats(self) -> dict[str, int]:
        blocks, g = self.blocks, self.geometries(self.blocks)
        r = self.r + blocks.extra
        spans = (g.infix(g.succ) >> r) - (g.infix(g.pred) >> r) + 1
        return {
            "blocks": len(blocks), "anchors": len(blocks) + 1, "entries": len(blocks.block), "slots": int(blocks.n_slots.sum()), "stretches": int(blocks.stretches.sum()),
            "moved": self.moved, "copied": int(blocks.copied.sum()), "inserted": self.n_inserted, "bits": int((spans + blocks.n_slots * (r + 2)).sum()) + (self.width + ANCHOR_BITS) * (len(blocks) + 1),
        }

    def _promoted(self, keys: np.ndarray, number: np.ndarray) -> np.ndarray:
        if self.promotion == "counter":
            return number % self.t == 0
        md5, seed, t = hashlib.md5, self.seed, self.t
        return np.fromiter((int(md5(b"%d#%d" % (seed, x)).hexdigest()[:15], 16) % t == 0 for x in keys.tolist()), bool, len(keys))

    def insert(self, keys: np.ndarray) -> None:
        """Adds ascending, different keys from the lower to the upper sentinel."""
        self._searched = None
        pred, top = self.blocks.pred, int(self.blocks.succ[-1])
        ends = (int(pred[0]), top)
        self.edge |= {e for e in ends if len(keys) and e in (int(keys[0]), int(keys[-1]))}
        at = np.searchsorted(pred, keys, side="right") - 1
        fresh = (pred[at] != keys) & (keys != top)
        keys, at = keys[fresh], at[fresh]
        number = self.n_inserted + 1 + np.arange(len(keys))
        promoted = self._promoted(keys, number)
        self.n_inserted += len(keys)
        # how many new anchors a key's block has had before it
        before = np.cumsum(promoted) - promoted
        part = before - before[np.searchsorted(at, at)] if len(at) else before
        by = np.argsort(part, kind="stable")
        keys, at, number, promoted, part = (x[by] for x in (keys, at, number, promoted, part))
        active, place, done, s, begin = self.blocks, np.arange(len(pred)), [], 0, 0
        while len(active):
            end = int(np.searchsorted(part, s, side="right"))
            now = slice(begin, end)
            cuts, plain = promoted[now], ~promoted[now]
            b, g = place[at[now][plain]], self.geometries(active)
            active = Blocks(active.columns, np.append(active.block, b), np.append(active.value, g.infix(keys[now][plain], b)), np.append(active.bits, g.m[b])).order()
            cut = np.zeros(len(active), bool)
            where = place[at[now][cuts]]
            cut[where] = True
            met = np.zeros(len(active), bool)
            met[b] = True
            done.append(self._stretched(active.take(~cut), met[~cut]))
            left, right = self._split(active.take(cut), keys[now][cuts], number[now][cuts])
            done.append(left)
            place[at[now][cuts]] = np.arange(len(where))
            active, s, begin = right, s + 1, end
        self.blocks = Blocks.concat(done)

    def _stretched(self, blocks: Blocks, met: np.ndarray) -> Blocks:
        slots, stretches, size = blocks.n_slots.copy(), blocks.stretches.copy(), blocks.sizes()
        while (full := met & (size > self.at * slots)).any():
            more = np.where(slots, slots * 2, 1) if self.expansion == "double" else np.maximum(slots + 1, np.ceil(slots * self.factor).astype(np.int64))
            slots, stretches = np.where(full, more, slots), stretches + full
        blocks.columns |= {"n_slots": slots, "stretches": stretches}
        return blocks

    def _split(self, old: Blocks, keys: np.ndarray, number: np.ndarray) -> tuple[Blocks, Blocks]:
        """Each block becomes two at its key; an entry that may belong to both goes to both."""
        extra = np.zeros(len(keys), np.int64)
        if self.widening == "per_doubling":
            extra = np.array([max(0, math.floor(math.log2((self.n_built + n) / max(1, self.n_built)))) for n in number.tolist()], np.int64)
        base, known = self.geometries(old).rebuild(old.value, old.block)
        known = known - (self.q + self.r + old.extra)[old.block] + old.bits
        span = np.where(known < self.width, mask(np.maximum(self.width - known, 0)), 0)
        base &= ~span
        out = []
        for pred, succ in ((old.pred, keys), (keys, old.succ)):
            part = Blocks({"pred": pred, "succ": succ, "extra": extra}, old.block, old.value, old.bits)
            out.append(self._narrowed(part, old.void, base, span, known))
        return out[0], out[1]

    def _narrowed(self, part: Blocks, void: np.ndarray, base: np.ndarray, span: np.ndarray, known: np.ndarray) -> Blocks:
        g, n = self.geometries(part), len(part)
        lo, hi = np.maximum(base, part.pred[part.block] + 1), np.minimum(base | span, part.succ[part.block] - 1)
        met = lo <= hi
        b, lo, known = part.block[met], lo[met], known[met]
        self.moved += len(b)
        have, redundant, m = np.maximum(0, known - g.shared[b]), g.redundant[b], g.m[b]
        have = np.minimum(np.where(have <= 1 + redundant, np.minimum(have, 1), have - redundant), m)
        value = np.where(have > 0, g.infix(lo, b) >> (m - have) << (m - have), 0)
        plain = have > self.q
        # what falls short of a quotient stands for all of them, each once in a block
        vb, vh, r = b[~plain], have[~plain], self.r + part.extra
        first = value[~plain] >> (m[~plain] - vh) << (self.q - vh)
        copies = np.int64(1) << (self.q - vh)
        owner = np.repeat(np.arange(len(vb)), copies)
        full = first[owner] + np.arange(len(owner)) - starts_of(copies)[owner]
        cb = vb[owner]
        legal = ((g.infix(g.pred) >> r)[cb] <= full) & (full <= (g.infix(g.succ) >> r)[cb])
        owner, full, cb = owner[legal], full[legal], cb[legal]
        once = np.unique(cb << self.q | full, return_index=True)[1]
        made = np.bincount(owner[once], minlength=len(vb))
        copied = np.bincount(vb, weights=np.maximum(0, made - 1), minlength=n).astype(np.int64)
        block = np.append(b[plain], cb[once])
        size = np.bincount(block, minlength=n)
        slots = np.maximum(1, np.ceil(size / 0.95).astype(np.int64))
        columns = part.columns | {"n_slots": slots, "stretches": np.zeros(n, np.int64), "void": void + np.bincount(vb, minlength=n), "copied": copied}
        return Blocks(columns, block, np.append(value[plain], full[once] << r[cb[once]]), np.append(have[plain], np.full(len(once), self.q))).order()
