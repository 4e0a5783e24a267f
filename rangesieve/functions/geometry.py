"""Block geometry and infixes: as Column expressions over BIGINT or BINARY keys, and over Python integers for the packed kernels.

A block lies between two anchors pred < succ.  Its keys agree on the anchors' shared prefix; the first differing bit tells which anchor a
key sides with; while pred goes on with ones and succ with zeros, a key's bits are the negation of that bit, so they carry nothing and
are skipped.  An infix is the first differing bit followed by the next bits past that run.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bits of an integer key; two fewer than a BIGINT has, so that shifts stay non-negative.
WIDTH = 62
#: Bits of a sample's metadata in the anchor index, besides the key itself.
ANCHOR_BITS = 96


def remainder_len(eps: float) -> int:
    return math.ceil(math.log2(2 / eps))


def infix_len(t: int, eps: float) -> int:
    """Bits of an infix for one anchor every t keys and a false positive rate of eps."""
    return math.ceil(math.log2(2 * t / eps))


def eps_for_bpk(bpk: float, key_bits: int, t: int, dynamic: bool = False, load: float = 0.95) -> float:
    """The rate that a budget of bits per key allows; dynamic blocks have a delimiter bit for each slot and unused slots."""
    overhead = (ANCHOR_BITS + key_bits) / t
    bits = (bpk - overhead - 1) * load * load - 1 if dynamic else bpk - overhead - 2
    return 2.0 / 2 ** max(0, math.floor(bits + 1e-9))


def bit_length(x: Column) -> Column:
    return F.when(x == 0, 0).otherwise(F.length(F.bin(x)))


def shared_bits(pred: Column, succ: Column, width: int = WIDTH) -> Column:
    """Length of the common prefix of two different keys of `width` bits."""
    return (width - bit_length(pred.bitwiseXOR(succ))).cast("int")


def mask(bits: Column) -> Column:
    """A BIGINT whose low `bits` bits are set."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), bits.cast("int")) - 1


def shift_left(x: Column, bits: Column) -> Column:
    return F.call_function("shiftleft", x.cast("long"), bits.cast("int"))


def shift_right(x: Column, bits: Column) -> Column:
    return F.call_function("shiftright", x.cast("long"), bits.cast("int"))


def redundant_bits(pred: Column, succ: Column, width: int = WIDTH) -> Column:
    """How long pred goes on with ones and succ with zeros after the first differing bit."""
    below = (width - shared_bits(pred, succ, width) - 1).cast("int")
    both = pred.bitwiseAND(F.bitwise_not(succ)).bitwiseAND(mask(below))
    return (below - bit_length(F.bitwise_not(both).bitwiseAND(mask(below)))).cast("int")


def derive_infix(key: Column, shared: Column, redundant: Column, m: int, width: int = WIDTH) -> Column:
    """The m-bit infix of an integer key in a block of this geometry, padded with zeros at the key's end."""
    first = (width - shared - 1).cast("int")
    left = first - redundant
    rest = F.when(left >= m - 1, shift_right(key, F.greatest(left - (m - 1), F.lit(0))).bitwiseAND(F.lit((1 << (m - 1)) - 1))).otherwise(shift_left(key.bitwiseAND(mask(left)), F.greatest((m - 1) - left, F.lit(0))))
    return shift_left(shift_right(key, first).bitwiseAND(F.lit(1)), F.lit(m - 1)).bitwiseOR(rest)


def rebuild_prefix(infix: Column, pred: Column, shared: Column, redundant: Column, m: int, width: int = WIDTH) -> Column:
    """The key bits that an infix stands for, the unknown rest zero: shared prefix, first bit, its negated run, the infix's rest."""
    first = (width - shared - 1).cast("int")
    head = shift_left(shift_right(pred, first + 1), first + 1)
    bit = shift_right(infix, F.lit(m - 1)).bitwiseAND(F.lit(1))
    left = first - redundant
    run = F.when(bit == 0, shift_left(mask(redundant), left)).otherwise(F.lit(0).cast("long"))
    low = infix.bitwiseAND(F.lit((1 << (m - 1)) - 1))
    rest = F.when(left >= m - 1, shift_left(low, F.greatest(left - (m - 1), F.lit(0)))).otherwise(shift_right(low, F.greatest((m - 1) - left, F.lit(0))))
    return head.bitwiseOR(shift_left(bit, first)).bitwiseOR(run).bitwiseOR(rest)


def split_infix(infix: Column, r: int) -> tuple[Column, Column]:
    """(quotient, remainder): the remainder is the low r bits."""
    return F.shiftright(infix, r), infix.bitwiseAND(F.lit((1 << r) - 1))


def binary_slice(key: Column, start: Column, bits: int) -> Column:
    """`bits` (48 at most) bits of a BINARY key from bit `start`, zeros past its end, as BIGINT."""
    at = start.cast("int")
    chunk = F.rpad(F.substring(key, F.floor(at / 8).cast("int") + 1, F.lit(7)), 7, F.lit(b"\x00"))
    return shift_right(F.conv(F.hex(chunk), 16, 10).cast("long"), 56 - at % 8 - bits).bitwiseAND(F.lit((1 << bits) - 1))


def derive_binary_infix(key: Column, shared: Column, redundant: Column, m: int) -> Column:
    """The m-bit infix of a byte-string key."""
    return shift_left(binary_slice(key, shared, 1), F.lit(m - 1)).bitwiseOR(binary_slice(key, shared + 1 + redundant, m - 1))


@dataclass(frozen=True)
class Geometry:
    """A block's geometry over integers of any width (byte strings are read as integers, padded with zeros)."""

    pred: int
    succ: int
    width: int
    m: int

    @property
    def shared(self) -> int:
        return self.width - (self.pred ^ self.succ).bit_length()

    @property
    def redundant(self) -> int:
        below = self.width - self.shared - 1
        ones = (1 << below) - 1
        both = self.pred & ~self.succ & ones
        return below - (~both & ones).bit_length()

    def infix(self, key: int) -> int:
        first = self.width - self.shared - 1
        left = first - self.redundant
        rest = key & ((1 << left) - 1)
        rest = rest >> (left - self.m + 1) if left >= self.m - 1 else rest << (self.m - 1 - left)
        return ((key >> first) & 1) << (self.m - 1) | rest

    def suffix(self, key: int) -> str:
        """The key's bits past its infix."""
        left = self.width - self.shared - 1 - self.redundant - (self.m - 1)
        return format(key & ((1 << left) - 1), f"0{left}b") if left > 0 else ""

    def rebuild(self, infix: int) -> tuple[int, int]:
        """(known bits as a left-aligned key, how many bits are known)."""
        first = self.width - self.shared - 1
        bit, left = infix >> (self.m - 1), first - self.redundant
        known = min(self.m - 1, left)
        low = (infix & ((1 << (self.m - 1)) - 1)) >> (self.m - 1 - known)
        run = ((1 << self.redundant) - 1) << left if bit == 0 else 0
        key = self.pred >> (first + 1) << (first + 1) | bit << first | run | low << (left - known)
        return key, self.shared + 1 + self.redundant + known

    @property
    def low(self) -> int:
        return self.infix(self.pred)

    @property
    def high(self) -> int:
        return self.infix(self.succ)


def bytes_to_int(key: bytes, width: int) -> int:
    return int.from_bytes(key, "big") << (width - 8 * len(key)) if 8 * len(key) <= width else int.from_bytes(key[: width // 8], "big")
