"""Packed blocks: infixes as quotients and remainders in an occupieds bitmap, a runends bitmap and bit-packed slots."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def rank(bits: np.ndarray, i: int) -> int:
    """Ones before place i."""
    return int(np.count_nonzero(bits[:i]))


def select(bits: np.ndarray, i: int) -> int:
    """Place of the i-th one, from 0; the length if there are fewer."""
    ones = np.flatnonzero(bits)
    return int(ones[i]) if 0 <= i < len(ones) else len(bits)


def pack_bits(values: np.ndarray, width: int) -> bytes:
    """Integers as consecutive fields of `width` bits, most significant bit first."""
    if not width or not len(values):
        return b""
    places = np.arange(width - 1, -1, -1, dtype=np.uint64)
    return np.packbits(((values.astype(np.uint64)[:, None] >> places) & np.uint64(1)).astype(np.uint8).ravel()).tobytes()


def unpack_bits(raw: bytes, n: int, width: int) -> np.ndarray:
    if not width or not n:
        return np.zeros(n, dtype=np.int64)
    bits = np.unpackbits(np.frombuffer(raw, np.uint8), count=n * width).reshape(n, width).astype(np.int64)
    return bits @ (1 << np.arange(width - 1, -1, -1, dtype=np.int64))


@dataclass
class Block:
    """Sorted infixes of one block; quotients count from q_base."""

    r: int
    q_base: int
    occupieds: np.ndarray
    runends: np.ndarray
    slots: np.ndarray

    @classmethod
    def pack(cls, infixes: np.ndarray, low: int, high: int, r: int) -> Block:
        """infixes between the anchors' own infixes `low` and `high`; duplicates stay."""
        infixes = np.sort(np.asarray(infixes, dtype=np.int64))
        q, base = infixes >> r, low >> r
        occupieds = np.zeros((high >> r) - base + 1, dtype=bool)
        occupieds[q - base] = True
        runends = np.ones(len(q), dtype=bool)
        runends[:-1] = q[1:] != q[:-1]
        return cls(r, base, occupieds, runends, infixes & ((1 << r) - 1))

    def to_bytes(self) -> tuple[bytes, bytes, bytes]:
        return np.packbits(self.occupieds).tobytes(), np.packbits(self.runends).tobytes(), pack_bits(self.slots, self.r)

    @classmethod
    def from_bytes(cls, r: int, q_base: int, q_count: int, n: int, occupieds: bytes, runends: bytes, slots: bytes) -> Block:
        bits = lambda raw, k: np.unpackbits(np.frombuffer(raw, np.uint8), count=k).astype(bool) if k else np.zeros(0, bool)
        return cls(r, q_base, bits(occupieds, q_count), bits(runends, n), unpack_bits(slots, n, r))

    def matched(self) -> bool:
        """The i-th occupied quotient owns the i-th run."""
        return int(self.occupieds.sum()) == int(self.runends.sum()) and (not len(self.runends) or bool(self.runends[-1]))

    def run(self, q: int) -> np.ndarray:
        """Remainders of an occupied quotient."""
        i = rank(self.occupieds, q - self.q_base)
        end = select(self.runends, i)
        start = select(self.runends, i - 1) + 1 if i else 0
        return self.slots[start : end + 1]

    def infixes(self) -> np.ndarray:
        run = np.cumsum(np.concatenate([[0], self.runends[:-1]])) if len(self.runends) else np.zeros(0, int)
        return ((np.flatnonzero(self.occupieds)[run] + self.q_base) << self.r) | self.slots

    def _occupied(self, q: int) -> bool:
        return 0 <= q - self.q_base < len(self.occupieds) and bool(self.occupieds[q - self.q_base])

    def probe(self, low: int, high: int) -> str:
        """The cause of a positive answer for infixes low to high, both included, or "none"."""
        ql, qh, ones = low >> self.r, high >> self.r, (1 << self.r) - 1
        if ql == qh:
            hit = self._occupied(ql) and bool(((self.run(ql) >= low & ones) & (self.run(ql) <= high & ones)).any())
            return "single" if hit else "none"
        if rank(self.occupieds, max(0, qh - self.q_base)) > rank(self.occupieds, max(0, ql + 1 - self.q_base)):
            return "middle"
        if self._occupied(ql) and int(self.run(ql)[-1]) >= low & ones:
            return "left"
        return "right" if self._occupied(qh) and int(self.run(qh)[0]) <= high & ones else "none"

    def bits(self) -> int:
        return len(self.occupieds) + len(self.runends) + len(self.slots) * self.r
