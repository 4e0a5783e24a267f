"""Order-preserving entropy code: bisection codes per context of k bytes, their quality measures, and encoding of keys.

Every context has pseudo-counts for all bytes, so that any query endpoint can be encoded; a context that the codebook lacks uses the
order-0 code.  Codes are prefix-free and ordered like the symbols, so encoded keys compare like keys.
"""

from __future__ import annotations

import bisect
import heapq
import math
import zlib
from array import array
from collections.abc import Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Contexts that are seen less often share the order-0 code.
LEAST_CONTEXT = 32


def bisection_codes(freqs: list[tuple[int, float]]) -> dict[int, str]:
    """Codes of (symbol, weight) pairs in symbol order: each set is cut where the halves' weights are closest, at the earlier place in a tie."""
    out: dict[int, str] = {}
    stack = [(0, len(freqs), "")]
    total = [0.0]
    for _, w in freqs:
        total.append(total[-1] + w)
    while stack:
        lo, hi, code = stack.pop()
        if hi - lo == 1:
            out[freqs[lo][0]] = code or "0"
            continue
        whole = total[lo] + total[hi]
        # running totals never fall: the closest is beside half the weight, the first of equal ones below it
        above = min(bisect.bisect_left(total, whole / 2, lo + 1, hi), hi - 1)
        below = bisect.bisect_left(total, total[max(lo + 1, above - 1)], lo + 1, hi)
        cut = min((below, above), key=lambda i: (abs(2 * total[i] - whole), i))
        stack += [(lo, cut, code + "0"), (cut, hi, code + "1")]
    return out


def alphabetic_codes(freqs: list[tuple[int, float]]) -> dict[int, str]:
    """Optimal ordered prefix codes, by dynamic programming over intervals with monotone roots; a comparison for small alphabets."""
    n = len(freqs)
    total = [0.0]
    for _, w in freqs:
        total.append(total[-1] + w)
    cost, root = [[0.0] * (n + 1) for _ in range(n + 1)], [[0] * (n + 1) for _ in range(n + 1)]
    for i in range(n):
        root[i][i + 1] = i + 1
    for size in range(2, n + 1):
        for i in range(n - size + 1):
            j = i + size
            lo, hi = max(i + 1, root[i][j - 1]), min(j - 1, root[i + 1][j])
            best = min(range(lo, max(lo, hi) + 1), key=lambda c: cost[i][c] + cost[c][j])
            root[i][j], cost[i][j] = best, cost[i][best] + cost[best][j] + total[j] - total[i]
    out: dict[int, str] = {}
    stack = [(0, n, "")]
    while stack:
        i, j, code = stack.pop()
        if j - i == 1:
            out[freqs[i][0]] = code or "0"
        else:
            stack += [(i, root[i][j], code + "0"), (root[i][j], j, code + "1")]
    return out


def huffman_lengths(freqs: list[tuple[int, float]]) -> dict[int, int]:
    """Code lengths of an optimal prefix code that need not keep the order."""
    heap = [(w, i, (s,)) for i, (s, w) in enumerate(freqs)]
    heapq.heapify(heap)
    out = dict.fromkeys((s for s, _ in freqs), 0 if len(freqs) > 1 else 1)
    n = len(freqs)
    while len(heap) > 1:
        (wa, _, a), (wb, _, b) = heapq.heappop(heap), heapq.heappop(heap)
        for s in (*a, *b):
            out[s] += 1
        heapq.heappush(heap, (wa + wb, n, (*a, *b)))
        n += 1
    return out


def entropy_bits(freqs: list[tuple[int, float]]) -> float:
    total = sum(w for _, w in freqs)
    return -sum(w / total * math.log2(w / total) for _, w in freqs if w)


def mean_length(freqs: list[tuple[int, float]], lengths: dict[int, int] | dict[int, str]) -> float:
    size = lambda v: v if isinstance(v, int) else len(v)
    return sum(w * size(lengths[s]) for s, w in freqs) / sum(w for _, w in freqs)


def symbol_counts(keys: DataFrame, k: int, key: str = "key") -> DataFrame:
    """(context, symbol, freq): bytes as hex pairs after the k bytes before them, 3 at most; keys count once each."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = [x for x in batch.column(0).to_pylist() if x]
            data = np.frombuffer(b"".join(raw), np.uint8).astype(np.uint64)
            size = np.array([len(x) for x in raw], dtype=np.int64)
            place = np.arange(len(data)) - np.repeat(np.cumsum(size) - size, size)
            # the byte, those before it, and how many of these there are
            code = data | (np.minimum(place, k).astype(np.uint64) << np.uint64(32))
            for j in range(1, k + 1):
                code[j:] |= np.where(place[j:] >= j, data[:-j] << np.uint64(8 * j), np.uint64(0))
            code, n = np.unique(code, return_counts=True)
            context = [format(x >> 8 & 0xFFFFFF, "08X")[8 - 2 * (x >> 32) :] for x in code.tolist()]
            yield pa.RecordBatch.from_arrays([pa.array(context, pa.string()), pa.array([format(x & 255, "02X") for x in code.tolist()], pa.string()), pa.array(n)], names=["context", "symbol", "freq"])

    parts = keys.select(F.col(key).cast("binary").alias("key")).mapInArrow(count, "context string, symbol string, freq long")
    return parts.groupBy("context", "symbol").agg(F.sum("freq").alias("freq"))


def pack_codes(codes: dict[int, str]) -> bytes:
    """The codes of all 256 bytes, each after a leading one, compressed."""
    return zlib.compress(array("Q", (int("1" + codes[s], 2) for s in range(256))).tobytes(), 1)


class PackedCodes(Mapping):
    """Codes by context, packed; those of the contexts that were asked last are held unpacked."""

    HELD = 2048

    def __init__(self, packed: dict[bytes, bytes]):
        self.packed, self._held = packed, {}

    def __getitem__(self, context: bytes) -> dict[int, str]:
        if (found := self._held.get(context)) is None:
            found = {s: bin(v)[3:] for s, v in enumerate(array("Q", zlib.decompress(self.packed[context])))}
            if len(self._held) >= self.HELD:
                self._held.clear()
            self._held[context] = found
        return found

    def get(self, context: bytes, default: dict[int, str] | None = None) -> dict[int, str] | None:
        found = self._held.get(context)
        return found if found is not None else self[context] if context in self.packed else default

    def __contains__(self, context: object) -> bool:
        return context in self.packed

    def __iter__(self) -> Iterator[bytes]:
        return iter(self.packed)

    def __len__(self) -> int:
        return len(self.packed)

    def __getstate__(self) -> dict[bytes, bytes]:
        return self.packed

    def __setstate__(self, packed: dict[bytes, bytes]) -> None:
        self.packed, self._held = packed, {}


def _context_codes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(context, seen) to (context, codes): the packed codes of each context, whose seen bytes come with their counts."""
    for b in batches:
        made = []
        for seen in b.column(1).to_pylist():
            freqs = {int(x["symbol"], 16): x["freq"] for x in seen}
            made.append(pack_codes(bisection_codes([(s, freqs.get(s, 0) + 1 / 256) for s in range(256)])))
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(made, pa.binary())], names=["context", "codes"])


class Codebook:
    """Codes by context; contexts are bytes, codes strings of 0 and 1."""

    def __init__(self, k: int, codes: Mapping[bytes, dict[int, str]], default: dict[int, str]):
        self.k, self.codes, self.default = k, codes, default

    @classmethod
    def build(cls, keys: DataFrame, k: int = 2, key: str = "key", least: int = LEAST_CONTEXT) -> Codebook:
        """Counts and codes are made in Spark; the packed codes of at most 256**k contexts that are seen often enough reach the driver."""
        if k > 3:
            raise ValueError("contexts of more than three bytes have no bounded codebook")
        zero = {int(r["symbol"], 16): r["freq"] for r in symbol_counts(keys, 0, key).collect()}
        default = bisection_codes([(s, zero.get(s, 0) + 1 / 256) for s in range(256)])
        packed: dict[bytes, bytes] = {}
        if k:
            # 256 bytes follow a context at most
            often = symbol_counts(keys, k, key).groupBy("context").agg(F.sum("freq").alias("n"), F.collect_list(F.struct("symbol", "freq")).alias("seen")).where(F.col("n") >= least)
            for b in often.select("context", "seen").mapInArrow(_context_codes, "context string, codes binary").toArrow().to_batches():
                packed.update(zip(map(bytes.fromhex, b.column(0).to_pylist()), b.column(1).to_pylist(), strict=True))
        return cls(k, PackedCodes(packed), default)

    def encode(self, key: bytes) -> str:
        return "".join(self.codes.get(key[max(0, i - self.k) : i], self.default)[b] if self.k else self.default[b] for i, b in enumerate(key))

    def _words(self, context: bytes, held: dict[bytes | None, np.ndarray]) -> np.ndarray:
        """The codes of all bytes after a leading one, 0 for a byte without any."""
        if (found := held.get(context)) is None:
            if not self.k or context not in self.codes:
                # the default's table is one for all
                if (found := held.get(None)) is None:
                    found = held[None] = np.array([int("1" + self.default[s], 2) if s in self.default else 0 for s in range(256)], np.uint64)
                return found
            if isinstance(self.codes, PackedCodes):
                found = np.frombuffer(zlib.decompress(self.codes.packed[context]), np.uint64)
            else:
                book = self.codes[context]
                found = np.array([int("1" + book[s], 2) if s in book else 0 for s in range(256)], np.uint64)
            if len(held) >= PackedCodes.HELD:
                held.clear()
            held[context] = found
        return found

    def encode_many(self, keys: list[bytes], held: dict[bytes | None, np.ndarray]) -> tuple[list[bytes], list[str]]:
        """(codes zero-padded to bytes, codes as text): bytes after the same context are looked up together; held: tables of contexts that were met."""
        data = np.frombuffer(b"".join(keys), np.uint8).astype(np.uint64)
        size = np.fromiter(map(len, keys), np.int64, len(keys))
        first = np.cumsum(size) - size
        place = np.arange(len(data)) - np.repeat(first, size)
        # the bytes before, and how many these are
        context = np.minimum(place, self.k).astype(np.uint64) << np.uint64(32)
        for j in range(1, self.k + 1):
            context[j:] |= np.where(place[j:] >= j, data[:-j] << np.uint64(8 * (j - 1)), np.uint64(0))
        by = np.argsort(context, kind="stable")
        begins = np.flatnonzero(np.diff(context[by], prepend=~context[by[:1]]))
        word = np.zeros(len(data), np.uint64)
        for a, b in zip(begins.tolist(), [*begins.tolist()[1:], len(by)], strict=False):
            x = int(context[by[a]])
            word[by[a:b]] = self._words((x & 0xFFFFFFFF).to_bytes(x >> 32, "big"), held)[data[by[a:b]].astype(np.int64)]
        if not word.all():
            raise KeyError(f"no code for byte {int(data[np.argmin(word)])}")
        high, low = word >> np.uint64(32), word & np.uint64(0xFFFFFFFF)
        length = (np.where(high > 0, 32 + np.frexp(high.astype(np.float64))[1], np.frexp(low.astype(np.float64))[1]) - 1).astype(np.int64)
        total = np.concatenate([[0], np.cumsum(length)])
        bits = total[first + size] - total[first]
        whole = -(-bits // 8)
        start = np.cumsum(whole) - whole
        at = total[:-1] + np.repeat(8 * start - total[first], size)
        flat, some, j = np.zeros(8 * int(whole.sum()), np.uint8), np.arange(len(data)), 0
        while len(some := some[length[some] > j]):
            flat[at[some] + j] = word[some] >> (length[some] - 1 - j).astype(np.uint64) & np.uint64(1)
            j += 1
        packed, text = np.packbits(flat).tobytes(), (flat + 48).tobytes().decode()
        rows = list(zip(start.tolist(), whole.tolist(), bits.tolist(), strict=True))
        return [packed[a : a + n] for a, n, _ in rows], [text[8 * a : 8 * a + n] for a, _, n in rows]

    def decode(self, bits: str) -> bytes:
        out, at = bytearray(), 0
        while at < len(bits):
            code = self.codes.get(bytes(out[max(0, len(out) - self.k) :]), self.default) if self.k else self.default
            inverse = {v: s for s, v in code.items()}
            end = next((e for e in range(at + 1, len(bits) + 1) if bits[at:e] in inverse), None)
            if end is None:
                raise ValueError("no code word")
            out.append(inverse[bits[at:end]])
            at = end
        return bytes(out)

    def bits(self) -> int:
        """Size: a tree of n leaves takes 2n - 1 bits of shape; symbols stand in order and need no labels."""
        return (len(self.codes) + 1) * (2 * 256 - 1) + len(self.codes) * 8 * self.k

    def rows(self) -> list[tuple[str, int, str]]:
        return [("", s, c) for s, c in self.default.items()] + [(ctx.hex(), s, c) for ctx, book in self.codes.items() for s, c in book.items()]

    @classmethod
    def from_rows(cls, k: int, rows: list[tuple[str, int, str]]) -> Codebook:
        codes: dict[bytes, dict[int, str]] = {}
        for context, s, c in rows:
            codes.setdefault(bytes.fromhex(context), {})[s] = c
        return cls(k, {c: b for c, b in codes.items() if c}, codes[b""])

    def save(self, spark, path: str) -> None:
        spark.createDataFrame(self.rows(), "context string, symbol int, code string").write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark, path: str, k: int) -> Codebook:
        return cls.from_rows(k, [tuple(r) for r in spark.read.parquet(path).collect()])


def to_bytes(bits: str) -> bytes:
    return int(bits.ljust(-(-len(bits) // 8) * 8, "0") or "0", 2).to_bytes(max(1, -(-len(bits) // 8)), "big") if bits else b""


def plain_bits(key: bytes) -> str:
    return format(int.from_bytes(key, "big"), f"0{8 * len(key)}b") if key else ""


def encode_columns(df: DataFrame, columns: list[str], book: Codebook | None) -> DataFrame:
    """df with each column replaced by its code, zero-padded to bytes, and `<column>_code`, the code as a string of 0 and 1.

    Without a book a key's code is its own bits.
    """
    rest = [f for f in df.schema.fields if f.name not in columns]
    full = T.StructType([*rest, *(T.StructField(c, T.BinaryType()) for c in columns), *(T.StructField(f"{c}_code", T.StringType()) for c in columns)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes | None, np.ndarray] = {}
        for b in batches:
            packed, codes = [], []
            for c in columns:
                keys = [v.encode() if isinstance(v, str) else v for v in b.column(c).to_pylist()]
                present = [v for v in keys if v is not None]
                raw, text = (present, list(map(plain_bits, present))) if book is None else book.encode_many(present, held)
                for made, out, kind in ((raw, packed, pa.binary()), (text, codes, pa.string())):
                    each = iter(made)
                    out.append(pa.array([None if v is None else next(each) for v in keys], kind))
            yield pa.RecordBatch.from_arrays([*(b.column(f.name) for f in rest), *packed, *codes], names=full.names)

    return df.mapInArrow(run, full)


def compression_ratio(keys: DataFrame, book: Codebook) -> float:
    """Key bits over code bits."""
    coded = encode_columns(keys.select(F.col("key").cast("binary").alias("key"), F.octet_length(F.col("key").cast("binary")).alias("n")), ["key"], book)
    row = coded.agg(F.sum("n").alias("a"), F.sum(F.length("key_code")).alias("b")).first()
    return 8.0 * row["a"] / row["b"] if row["b"] else float("nan")


def dictionary_codes(keys: list[bytes], n: int, gram: int = 3) -> list[tuple[bytes, bytes]]:
    """An order-preserving dictionary of n byte-aligned intervals bounded by frequent grams: (least string, two-byte code)."""
    seen: dict[bytes, int] = {}
    for k in keys:
        for i in range(0, len(k), gram):
            seen[k[i : i + gram]] = seen.get(k[i : i + gram], 0) + 1
    bounds = sorted({b"", *sorted(seen, key=lambda g: (-seen[g], g))[: n - 1]})
    return [(b, i.to_bytes(2, "big")) for i, b in enumerate(bounds)]
