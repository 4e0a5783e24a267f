"""Vectorised text kernels over Arrow batches: tokens, hashes of byte segments, hashes of word windows.

Texts of a batch lie in one UTF-8 buffer, so that separators, lines and words are found for thousands of documents
by a handful of array operations.  Work runs in slices of bounded text size; only a single text larger than the
slice makes a slice of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 2 << 20
SLICE_ROWS = 20_000

_MULT = np.uint64(0x9E3779B97F4A7C15 | 1)
_MULT_INV = np.uint64(pow(int(_MULT), -1, 1 << 64))
#: Bytes of a segment up to which it is hashed in steps of eight.
LONG_SEGMENT = 256
_FIRST_BYTES = np.array([(1 << 8 * i) - 1 for i in range(9)], dtype=np.uint64)
_WORD_MULT = np.uint64(0xD6E8FEB86659FD93)
_WORD_INV = np.uint64(pow(int(_WORD_MULT), -1, 1 << 64))


class _Tables(dict):
    """Tables that each process makes for itself: they don't travel with pickled kernels."""

    def __reduce__(self):
        return _Tables, ()


_powers = _Tables()

#: Bytes that part words: space and the control characters 0x09 to 0x0D.
SPACES = np.zeros(256, dtype=bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
#: Bytes that part alphanumeric words once A-Z are lower-cased: every ASCII byte but digits and a-z.
NON_ALNUM = np.ones(256, dtype=bool)
NON_ALNUM[0x30:0x3A] = False
NON_ALNUM[0x61:0x7B] = False
NON_ALNUM[0x80:] = False
#: A-Z to a-z, other bytes unchanged.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 0x20


def power_table(base: np.uint64, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept for the next call."""
    have = _powers.get(int(base))
    if have is None or len(have) < n:
        step = np.full(max(n, 1 << 16), base, dtype=np.uint64)
        step[0] = 1
        have = _powers[int(base)] = np.cumprod(step, dtype=np.uint64)
    return have[:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser that spreads every input bit over the word."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def text_slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(slice of rows, bytes of their texts, row offsets into those bytes), `most` bytes or one text; a null text has no bytes."""
    for batch in batches:
        if not batch.num_rows:
            continue
        texts = batch.column(batch.schema.get_field_index(column))
        if not pa.types.is_string(texts.type):
            texts = texts.cast(pa.string())
        where = np.frombuffer(texts.buffers()[1], dtype=np.int32, count=texts.offset + len(texts) + 1)[texts.offset :].astype(np.int64)
        raw = texts.buffers()[2]
        data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, np.uint8)
        at = 0
        while at < batch.num_rows:
            to = int(np.searchsorted(where, where[at] + most, side="right")) - 1
            to = min(max(to, at + 1), at + SLICE_ROWS, batch.num_rows)
            yield batch.slice(at, to - at), data[where[at] : where[to]], where[at : to + 1] - where[at]
            at = to


def find_words(data: np.ndarray, rows: np.ndarray, separators: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first word of each row and the word count): words never cross a row's border."""
    inside = ~separators[data]
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(rows), np.int64)
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    border = rows[1:-1][(rows[1:-1] > 0) & (rows[1:-1] < len(data))]
    begins[border] = inside[border]
    stops = inside.copy()
    stops[:-1] &= ~inside[1:]
    stops[border - 1] = inside[border - 1]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    return starts, ends, np.searchsorted(starts, rows)


def segment_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte segment [start, end); segments are in order and do not overlap.

    Eight bytes of all segments at a time; those longer than LONG_SEGMENT are hashed by running sums instead.
    """
    length = ends - starts
    out = mix64(length.astype(np.uint64))
    padded = np.zeros(len(data) + 8, dtype=np.uint8)
    padded[: len(data)] = data
    eights = np.ndarray((len(data) + 1,), "<u8", padded, 0, (1,))
    live = np.flatnonzero(length <= LONG_SEGMENT)
    at, left = starts[live], length[live]
    while len(live):
        x = (out[live] ^ (eights[at] & _FIRST_BYTES[np.minimum(left, 8)])) * _MULT
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        out[live] = x ^ (x >> np.uint64(32))
        more = np.flatnonzero(left > 8)
        live, at, left = live[more], at[more] + 8, left[more] - 8
    out = mix64(out)
    long = np.flatnonzero(length > LONG_SEGMENT)
    if len(long):
        out[long] = _summed_hashes(data, starts[long], ends[long])
    return out


def _summed_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    out = np.empty(len(starts), dtype=np.uint64)
    at = 0
    while at < len(starts):
        to = max(int(np.searchsorted(ends, starts[at] + SLICE_BYTES, side="right")), at + 1)
        lo, hi = int(starts[at]), int(ends[to - 1])
        sums = np.zeros(hi - lo + 1, dtype=np.uint64)
        np.cumsum((data[lo:hi].astype(np.uint64) + np.uint64(1)) * power_table(_MULT, hi - lo), out=sums[1:])
        s, e = starts[at:to] - lo, ends[at:to] - lo
        out[at:to] = (sums[e] - sums[s]) * power_table(_MULT_INV, hi - lo + 1)[s] + (e - s).astype(np.uint64)
        at = to
    return mix64(out)


def run_hashes(words: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each run words[start:end] of word hashes; runs may overlap."""
    sums = np.zeros(len(words) + 1, dtype=np.uint64)
    np.cumsum(words * power_table(_WORD_MULT, len(words)), out=sums[1:])
    return mix64((sums[ends] - sums[starts]) * power_table(_WORD_INV, len(words) + 1)[starts] + (ends - starts).astype(np.uint64))


def window_starts(first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(start of each window of `width` words within a row, row of each)."""
    count = np.maximum(np.diff(first) - width + 1, 0)
    row = np.repeat(np.arange(len(count)), count)
    begin = np.cumsum(count) - count
    return first[:-1][row] + np.arange(len(row)) - begin[row], row


def covered(n: int, starts: np.ndarray, width: int | np.ndarray) -> np.ndarray:
    """Which of n words lie in a window that begins at one of `starts`."""
    edge = np.zeros(n + 1, dtype=np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + width, -1)
    return np.cumsum(edge[:-1]) > 0


def row_sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of values[first[i]:first[i+1]] for each row i."""
    total = np.zeros(len(values) + 1, dtype=np.int64)
    np.cumsum(values, out=total[1:])
    return np.diff(total[first])


def common_counts(of: np.ndarray, items: np.ndarray, sets: int, x: np.ndarray, y: np.ndarray, step_words: int = 1 << 21) -> np.ndarray:
    """Sizes of the intersections of sets x[k] and y[k], which are given as (set, item) without repeats."""
    _, number, count = np.unique(items, return_inverse=True, return_counts=True)
    shared = count > 1
    use = shared[number]
    of, bit = of[use], (np.cumsum(shared) - 1)[number[use]]
    bits = np.zeros((sets, (int(shared.sum()) + 63) // 64 + 1), dtype=np.uint64)
    np.bitwise_or.at(bits, (of, bit >> 6), np.uint64(1) << (bit & 63).astype(np.uint64))
    out = np.zeros(len(x), dtype=np.int64)
    step = max(1, step_words // bits.shape[1])
    for c in range(0, len(x), step):
        out[c : c + step] = np.bitwise_count(bits[x[c : c + step]] & bits[y[c : c + step]]).sum(axis=1, dtype=np.int64)
    return out


def batch_of(schema: pa.Schema, **columns) -> pa.RecordBatch:
    """A record batch of the given columns, cast to the schema's types."""
    arrays = [c if isinstance(c := columns[f.name], (pa.Array, pa.ChunkedArray)) else pa.array(c, type=f.type) for f in schema]
    arrays = [a if a.type == f.type else a.cast(f.type) for a, f in zip(arrays, schema, strict=True)]
    return pa.RecordBatch.from_arrays(arrays, schema=schema)
