"""Line dedup: an exact set-similarity join over the word sets of lines, by prefixes of their rarest words.

A line's distinct words are ordered by rarity: words outside a bounded list of frequent ones first, by hash, then the listed ones by
count.  Lines that reach the threshold share a word of their prefixes; length, position and a parity sketch of the sets rule out most
other pairs, and exact counts on the line texts decide.  A line goes if a similar line stands earlier.

Lines of equal words are one class, whose first line stays for all; classes are joined, not lines.  The words of a prefix meet in
buckets, and a bucket proposes for each class the earlier class that is closest by the sketches, which the texts confirm or not.  A
class that isn't settled by that and has more partners than one is compared with all of them: the classes of such a word, and those of
words too frequent for one bucket, are a star, stars are cut into blocks, and each pair of blocks is a cell of work, which returns the
settled classes only.  So the work may grow with the square of a group of near lines, as comparing them does, but not the rows.

Defined results: a null or wordless text has no lines; lines are parted by newlines and numbered from 0, wordless ones are never
removed; order is (doc_id, line number); rows that repeat a doc_id are versions side by side and do not remove each other's equal lines;
a null doc_id keeps all its lines and removes none; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, table
from .textkernel import common_counts, find_words, mix64, segment_hashes, text_slices

#: Counters of words, by the first bits of their hashes: 4 MB once each is one byte, whatever the data.
COUNTER_BITS = 22
#: Counters that travel as one row.
SEGMENT = 1 << 16
#: Levels of a counter to a doubling of the count.
LEVELS = 8
#: A word with more occurrences has its classes dealt over several buckets, and meets them in cells.
HOT_WORD = 200_000
#: Prefix words that meet in one exchange bucket; bounds the memory of the task that reads it.
BUCKET_WORDS = 100_000
#: Prefix words that a task of the exchange gathers before it sends them.
SEND_WORDS = 1_000_000
#: Classes of one word that a bucket compares itself; more are a star.
IN_BUCKET = 4096
#: Members of a cell's block and words of their texts; more members make more cells, none is left out.
BLOCK_MEMBERS, BLOCK_WORDS = 2048, 200_000
#: Bits of the filter that picks lines out of the documents: 4 MB, whatever the data.
PICK_BITS = 1 << 25
#: Pairs that are compared in one step, and bytes of texts.
STEP_PAIRS, STEP_BYTES = 1 << 19, 4 << 20
CLASS = np.dtype([("cls", "<u8"), ("s1", "<u8"), ("s2", "<u8"), ("doc", "<i8"), ("line", "<i4"), ("n", "<u2")])
ENTRY = np.dtype([("word", "<u4"), ("at", "<u4"), ("pos", "u1")])
#: Columns in whose bytes there is nothing to find.
HASHED = ("cls", "s1", "s2")
#: Bit of `pos` that tells that the word belongs to the shorter prefix under which the class can be found.
INDEXED = 128
#: Buckets of hot words.
HOT_BUCKET = 1 << 30
_SECOND = np.uint64(0xC2B2AE3D27D4EB4F)
_LISTED = "doc_id long, lines array<int>, c1 array<long>, c2 array<long>, segment int, cells binary, counts binary, n_words long"
_PACKED = "bucket int, classes binary, entries binary"
_MEMBER = "star long, cls long, dense boolean, doc long, line int, s1 long, s2 long, n int, pos int"
_MET = f"a long, b long, apart int, b_doc long, b_line int, {_MEMBER}"
_LINE = "doc_id long, line int, c1 long, c2 long, text binary"


class Lines:
    """The lines of a slice that hold a word: bounds, row, number, words, and two hashes of the words' multiset."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        starts, ends, first = find_words(data, offsets)
        of_row = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
        breaks = np.flatnonzero(data == 10)
        of_break = np.repeat(np.arange(len(breaks) + 1), np.diff(np.concatenate([[0], np.searchsorted(starts, breaks), [len(starts)]])))
        self.head = np.flatnonzero(np.diff(of_break + of_row, prepend=-1))
        self.ends = np.append(self.head[1:], len(starts))[: len(self.head)]
        before = of_break[self.head]
        padded = np.concatenate([[-1], breaks, [len(data)]])
        self.row = of_row[self.head]
        self.lo = np.maximum(padded[before] + 1, offsets[self.row])
        self.hi = np.minimum(padded[before + 1], offsets[self.row + 1])
        self.number = (before - np.searchsorted(breaks, offsets[self.row])).astype(np.int32)
        self.words = segment_hashes(data, starts, ends)
        self.c1, self.c2 = (mix64(self._sums(x) + (self.ends - self.head).astype(np.uint64)) for x in (self.words, mix64(self.words ^ _SECOND)))

    def _sums(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x) + 1, dtype=np.uint64)
        np.cumsum(x, out=total[1:])
        return total[self.ends] - total[self.head]


def counter_of(words: np.ndarray) -> np.ndarray:
    return (words >> np.uint64(64 - COUNTER_BITS)).astype(np.int64)


def new_runs(*keys: np.ndarray) -> np.ndarray:
    """Where any of the keys differs from the row before."""
    out = np.ones(len(keys[0]), dtype=bool)
    out[1:] = np.any([k[1:] != k[:-1] for k in keys], axis=0)
    return out


def list_lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text) to _LISTED: numbers and hashes of each text's lines, and last the word counters of all that the task saw."""
    counters = np.zeros(1 << COUNTER_BITS, dtype=np.uint32)
    names = [x.split()[0] for x in _LISTED.split(", ")]
    for batch, data, offsets in text_slices(batches):
        lines = Lines(data, offsets)
        np.add.at(counters, counter_of(lines.words), np.uint32(1))
        at = pa.array(np.searchsorted(lines.row, np.arange(batch.num_rows + 1)), pa.int32())
        lists = [pa.ListArray.from_arrays(at, pa.array(x)) for x in (lines.number, lines.c1.view(np.int64), lines.c2.view(np.int64))]
        yield pa.RecordBatch.from_arrays([batch.column(0), *lists, *(pa.nulls(batch.num_rows, t) for t in (pa.int32(), pa.binary(), pa.binary(), pa.int64()))], names=names)
    used = np.flatnonzero(counters)
    cuts = np.searchsorted(used, np.arange(0, (1 << COUNTER_BITS) + 1, SEGMENT))
    for k in np.flatnonzero(np.diff(cuts)).tolist():
        part = used[cuts[k] : cuts[k + 1]]
        row = [pa.nulls(1, pa.int64()), *(pa.nulls(1, pa.list_(t)) for t in (pa.int32(), pa.int64(), pa.int64())), pa.array([k], pa.int32()), pa.array([by_bytes(np.diff((part % SEGMENT).astype(np.uint16), prepend=np.uint16(0)))], pa.binary()), pa.array([by_bytes(counters[part])], pa.binary()), pa.array([int(counters[part].sum(dtype=np.int64))])]
        yield pa.RecordBatch.from_arrays(row, names=names)


def by_bytes(x: np.ndarray) -> bytes:
    """First bytes, second bytes and so on of all numbers: the exchange's compression finds the zeros."""
    return np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes() if len(x) else b""


def from_bytes(raw: bytes, dtype: np.dtype) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(dtype.itemsize, -1).T).view(dtype).ravel()


def add_counters(group: pa.Table) -> pa.Table:
    """The levels of one segment of counters."""
    total = np.zeros(SEGMENT, dtype=np.int64)
    for cells, counts in zip(group.column("cells").to_pylist(), group.column("counts").to_pylist(), strict=True):
        total[np.cumsum(from_bytes(cells, np.dtype(np.uint16)), dtype=np.uint16)] += from_bytes(counts, np.dtype(np.uint32))
    level = np.where(total > 0, np.minimum(1 + LEVELS * np.log2(np.maximum(total, 1)), 255), 0).astype(np.uint8)
    return pa.table({"segment": group.column("segment").slice(0, 1), "levels": pa.array([level.tobytes()], pa.binary())})


def parity_of(words: np.ndarray, of: np.ndarray, n: int) -> np.ndarray:
    """128 bits for each of n sets: bit i tells whether an odd number of the set's words falls on i."""
    bit = (mix64(words ^ np.uint64(0xA5A5A5A5A5A5A5A5)) >> np.uint64(57)).astype(np.int64)
    odd = np.bincount(of * 128 + bit, minlength=128 * n).astype(np.uint8) & np.uint8(1)
    return np.packbits(odd.reshape(n, 128), axis=1, bitorder="little").view("<u8").reshape(n, 2)


class Prefixes:
    """What orders words by rarity, and where the entries of their classes go."""

    def __init__(self, levels: np.ndarray, num: int, den: int, buckets: int):
        self.levels, self.num, self.den, self.buckets = levels, num, den, buckets

    def entries(self, lines: Lines, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(classes, buckets, entries) of a slice, each class under its first line."""
        num, den = self.num, self.den
        order = np.lexsort((lines.number, ids[lines.row], lines.c1))
        keep = np.sort(order[new_runs(lines.c1[order])])
        size = lines.ends[keep] - lines.head[keep]
        of = np.repeat(np.arange(len(keep)), size)
        words = lines.words[np.arange(int(size.sum())) + np.repeat(lines.head[keep] - np.cumsum(size) + size, size)]
        by_hash = np.argsort(words)
        head = np.flatnonzero(new_runs(words[by_hash]))
        unique = words[by_hash[head]]
        # a word's place: by level, then by hash
        by_place = np.argsort((self.levels[counter_of(unique)].astype(np.int64) << 32) + np.arange(len(unique)))
        place = np.empty(len(unique), np.int64)
        place[by_place] = np.arange(len(unique))
        of_word = np.empty(len(words), np.int64)
        of_word[by_hash] = np.repeat(place, np.diff(np.append(head, len(words))))
        key = np.sort((of << 32) | of_word)
        key = key[new_runs(key)]
        of, number = key >> 32, key & 0xFFFFFFFF
        unique = unique[by_place]
        first = np.searchsorted(of, np.arange(len(keep) + 1))
        n = np.diff(first)
        classes = np.empty(len(keep), dtype=CLASS)
        sketch = parity_of(unique[number], of, len(keep))
        classes["cls"], classes["doc"], classes["line"], classes["n"] = lines.c1[keep], ids[lines.row[keep]], lines.number[keep], np.minimum(n, 65535)
        classes["s1"], classes["s2"] = sketch[:, 0], sketch[:, 1]
        probe, index = n - -(-n * num // den) + 1, n - -(-2 * n * num // (num + den)) + 1
        at = np.repeat(first[:-1] - np.cumsum(probe) + probe, probe) + np.arange(int(probe.sum()))
        o, word = of[at], unique[number[at]]
        pos = at - first[o]
        e = np.empty(len(at), dtype=ENTRY)
        e["word"], e["at"], e["pos"] = (word & np.uint64(0xFFFFFFFF)).astype(np.uint32), o, np.minimum(pos, 127) + INDEXED * (pos < index[o])
        bucket = ((word >> np.uint64(32)) % np.uint64(self.buckets)).astype(np.int64)
        often = 2.0 ** ((self.levels[counter_of(word)].astype(np.float64) - 1) / LEVELS)
        hot = np.flatnonzero(often > HOT_WORD)
        parts = (often[hot] / HOT_WORD).astype(np.uint64) + np.uint64(1)
        bucket[hot] = HOT_BUCKET + (mix64(word[hot] + mix64(classes["cls"][o[hot]]) % parts) % np.uint64(HOT_BUCKET)).astype(np.int64)
        return classes, bucket, e

    def __call__(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch, data, offsets in text_slices(batches):
            lines = Lines(data, offsets)
            if len(lines.row):
                held.append(self.entries(lines, np.asarray(batch.column(0).to_numpy(zero_copy_only=False), dtype=np.int64)))
                n += len(held[-1][2])
            if n >= SEND_WORDS:
                yield pack(held)
                held, n = [], 0
        if held:
            yield pack(held)


def pack(held: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    """One row for each bucket: its classes and their entries; of a class that several slices hold, the first line stays."""
    starts = np.cumsum([0] + [len(c) for c, _, _ in held])
    classes = np.concatenate([c for c, _, _ in held])
    bucket, e = np.concatenate([b for _, b, _ in held]), np.concatenate([x for _, _, x in held])
    e["at"] += np.repeat(starts[:-1], [len(x) for _, _, x in held]).astype(np.uint32)
    order = np.lexsort((classes["line"], classes["doc"], classes["cls"]))
    stays = np.zeros(len(classes), dtype=bool)
    stays[order[new_runs(classes["cls"][order])]] = True
    use = stays[e["at"]]
    bucket, e = bucket[use], e[use]
    order = np.argsort(bucket, kind="stable")
    bucket, e = bucket[order], e[order]
    cuts = np.flatnonzero(np.diff(bucket, prepend=-1, append=-1))
    rank = np.empty(len(classes), dtype=np.int64)
    rank[np.lexsort((classes["line"], classes["doc"]))] = np.arange(len(classes))
    by_rank = np.argsort(rank)
    out: tuple[list, list] = ([], [])
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        part = e[a:b][np.argsort(e["word"][a:b], kind="stable")]
        used, part["at"] = np.unique(rank[part["at"]], return_inverse=True)
        out[0].append(dense_bytes(classes[by_rank[used]], "doc"))
        out[1].append(dense_bytes(part, "word"))
    return pa.RecordBatch.from_arrays([pa.array(bucket[cuts[:-1]].astype(np.int32)), *(pa.array(x, pa.binary()) for x in out)], names=["bucket", "classes", "entries"])


def dense_bytes(rows: np.ndarray, ascending: str) -> bytes:
    """The rows column by column and byte by byte, the ascending column as steps."""
    parts = []
    for c in rows.dtype.names:
        if c in HASHED:
            parts.append(rows[c].tobytes())
        else:
            parts.append(by_bytes(np.diff(rows[c], prepend=rows[c].dtype.type(0)) if c == ascending else rows[c]))
    return b"".join(parts)


def from_dense(raw: list[bytes], dtype: np.dtype, ascending: str) -> np.ndarray:
    sizes = [len(x) // dtype.itemsize for x in raw]
    out, to = np.empty(sum(sizes), dtype=dtype), 0
    for x, k in zip(raw, sizes, strict=True):
        at = 0
        for c in dtype.names:
            wide = dtype[c].itemsize
            column = np.frombuffer(x, dtype[c], k, at) if c in HASHED else from_bytes(x[at : at + k * wide], dtype[c])
            out[c][to : to + k] = np.cumsum(column, dtype=dtype[c]) if c == ascending else column
            at += k * wide
        to += k
    return out


def unpack(group: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(classes, entries) of packed rows."""
    raw = group.column("classes").to_pylist(), group.column("entries").to_pylist()
    classes, e = from_dense(raw[0], CLASS, "doc"), from_dense(raw[1], ENTRY, "word")
    starts = np.cumsum([0] + [len(x) // CLASS.itemsize for x in raw[0]])
    e["at"] += np.repeat(starts[:-1], [len(x) // ENTRY.itemsize for x in raw[1]]).astype(np.uint32)
    return classes, e


def compatible(x: dict[str, np.ndarray], i: np.ndarray, j: np.ndarray, num: int, den: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, bits in which the sketches differ) of the pairs of one word that pass the filters; caps of n and pos only weaken the filters."""
    ni, nj = x["n"][i], x["n"][j]
    # length, and the word is in the shorter prefix of one of them
    keep = np.flatnonzero((den * np.minimum(ni, nj) >= num * np.maximum(ni, nj)) & (((x["pos"][i] | x["pos"][j]) & INDEXED) > 0) | (np.maximum(ni, nj) == 65535))
    for c in ("s1", "s2"):
        i, j, ni, nj = i[keep], j[keep], ni[keep], nj[keep]
        more = np.bitwise_count(x[c][i] ^ x[c][j]).astype(np.int32)
        apart = more if c == "s1" else apart[keep] + more
        keep = np.flatnonzero((apart * (num + den) <= (ni + nj) * (den - num)) | (np.maximum(ni, nj) == 65535))
    i, j, ni, nj, apart = i[keep], j[keep], ni[keep], nj[keep], apart[keep]
    place = np.minimum(ni - (x["pos"][i] & (INDEXED - 1)), nj - (x["pos"][j] & (INDEXED - 1))) >= -(-num * (ni + nj) // (num + den))
    keep = (place | (np.maximum(ni, nj) == 65535)) & ((x["cls"][i] != x["cls"][j]) | (x["s1"][i] != x["s1"][j]))
    return i[keep], j[keep], apart[keep].astype(np.int64)


def first_lines(classes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row of the first line of each class, classes in the order of these lines; the number of each row's class)."""
    rank = np.empty(len(classes), np.int64)
    rank[np.lexsort((classes["line"], classes["doc"]))] = np.arange(len(classes))
    key = classes["cls"] + mix64(classes["s1"])
    order = np.argsort(key)
    new = new_runs(key[order])
    if (~new & new_runs(classes["cls"][order], classes["s1"][order])).any():
        order = np.lexsort((classes["s1"], classes["cls"]))
        new = new_runs(classes["cls"][order], classes["s1"][order])
    head = np.flatnonzero(new)
    least = np.minimum.reduceat(rank[order], head) if len(head) else head
    number = np.empty(len(head), np.int64)
    number[np.argsort(least)] = np.arange(len(head))
    of = np.empty(len(classes), np.int64)
    of[order] = np.repeat(number, np.diff(np.append(head, len(order))))
    row = np.empty(len(classes), np.int64)
    row[rank] = np.arange(len(classes))
    return row[np.sort(least)], of


def meet(group: pa.Table, num: int, den: int) -> pa.Table:
    """The entries of one bucket to _MET rows.

    With a and b: b is the closest class that stands before a under one of its words and passes the filters; doc and line are those of the
    first line of a, as every entry of a class for a word comes to one bucket.  With a star: the members
    of a word some of whose classes have more than one such partner, or that has too many classes; dense ones may have more than one.
    """
    bucket = group.column("bucket")[0].as_py()
    classes, e = unpack(group)
    first, of = first_lines(classes)
    if len(first) >= 1 << 24:
        raise ValueError("a bucket holds too many classes")
    # one number for word, class and place: sorted, a word's classes stand in the order of their first lines, each once
    key = np.sort((e["word"].astype(np.uint64) << np.uint64(32)) | (of[e["at"]].astype(np.uint64) << np.uint64(8)) | e["pos"].astype(np.uint64))
    key = key[new_runs(key >> np.uint64(8))]
    word = key >> np.uint64(32)
    new = new_runs(word)
    # a word with one class pairs nothing
    key = key[~(new & np.append(new[1:], True))[: len(key)]]
    at = first[((key >> np.uint64(8)) & np.uint64((1 << 24) - 1)).astype(np.int64)]
    x = {c: classes[c][at] for c in ("cls", "s1", "s2", "doc", "line")}
    x |= {"word": key >> np.uint64(32), "pos": (key & np.uint64(255)).astype(np.int32), "n": classes["n"][at].astype(np.int32)}
    total = len(key)
    head = np.flatnonzero(new_runs(x["word"]))
    size = np.diff(np.append(head, total))
    start = np.repeat(head, size)
    large = np.repeat(size > IN_BUCKET, size) | (bucket >= HOT_BUCKET)
    far = np.int64(1) << 62
    best, partners, touched = np.full(total, far), np.zeros(total, np.int64), np.zeros(total, dtype=bool)
    open_ = np.flatnonzero((np.arange(total) > start) & ~large)
    step = np.zeros(len(open_), dtype=np.int64)
    while len(open_):
        left = open_ - start[open_] - step
        room = np.cumsum(np.minimum(left, 64)) <= STEP_PAIRS
        room[0] = True
        todo, chunk = open_[room], np.minimum(left[room], 64)
        j = np.repeat(todo, chunk)
        i = np.repeat(start[todo] + step[room] - np.cumsum(chunk) + chunk, chunk) + np.arange(len(j))
        i, j, apart = compatible(x, i, j, num, den)
        touched[i] = True
        np.minimum.at(best, j, (apart << 40) | i)
        np.add.at(partners, j, 1)
        step[room] += 64
        more = ~room | (left > 64)
        open_, step = open_[more], step[more]
    dense = (partners > 1) | large
    group_of = np.cumsum(new_runs(x["word"])) - 1
    crowded = (np.bincount(group_of, dense, minlength=len(head)) > 0)[group_of] if total else dense
    member = np.flatnonzero(crowded & (touched | (partners > 0) | large))
    got = np.flatnonzero(partners > 0)
    other = best[got] & ((1 << 40) - 1)
    order = np.lexsort((x["cls"][other], x["cls"][got]))
    order = order[new_runs(x["cls"][got[order]], x["cls"][other[order]])]
    got, other = got[order], other[order]
    apart = (best[got] >> 40).astype(np.int32)
    nothing = np.zeros(len(got), np.int64)
    pair = [x["cls"][got].view(np.int64), x["cls"][other].view(np.int64), apart, x["doc"][other], x["line"][other]]
    of_a = [nothing, nothing, nothing.astype(bool), x["doc"][got], x["line"][got], *[nothing] * 4]
    star = mix64((x["word"][member] << np.uint64(32)) + np.uint64(0 if bucket >= HOT_BUCKET else bucket)).view(np.int64)
    found = [star, x["cls"][member].view(np.int64), dense[member], x["doc"][member], x["line"][member], x["s1"][member].view(np.int64), x["s2"][member].view(np.int64), x["n"][member].astype(np.int32), x["pos"][member].astype(np.int32)]
    place = np.arange(len(got) + len(member))
    columns = [pa.array(np.concatenate([v, np.zeros(len(member), v.dtype)]), mask=place >= len(got)) for v in pair]
    columns += [pa.array(np.concatenate([u.astype(v.dtype), v]), mask=None if k in (3, 4) else place < len(got)) for k, (u, v) in enumerate(zip(of_a, found, strict=True))]
    return pa.table(columns, names=[c.split()[0] for c in _MET.split(", ")])


def picker(bits: np.ndarray) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(doc_id, text) to _LINE: the lines whose place among PICK_BITS is set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in text_slices(batches):
            ids = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), dtype=np.int64)
            breaks = np.flatnonzero(data == 10)
            inner = np.searchsorted(breaks, offsets)
            count = np.diff(inner) + 1
            row = np.repeat(np.arange(batch.num_rows), count)
            first = np.cumsum(count) - count
            number = np.arange(len(row)) - first[row]
            place = (ids[row] % PICK_BITS * 1_000_003 + number * 7_919) % PICK_BITS
            at = np.flatnonzero((bits[place >> 3] >> (place & 7).astype(np.uint8)) & 1)
            if not len(at):
                continue
            row, number = row[at], number[at]
            edge = np.append(breaks, 0)
            lo = np.where(number > 0, edge[inner[row] + number - 1] + 1, offsets[row])
            hi = np.where(number + 1 < count[row], edge[np.minimum(inner[row] + number, len(breaks))], offsets[row + 1])
            texts = [data[a:b].tobytes() for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
            whole = np.frombuffer(b"".join(texts), np.uint8)
            lines = Lines(whole, np.cumsum([0] + [len(t) for t in texts]))
            own = lines.row
            yield pa.RecordBatch.from_arrays([pa.array(ids[row[own]]), pa.array(number[own].astype(np.int32)), pa.array(lines.c1.view(np.int64)), pa.array(lines.c2.view(np.int64)), pa.array([texts[k] for k in own], pa.binary())], names=["doc_id", "line", "c1", "c2", "text"])

    return run


def word_sets(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(text, word) of the texts' distinct words, texts in order."""
    offsets = np.cumsum([0] + [len(t) for t in texts])
    data = np.frombuffer(b"".join(texts), np.uint8)
    starts, ends, first = find_words(data, offsets)
    of, words = np.repeat(np.arange(len(texts)), np.diff(first)), segment_hashes(data, starts, ends)
    order = np.lexsort((words, of))
    order = order[new_runs(of[order], words[order])]
    return of[order], words[order]


def similar(x: np.ndarray, y: np.ndarray, texts: list[bytes], num: int, den: int) -> np.ndarray:
    """Which pairs of texts are similar, by exact counts of words."""
    of, words = word_sets(texts)
    size = np.bincount(of, minlength=len(texts))
    common = common_counts(of, words, len(texts), x, y)
    return den * common >= num * (size[x] + size[y] - common)


def confirm(batches: Iterator[pa.RecordBatch], num: int, den: int) -> Iterator[pa.RecordBatch]:
    """(a, a2, ta, tb, doc, line) to the (c1, c2, s1, doc, line) of the lines ta that are similar to their tb; s1: half of the sketch."""
    for batch in batches:
        size = np.cumsum([len(a) + len(b) for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)])
        at = 0
        while at < batch.num_rows:
            to = max(int(np.searchsorted(size, (size[at - 1] if at else 0) + STEP_BYTES, side="right")), at + 1)
            part = batch.slice(at, to - at)
            # pair by pair side by side: the words of a pair are sorted together, so that common ones are neighbours
            of, words = word_sets([t for pair in zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True) for t in pair])
            sketch = parity_of(words, of, 2 * part.num_rows)[::2, 0]
            order = np.lexsort((words, of >> 1))
            pair, words = of[order] >> 1, words[order]
            both = np.bincount(pair[1:][(words[1:] == words[:-1]) & (pair[1:] == pair[:-1])], minlength=part.num_rows)
            fit = den * both >= num * (np.bincount(pair, minlength=part.num_rows) - both)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(sketch.copy().view(np.int64)), part.column(4), part.column(5)], names=["c1", "c2", "s1", "doc", "line"]).filter(pa.array(fit))
            at = to


def cell_pairs(cell: pa.Table, num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, row) of a cell's pairs that pass the filters; the second stands later and isn't settled."""
    x = {c: cell.column(c).to_numpy() for c in ("star", "cls", "doc", "line", "n", "pos", "block")}
    x |= {c: cell.column(c).to_numpy().view(np.uint64) for c in ("s1", "s2")} | {"n": x["n"].astype(np.int32), "pos": x["pos"].astype(np.int32)}
    asks = np.asarray(cell.column("asks").to_numpy(zero_copy_only=False), dtype=bool)
    across = cell.column("i")[0].as_py() != cell.column("j")[0].as_py()
    order = np.lexsort((x["line"], x["doc"], x["star"]))
    cuts = np.append(np.flatnonzero(new_runs(x["star"][order])), len(order))
    left, right = [], []
    for s, e in zip(cuts[:-1], cuts[1:], strict=True):
        rows = order[s:e]
        late = np.flatnonzero(asks[rows])
        for k in range(0, len(late), max(1, STEP_PAIRS // len(rows))):
            part = late[k : k + max(1, STEP_PAIRS // len(rows))]
            j = np.repeat(rows[part], part)
            i = rows[np.arange(len(j)) - np.repeat(np.cumsum(part) - part, part)]
            i, j, _ = compatible(x, i, j, num, den)
            if across:
                fit = x["block"][i] != x["block"][j]
                i, j = i[fit], j[fit]
            left.append(i)
            right.append(j)
    none = [np.zeros(0, np.int64)]
    return np.concatenate(left or none), np.concatenate(right or none)


def needed(cell: pa.Table, num: int, den: int) -> pa.Table:
    """(star, i, j, cls, doc, line): whose line the cell needs."""
    i, j = cell_pairs(cell, num, den)
    return cell.select(["star", "i", "j", "cls", "doc", "line"]).take(pa.array(np.unique(np.concatenate([i, j]))))


def settle(cell: pa.Table, num: int, den: int) -> pa.Table:
    """(c1, c2) of the cell's classes that an earlier one resembles."""
    i, j = cell_pairs(cell, num, den)
    key = np.stack([cell.column(c).to_numpy() for c in ("cls", "c2")])
    _, at, of = np.unique(key, axis=1, return_index=True, return_inverse=True)
    texts = cell.column("text").take(pa.array(at)).to_pylist()
    fit = similar(of.ravel()[i], of.ravel()[j], texts, num, den) if len(i) else np.zeros(0, dtype=bool)
    rows = np.unique(j[fit])
    return pa.table({"c1": key[0][rows], "c2": key[1][rows]})


def _place(doc: Column, line: Column) -> Column:
    return F.pmod(F.pmod(doc, F.lit(PICK_BITS)) * 1_000_003 + line.cast("long") * 7_919, F.lit(PICK_BITS))


def find_similar_lines(docs: DataFrame, num: int = 75, den: int = 100) -> DataFrame:
    """(doc_id, line, c1, c2, removed) of every line with a word; c1 and c2 tell lines of other words apart."""
    lines, gone = _judged_lines(docs, num, den)
    spread = lines.select("doc_id", F.explode(F.arrays_zip("lines", "c1", "c2", "removed")).alias("l"))
    return spread.select("doc_id", F.col("l.lines").alias("line"), "l.c1", "l.c2", "l.removed")


def _judged_lines(docs: DataFrame, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, lines, c1, c2, removed: arrays, a row for each row of docs that has a doc_id; the (c1, c2) that an earlier line resembles)."""
    spark = docs.sparkSession
    known = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    listed = cut_lineage(known.mapInArrow(list_lines, _LISTED))
    lines = listed.where("segment IS NULL").select("doc_id", "lines", "c1", "c2")
    spread = lines.select("doc_id", F.explode(F.arrays_zip("lines", "c1", "c2")).alias("l"))
    first = cut_lineage(spread.groupBy("l.c1", "l.c2").agg(F.min(F.struct("doc_id", "l.lines")).alias("f")).select("c1", "c2", F.col("f.doc_id").alias("doc"), F.col("f.lines").alias("line")))
    # one row for each segment of the counters
    parts = listed.where("segment IS NOT NULL").select("segment", "cells", "counts").groupBy("segment").applyInArrow(add_counters, "segment int, levels binary").collect()
    levels = np.zeros(1 << COUNTER_BITS, dtype=np.uint8)
    for r in parts:
        levels[r["segment"] * SEGMENT : (r["segment"] + 1) * SEGMENT] = np.frombuffer(r["levels"], np.uint8)
    words = listed.agg(F.coalesce(F.sum("n_words"), F.lit(0))).first()[0]
    buckets = int(words * (den - num) / den // BUCKET_WORDS) + 1
    shared = spark.sparkContext.broadcast(levels)
    packed = known.mapInArrow(lambda b: Prefixes(shared.value, num, den, buckets)(b), _PACKED)
    met = cut_lineage(packed.groupBy("bucket").applyInArrow(lambda g: meet(g, num, den), _MET))

    def texts_of(classes: DataFrame) -> DataFrame:
        """(c1, c2, doc, line, text) of the first lines (c1, doc, line) of classes."""
        wanted = cut_lineage(classes.distinct())
        held = wanted.select((_place(F.col("doc"), F.col("line")) + 1).alias("p")).groupBy(F.bitmap_bucket_number("p").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bits")).collect()
        bits = np.zeros(PICK_BITS // 8, dtype=np.uint8)
        for r in held:
            # bitmap buckets count from 1
            bits[(r["k"] - 1) * 4096 : r["k"] * 4096] = np.frombuffer(r["bits"], np.uint8)
        there = spark.sparkContext.broadcast(bits)
        picked = known.mapInArrow(lambda b: picker(there.value)(b), _LINE)
        return cut_lineage(picked.join(wanted.withColumnRenamed("doc", "doc_id"), ["doc_id", "line", "c1"]).select("c1", "c2", F.col("doc_id").alias("doc"), "line", "text").dropDuplicates(["c1", "c2"]))

    pairs = cut_lineage(met.where("a IS NOT NULL").select("a", "doc", "line", "b", "b_doc", "b_line", "apart").distinct())
    ends = F.explode(F.array(F.struct(F.col("a").alias("c1"), "doc", "line"), F.struct(F.col("b").alias("c1"), F.col("b_doc").alias("doc"), F.col("b_line").alias("line"))))
    texts = texts_of(pairs.select(ends.alias("e")).select("e.*"))
    ta = texts.select(F.col("c1").alias("a"), F.col("c2").alias("a2"), F.struct("doc", "line").alias("_fa"), F.col("text").alias("ta"))
    tb = texts.select(F.col("c1").alias("b"), F.struct("doc", "line").alias("_fb"), F.col("text").alias("tb"))

    def confirmed(some: DataFrame) -> DataFrame:
        both = some.select("a", "b").join(ta, "a").join(tb, "b").where("_fb < _fa").select("a", "a2", "ta", "tb", "_fa.doc", "_fa.line")
        return both.mapInArrow(lambda b: confirm(b, num, den), "c1 long, c2 long, s1 long, doc long, line int").distinct()

    # the closest of the earlier classes that the words propose, and the others only where that one isn't similar
    closest = cut_lineage(pairs.groupBy("a", "doc", "line").agg(F.min(F.struct("apart", "b", "b_doc", "b_line")).alias("m")).select("a", "doc", "line", "m.b"))
    gone = cut_lineage(confirmed(closest))
    settled = gone.select(F.col("c1").alias("a"), "doc", "line")
    rest = cut_lineage(pairs.join(closest, ["a", "doc", "line", "b"], "left_anti").join(settled, ["a", "doc", "line"], "left_anti"))
    if not rest.isEmpty():
        gone = cut_lineage(gone.union(confirmed(rest)).distinct())

    # what that leaves open meets all members of its stars
    member = met.where("star IS NOT NULL").drop("a", "b", "b_doc", "b_line")
    asking = cut_lineage(member.where("dense").select("star", "cls", "s1").distinct().join(gone.select(F.col("c1").alias("cls"), "s1"), ["cls", "s1"], "left_anti"))
    if not asking.isEmpty():
        stars = asking.select("star").distinct()
        # a hot word's class may have come from several buckets' tasks, each with its own first line
        least = F.min(F.struct("doc", "line", "s2", "n", "pos")).alias("m")
        members = cut_lineage(member.join(stars, "star", "left_semi").groupBy("star", "cls", "s1").agg(least).select("star", "cls", "s1", "m.*").join(asking.withColumn("asks", F.lit(True)), ["star", "cls", "s1"], "left").withColumn("asks", F.coalesce("asks", F.lit(False))))
        totals = members.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
        cells = int(totals[0] // BLOCK_MEMBERS + totals[1] // BLOCK_WORDS) + 1
        blocks = members.groupBy("star").agg((1 + F.floor(F.count("*") / BLOCK_MEMBERS) + F.floor(F.sum("n") / BLOCK_WORDS)).alias("blocks"))
        placed = members.join(blocks, "star").withColumn("block", F.pmod(F.xxhash64("cls"), F.col("blocks"))).withColumn("_o", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
        large = F.col("blocks") > 1
        placed = placed.select("*", large.alias("large"), F.when(large, F.col("star")).otherwise(F.pmod(F.xxhash64("star"), F.lit(cells))).alias("cell"), F.least("block", "_o").alias("i"), F.greatest("block", "_o").alias("j")).drop("_o", "blocks")
        keys = ["large", "cell", "i", "j"]
        wanted = cut_lineage(placed.groupBy(*keys).applyInArrow(lambda g: needed(g, num, den), "star long, i long, j long, cls long, doc long, line int"))
        held = texts_of(wanted.select(F.col("cls").alias("c1"), "doc", "line")).select(F.col("c1").alias("cls"), "c2", "text")
        work = placed.join(wanted, ["star", "i", "j", "cls"], "left_semi").join(held, "cls")
        gone = cut_lineage(gone.select("c1", "c2").union(work.groupBy(*keys).applyInArrow(lambda g: settle(g, num, den), "c1 long, c2 long")).distinct())
    # the lines that stay are the first ones of the classes that stay
    stay = first.join(gone, ["c1", "c2"], "left_anti").groupBy(F.col("doc").alias("_d")).agg(F.collect_list(F.struct("line", "c1", "c2")).alias("_stay"))
    own = F.transform(F.arrays_zip("lines", "c1", "c2"), lambda l: F.struct(l["lines"].alias("line"), l["c1"].alias("c1"), l["c2"].alias("c2")))  # noqa: E741
    joined = lines.join(stay, F.col("doc_id") == F.col("_d"), "left")
    kept = F.transform(own, lambda l: ~F.array_contains(F.coalesce("_stay", F.array().cast("array<struct<line:int,c1:bigint,c2:bigint>>")), l))  # noqa: E741
    return joined.select("doc_id", "lines", "c1", "c2", kept.alias("removed")), gone


def without_similar_lines(docs: DataFrame, **options) -> DataFrame:
    """docs with the lines taken out that stand earlier in a similar form; versions of one doc_id each lose their own lines."""
    gone = find_similar_lines(docs, **options).where("removed").groupBy(F.col("doc_id").alias("_d")).agg(F.collect_set("line").alias("_gone"))
    kept = F.filter(F.split("text", "\n", -1), lambda _, i: ~F.array_contains(F.col("_gone"), i))
    return docs.join(gone, F.col("doc_id").cast("long") == F.col("_d"), "left").withColumn("text", F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))).drop("_d", "_gone")


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found, _ = _judged_lines(docs, 75, 100)
    removed = F.filter(F.arrays_zip("lines", "removed"), lambda x: x["removed"])
    out = found.select("doc_id", F.size("lines").cast("long").alias("n_lines"), F.size(removed).cast("long").alias("n_removed"), F.array_join(F.transform(removed, lambda x: x["lines"].cast("string")), ",").alias("removed_lines"))
    nowhere = docs.where("doc_id IS NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(0).cast("long").alias("n_lines"), F.lit(0).cast("long").alias("n_removed"), F.lit("").alias("removed_lines"))
    return out.union(nowhere)
