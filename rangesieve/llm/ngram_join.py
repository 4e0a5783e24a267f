"""Exact n-gram Jaccard join: the shingle universe is cut into segments, and similar sets share one segment's subset.

Sets of one size band spread their shingles over the band's segments by hash.  Two sets of sizes r >= s that reach the threshold
differ in at most H = (r + s)(1 - t)/(1 + t) shingles, so of any H + 1 segments one is equal in both; a segment for which the
one-deletion neighbourhoods are searched too counts twice, since it tolerates one difference.  Each set is indexed in all segments
of its band and, as the larger side, probes the cheapest sufficient units in its own and the next smaller band, by the frequency
of their subsets where it was signed.  Segments without shingles are the last resort, and are then keyed by exact set size.

Equal sets are one class before anything is compared.  A group of signature buckets yields stars: its members, each with the signatures that it
asks for and has, around the smallest probing set.  A pair of classes belongs to the smallest star in which one asks for what the other
has, and is looked at there alone.  Large stars are cut into blocks, and each pair of blocks is one cell of work; parity sketches rule
out most pairs of a cell, and exact counts on whole texts decide the others.  So every link is verified and counted, while what leaves
a cell is a count for each member and a spanning forest of the cell's links, not the pairs.

Defined results: a null or wordless text has an empty set and links with nothing; fewer words than the shingle width make one
shingle; rows of one doc_id are one document with the first of its texts by hash; a null doc_id gives a row of its own component,
null, and no link; ties go to the smallest doc_id; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, cut_lineage, sifted, table
from .textkernel import LOWER, find_words, mix64, run_hashes, segment_hashes, text_slices, window_starts

#: Shingles whose signatures are sorted in one bucket; bounds the memory of that step.
BUCKET_SHINGLES = 1_000_000
#: Groups that buckets meet in, and buckets of a group at most: a pair that shares signatures in many buckets comes out once for each group.
GROUPS, GROUP_BUCKETS = 32, 8
#: Shingles whose corpus frequency is known when segments are priced; all others count as rare.
FREQUENT_SHINGLES = 1 << 17
#: Bands of sets up to this size index and probe one-deletion neighbourhoods in all segments, larger ones in none.
DELETIONS_UP_TO = 128
#: Segments of a band over the most that its sets can differ in: the choice that a probing set has.
SLACK = 1.8
#: Members and shingles of a cell's block; more members make more cells, none is left out.
BLOCK_MEMBERS, BLOCK_SHINGLES = 1024, 400_000
#: Words of sketches or bitmaps that are compared in one step.
STEP_WORDS = 1 << 21
INDEX, PROBE = np.uint64(1), np.uint64(2)
_ROW_SALT = np.uint64(0x9E3779B97F4A7C15)
_SECOND = np.uint64(0xC2B2AE3D27D4EB4F)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of each row's distinct word shingles, A-Z lower-cased, rows in order."""
    data = LOWER[data]
    starts, ends, first = find_words(data, offsets)
    words = segment_hashes(data, starts, ends)
    begin, row = window_starts(first, width)
    count = np.diff(first)
    short = np.flatnonzero((count > 0) & (count < width))
    h = np.concatenate([run_hashes(words, begin, begin + width), run_hashes(words, first[short], first[short + 1])])
    row = np.concatenate([row, short])
    at = np.unique(mix64(h + row.astype(np.uint64) * _ROW_SALT), return_index=True)[1]
    at = at[np.argsort(row[at], kind="stable")]
    return row[at], h[at]


def describe(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, text_hash, text) to (doc_id, text_hash, n, s1, s2, sketch, shared): the size, a 128-bit hash and a parity sketch of each set.

    shared, in a slice's first row: its shingles that stand in more than one of its sets, with their counts.
    """
    for rows, data, offsets in text_slices(batches):
        row, h = shingle_sets(data, offsets, width)
        n, s1, s2 = _set_hashes(rows.num_rows, row, h)
        word, count = np.unique(h, return_counts=True)
        shared = np.stack([word[count > 1].view(np.int64), count[count > 1]]).tobytes()
        yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(n), pa.array(s1.view(np.int64)), pa.array(s2.view(np.int64)), pa.array(parity_sketches(rows.num_rows, row, h), pa.binary()), pa.array([shared] + [None] * (rows.num_rows - 1), pa.binary())], names=["doc_id", "text_hash", "n", "s1", "s2", "sketch", "shared"])


def spread_shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(shared) to (shingle, n)."""
    for batch in batches:
        for raw in batch.column(0).to_pylist():
            word, count = np.frombuffer(raw, np.int64).reshape(2, -1)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(count)], names=["shingle", "n"])


def _set_hashes(rows: int, row: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    at = np.searchsorted(row, np.arange(rows + 1))
    out = []
    for x in (mix64(h), mix64(h ^ _SECOND)):
        total = np.zeros(len(x) + 1, dtype=np.uint64)
        np.cumsum(x, out=total[1:])
        out.append(total[at[1:]] - total[at[:-1]])
    return np.diff(at), *out


def bands(num: int, den: int, largest: int) -> tuple[np.ndarray, np.ndarray]:
    """(least set size, number of segments) of each band for the threshold num/den."""
    least, parts = [1], []
    while least[-1] <= largest:
        up = least[-1] * den // num
        parts.append(int(np.ceil(SLACK * (most_differences(up, up, num, den) + 1))))
        least.append(up + 1)
    return np.array(least[:-1] or [1]), np.array(parts or [1])


def most_differences(r: int, s: int, num: int, den: int) -> int:
    """Largest symmetric difference of sets of sizes r and s at a similarity of num/den."""
    return (r + s) * (den - num) // (den + num)


def parity_sketches(rows: int, row: np.ndarray, h: np.ndarray) -> list[bytes]:
    """For each set, bit i tells whether an odd number of its shingles falls on i; twice as many bits as shingles, a power of two.

    Sets whose sketches, folded to one length, differ in d bits differ in d shingles at least.
    """
    n = np.bincount(row, minlength=rows)
    bits = np.maximum(64, 1 << np.ceil(np.log2(np.maximum(2 * n, 2))).astype(np.int64))
    base = np.cumsum(bits) - bits
    at = base[row] + (mix64(h ^ np.uint64(0x5851F42D4C957F2D)) % bits[row].astype(np.uint64)).astype(np.int64)
    odd = np.packbits((np.bincount(at, minlength=int(bits.sum())) & 1).astype(np.uint8), bitorder="little")
    return [odd[b // 8 : (b + k) // 8].tobytes() for b, k in zip(base.tolist(), bits.tolist(), strict=True)]


def least_differences(a: bytes, b: bytes) -> int:
    """A lower bound for the symmetric difference of two sets, from their sketches."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    if len(x) < len(y):
        x, y = y, x
    return int(np.bitwise_count(np.bitwise_xor.reduce(x.reshape(-1, len(y)), axis=0) ^ y).sum())


def _tag(band: np.ndarray, segment: np.ndarray) -> np.ndarray:
    return mix64(band.astype(np.uint64) * np.uint64(1 << 32) + segment.astype(np.uint64) + np.uint64(1))


def sign(sizes: np.ndarray, row: np.ndarray, h: np.ndarray, num: int, den: int, often: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(signature with role bits, row) of sets given as (row, hash); often: in how many sets each shingle is known to stand."""
    least, parts = bands(num, den, int(sizes.max(initial=1)) * 2)
    band = np.searchsorted(least, sizes, side="right") - 1
    sigs, rows = [], []
    for lower in (False, True):
        wanted = sizes > 0
        at = band - lower
        if lower:
            wanted &= (band > 0) & (-(-sizes * num // den) < least[np.maximum(band, 0)])
        at = np.maximum(at, 0)
        peer = np.minimum(sizes, least[at + 1] - 1 if len(least) > at.max(initial=0) + 1 else sizes) if lower else sizes
        need = np.where(wanted, (sizes + peer) * (den - num) // (den + num) + 1, 0)
        m = np.where(wanted, parts[at], 0)
        base = np.cumsum(m) - m
        use = wanted[row]
        r, x, known = row[use], h[use], often[use]
        if not len(r):
            continue
        segment = base[r] + ((x >> np.uint64(20)) % m[r].astype(np.uint64)).astype(np.int64)
        total = int(m.sum())
        inner = mix64(x ^ _SECOND)
        subset = np.zeros(total, dtype=np.uint64)
        np.add.at(subset, segment, inner)
        count = np.bincount(segment, minlength=total)
        owner = np.repeat(np.arange(len(m)), m)
        tag = _tag(at[owner], np.arange(total) - base[owner])
        empty = count == 0
        sig = mix64(subset + tag)
        sig[empty] = mix64(tag[empty] ^ mix64(sizes[owner[empty]].astype(np.uint64)))
        sig &= ~np.uint64(3)

        full = np.flatnonzero(~empty)
        _, inverse, here = np.unique(sig[full], return_inverse=True, return_counts=True)
        # sets that share a subset share all of it: the rarest shingle bounds their number
        rarest = np.full(total, np.iinfo(np.int64).max)
        np.minimum.at(rarest, segment, known)
        cost = np.maximum(here[inverse].astype(np.int64), rarest[full])
        doubled = full[(least[at[owner[full]]] * den // num <= DELETIONS_UP_TO) & (count[full] >= 2)]
        unit = np.concatenate([full, doubled])
        price = np.concatenate([2 * cost, 8 * cost[np.searchsorted(full, doubled)] + 1])
        order = np.lexsort((price, owner[unit]))
        unit, second = unit[order], (np.arange(len(unit)) >= len(full))[order]
        have = np.bincount(owner[unit], minlength=len(m))
        place = np.arange(len(unit)) - np.repeat(np.cumsum(have) - have, have)
        chosen = place < need[owner[unit]]
        probed = np.zeros(total, dtype=bool)
        probed[unit[chosen & ~second]] = True
        widened = np.zeros(total, dtype=bool)
        widened[unit[chosen & second]] = True

        emit = probed if lower else np.ones(total, dtype=bool)
        out = sig[emit] | np.where(probed[emit], PROBE, np.uint64(0)) | (np.uint64(0) if lower else INDEX)
        sigs.append(out)
        rows.append(owner[emit])
        of_small = np.zeros(total, dtype=bool)
        of_small[doubled] = True
        pick = widened[segment] if lower else of_small[segment]
        if pick.any():
            s = segment[pick]
            cut = mix64(subset[s] - inner[pick] + tag[s]) & ~np.uint64(3)
            sigs.append(cut | np.where(widened[s], PROBE, np.uint64(0)) | (np.uint64(0) if lower else INDEX))
            rows.append(owner[s])
        for i in np.flatnonzero(have < need):
            gone = base[i] + np.flatnonzero(empty[base[i] : base[i] + m[i]])
            peers = np.arange(-(-int(sizes[i]) * num // den), int(sizes[i]) + 1).astype(np.uint64)
            sigs.append((mix64(tag[gone][:, None] ^ mix64(peers)[None, :]).ravel() & ~np.uint64(3)) | PROBE)
            rows.append(np.full(len(gone) * len(peers), i))
    if not sigs:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(sigs), np.concatenate(rows)


def deal(sigs: np.ndarray, rows: np.ndarray, ids: np.ndarray, buckets: int) -> pa.RecordBatch:
    """One packed row for each bucket that has signatures: its document ids, signatures, and each one's place in the ids."""
    bucket = ((sigs >> np.uint64(32)) % np.uint64(buckets)).astype(np.int32)
    order = np.argsort(bucket, kind="stable")
    bucket, sigs, rows = bucket[order], sigs[order], rows[order]
    cuts = np.flatnonzero(np.diff(bucket, prepend=-1, append=-1))
    packed: tuple[list, list, list] = ([], [], [])
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        used, place = np.unique(rows[a:b], return_inverse=True)
        for to, x in zip(packed, (ids[used], sigs[a:b], place.astype(np.uint16)), strict=True):
            to.append(x.tobytes())
    return pa.RecordBatch.from_arrays([pa.array(bucket[cuts[:-1]], pa.int32()), *(pa.array(x, pa.binary()) for x in packed)], names=["bucket", "ids", "sigs", "rows"])


def signer(width: int, num: int, den: int, buckets: int, frequent: np.ndarray, counts: np.ndarray) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in text_slices(batches):
            row, h = shingle_sets(data, offsets, width)
            n, s1, s2 = _set_hashes(batch.num_rows, row, h)
            # equal sets of a slice are signed once; their class is known from their hashes
            new = np.zeros(batch.num_rows, dtype=bool)
            new[np.unique(mix64(s1 + mix64(s2 + n.astype(np.uint64))), return_index=True)[1]] = True
            keep = new[row]
            often = np.ones(int(keep.sum()), dtype=np.int64)
            if len(frequent):
                at = np.minimum(np.searchsorted(frequent, h[keep]), len(frequent) - 1)
                often = np.where(frequent[at] == h[keep], counts[at], 1)
            sigs, rows = sign(np.where(new, n, 0), row[keep], h[keep], num, den, often)
            if len(sigs):
                yield deal(sigs, rows, np.asarray(batch.column(0).to_numpy(zero_copy_only=False), dtype=np.int64), buckets)

    return run


def group_count(buckets: int) -> int:
    """As many groups at any size until they would hold more than GROUP_BUCKETS buckets."""
    return min(buckets, max(GROUPS, -(-buckets // GROUP_BUCKETS)))


def stars(group: pa.Table) -> pa.Table:
    """Candidate pairs of a group of buckets, each once: (doc, centre, asks, has).

    asks and has are 64-bit masks of the signatures that doc probes there, and of all it has there: two documents of a star can be
    needed as a pair only if one asks for what the other has.
    """
    bucket, parts = group.column("bucket").to_numpy(), []
    for b in np.unique(bucket):
        some = group.take(pa.array(np.flatnonzero(bucket == b)))
        packs = list(zip(*(some.column(c).to_pylist() for c in ("ids", "sigs", "rows")), strict=True))
        sigs = np.concatenate([np.frombuffer(s, np.uint64) for _, s, _ in packs])
        docs = np.concatenate([np.frombuffer(i, np.int64)[np.frombuffer(r, np.uint16)] for i, _, r in packs])
        del some, packs
        parts.append(_merged(*_bucket_stars(sigs, docs)))
    docs, centre, asks, has = _merged(*(np.concatenate(c) for c in zip(*parts, strict=True)))
    return pa.table({"doc": docs, "centre": centre, "asks": asks.view(np.int64), "has": has.view(np.int64)})


def _merged(docs: np.ndarray, centre: np.ndarray, asks: np.ndarray, has: np.ndarray) -> tuple[np.ndarray, ...]:
    """One row for each (doc, centre), its masks united."""
    if not len(docs):
        return docs, centre, asks, has
    order = np.lexsort((centre, docs))
    docs, centre = docs[order], centre[order]
    new = np.ones(len(docs), dtype=bool)
    new[1:] = (docs[1:] != docs[:-1]) | (centre[1:] != centre[:-1])
    at = np.flatnonzero(new)
    return docs[at], centre[at], np.bitwise_or.reduceat(asks[order], at), np.bitwise_or.reduceat(has[order], at)


def _bucket_stars(sigs: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, ...]:
    """(doc, centre, asks, has) of a bucket, a row for each signature that doc shares with a centre."""
    order = np.argsort(sigs)
    sigs, docs = sigs[order], docs[order]
    roles, sigs = sigs & np.uint64(3), sigs >> np.uint64(2)
    head = np.flatnonzero(np.diff(sigs, prepend=sigs[:1] + np.uint64(1)))
    size = np.diff(np.append(head, len(sigs)))
    wide = np.repeat(size > 1, size)
    sigs, docs, roles, size = sigs[wide], docs[wide], roles[wide], size[size > 1]
    if not len(sigs):
        return docs, docs, sigs, sigs
    head = np.cumsum(size) - size
    none = np.iinfo(np.int64).max
    probes = (roles & PROBE) > 0
    centre = np.minimum.reduceat(np.where(probes, docs, none), head)
    met = (centre < none) & (np.maximum.reduceat(roles & INDEX, head) > 0)
    centre, met = np.repeat(centre, size), np.repeat(met, size) & (docs != np.repeat(centre, size))
    has = np.uint64(1) << (mix64(sigs[met]) >> np.uint64(58))
    return docs[met], centre[met], np.where(probes[met], has, np.uint64(0)), has


def _meet(asks: np.ndarray, has: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return ((asks[i] & has[j]) | (asks[j] & has[i])) != 0


def _sketches_apart(sketches: list[bytes], i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """least_differences of each pair of sketches."""
    words = np.array([len(s) // 8 for s in sketches])
    out = np.zeros(len(i), dtype=np.int64)
    long_, short = np.where(words[i] >= words[j], i, j), np.where(words[i] >= words[j], j, i)
    key = words[long_] * (1 << 32) + words[short]
    for k in np.unique(key).tolist():
        at, w, v = np.flatnonzero(key == k), k >> 32, k & 0xFFFFFFFF
        x, y = np.unique(long_[at], return_inverse=True), np.unique(short[at], return_inverse=True)
        wide = np.frombuffer(b"".join(sketches[m] for m in x[0]), np.uint64).reshape(len(x[0]), w // v, v)
        folded, own = np.bitwise_xor.reduce(wide, axis=1), np.frombuffer(b"".join(sketches[m] for m in y[0]), np.uint64).reshape(-1, v)
        step = max(1, STEP_WORDS // v)
        for c in range(0, len(at), step):
            out[at[c : c + step]] = np.bitwise_count(folded[x[1][c : c + step]] ^ own[y[1][c : c + step]]).sum(axis=1, dtype=np.int64)
    return out


def candidate_pairs(cell: pa.Table, num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a cell that form a pair to be verified: a pair of classes comes out in one star of one cell only."""
    star, block, asks, has, n = (cell.column(c).to_numpy() for c in ("star", "block", "asks", "has", "n"))
    across = cell.column("i")[0].as_py() != cell.column("j")[0].as_py()
    lists = [cell.column(c).combine_chunks() for c in ("stars", "all_asks", "all_has")]
    starts = lists[0].offsets.to_numpy()
    every, every_asks, every_has = (x.values.to_numpy() for x in lists)
    order = np.argsort(star, kind="stable")
    cuts = np.flatnonzero(np.diff(star[order], prepend=star[order[:1]] + 1, append=star[order[-1:]] + 1))
    left, right = [], []
    for s, e in zip(cuts[:-1], cuts[1:], strict=True):
        rows = order[s:e]
        if across:
            low, high = rows[block[rows] == block[rows].min()], rows[block[rows] == block[rows].max()]
            if not len(low) or block[low[0]] == block[high[0]]:
                continue
            i, j = np.repeat(low, len(high)), np.tile(high, len(low))
        else:
            x, y = np.triu_indices(len(rows), 1)
            i, j = rows[x], rows[y]
        fit = _meet(asks, has, i, j) & (den * np.minimum(n[i], n[j]) >= num * np.maximum(n[i], n[j]))
        i, j = i[fit], j[fit]
        if not len(i):
            continue
        # pairs that meet in a smaller star belong to that one
        owner = np.repeat(rows, starts[rows + 1] - starts[rows])
        place = np.concatenate([np.arange(starts[r], starts[r + 1]) for r in rows])
        smaller = every[place] < star[rows[0]]
        owner, place = owner[smaller], place[smaller]
        if len(place):
            by_star = np.argsort(every[place], kind="stable")
            owner, place = owner[by_star], place[by_star]
            head = np.flatnonzero(np.diff(every[place], prepend=every[place[:1]] + 1, append=every[place[-1:]] + 1))
            runs = [(a, b) for a, b in zip(head[:-1], head[1:], strict=True) if b - a > 1]
            there_asks, there_has = np.zeros(len(star), np.int64), np.zeros(len(star), np.int64)
            for a, b in sorted(runs, key=lambda r: r[0] - r[1]):
                there_asks[owner[a:b]], there_has[owner[a:b]] = every_asks[place[a:b]], every_has[place[a:b]]
                own = ~_meet(there_asks, there_has, i, j)
                there_asks[owner[a:b]] = there_has[owner[a:b]] = 0
                i, j = i[own], j[own]
                if not len(i):
                    break
        left.append(i)
        right.append(j)
    if not left:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    i, j = np.concatenate(left), np.concatenate(right)
    fit = _sketches_apart(cell.column("sketch").to_pylist(), i, j) * (den + num) <= (n[i] + n[j]) * (den - num)
    return i[fit], j[fit]


def needed(cell: pa.Table, num: int, den: int) -> pa.Table:
    """(star, i, j, member): whose text the cell needs."""
    i, j = candidate_pairs(cell, num, den)
    return cell.select(["star", "i", "j", "member"]).take(pa.array(np.unique(np.concatenate([i, j]))))


def linked_pairs(cell: pa.Table, width: int, num: int, den: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, row, common, united) of the cell's pairs that reach the threshold, by exact counts of shingles."""
    i, j = candidate_pairs(cell, num, den)
    if not len(i):
        return i, j, i, j
    members, text_of = np.unique(cell.column("member").to_numpy(), return_inverse=True)
    of_member = np.zeros(len(members), dtype=np.int64)
    of_member[text_of] = np.arange(cell.num_rows)
    raw = [t.encode() for t in cell.column("text").take(pa.array(of_member)).to_pylist()]
    row, h = shingle_sets(np.frombuffer(b"".join(raw), dtype=np.uint8), np.cumsum([0] + [len(t) for t in raw]), width)
    size = np.bincount(row, minlength=len(members))
    _, number, count = np.unique(h, return_inverse=True, return_counts=True)
    shared = count > 1
    bit = (np.cumsum(shared) - 1)[number]
    row, bit = row[shared[number]], bit[shared[number]]
    bits = np.zeros((len(members), (int(shared.sum()) + 63) // 64 + 1), dtype=np.uint64)
    np.bitwise_or.at(bits, (row, bit >> 6), np.uint64(1) << (bit & 63).astype(np.uint64))
    x, y = text_of[i], text_of[j]
    common = np.zeros(len(i), dtype=np.int64)
    step = max(1, STEP_WORDS // bits.shape[1])
    for c in range(0, len(i), step):
        common[c : c + step] = np.bitwise_count(bits[x[c : c + step]] & bits[y[c : c + step]]).sum(axis=1, dtype=np.int64)
    united = size[x] + size[y] - common
    fit = den * common >= num * united
    return i[fit], j[fit], common[fit], united[fit]


def list_links(cell: pa.Table, width: int, num: int, den: int) -> pa.Table:
    """(a, b, common, united) of the cell's links."""
    i, j, common, united = linked_pairs(cell, width, num, den)
    member = cell.column("member").to_numpy()
    return pa.table({"a": np.minimum(member[i], member[j]), "b": np.maximum(member[i], member[j]), "common": common, "united": united})


def count_links(cell: pa.Table, width: int, num: int, den: int) -> pa.Table:
    """(a, b, n): with b null, n documents of other classes link to class a in this cell; else a and b are in one component."""
    i, j, _, _ = linked_pairs(cell, width, num, den)
    member, root = np.unique(cell.column("member").to_numpy(), return_inverse=True)
    x, y = root[i], root[j]
    weight = np.zeros(len(member), dtype=np.int64)
    weight[root] = cell.column("weight").to_numpy()
    linked = np.zeros(len(member), dtype=np.int64)
    np.add.at(linked, x, weight[y])
    np.add.at(linked, y, weight[x])
    label = np.arange(len(member))
    while True:
        least = np.minimum(label[x], label[y])
        if (least == label[x]).all() and (least == label[y]).all():
            break
        np.minimum.at(label, x, least)
        np.minimum.at(label, y, least)
        label = label[label]
    some, tied = np.flatnonzero(linked), np.flatnonzero(label != np.arange(len(member)))
    b = pa.array(np.concatenate([member[some], member[label[tied]]]), mask=np.arange(len(some) + len(tied)) < len(some))
    return pa.table({"a": np.concatenate([member[some], member[tied]]), "b": b, "n": np.concatenate([linked[some], np.zeros(len(tied), np.int64)])})


def join_ngrams(docs: DataFrame, num: int = 75, den: int = 100, width: int = 5) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, class_id, component_id, n_links of every document; a, b, common, united of all linked pairs of classes).

    n_links: other documents of similarity num/den or more, those with an equal set among them.  Classes stand for their documents in
    the second result, which is computed when it is read.
    """
    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"), F.coalesce("text", F.lit("")).alias("text"))
    sets = cut_lineage(given.select("doc_id", "text_hash", "text").mapInArrow(lambda b: describe(b, width), "doc_id long, text_hash long, n long, s1 long, s2 long, sketch binary, shared binary"))
    known = sets.where("doc_id is not null")
    first = known.groupBy("doc_id").agg(F.min_by(F.struct("n", "s1", "s2", "text_hash"), "text_hash").alias("s")).select("doc_id", "s.*")
    classes = first.where("n > 0").groupBy("n", "s1", "s2").agg(F.min("doc_id").alias("class_id"))
    member = cut_lineage(first.join(classes, ["n", "s1", "s2"], "left").select("doc_id", "n", "text_hash", F.coalesce("class_id", "doc_id").alias("class_id")))
    heads = member.where("doc_id = class_id").select(F.col("doc_id").alias("_i"), F.col("text_hash").alias("_t"))
    sketches = known.join(heads, (F.col("doc_id") == F.col("_i")) & (F.col("text_hash") == F.col("_t"))).select("doc_id", "n", "sketch").dropDuplicates(["doc_id"])

    shingles = sets.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    buckets = int(shingles // BUCKET_SHINGLES) + 1
    # FREQUENT_SHINGLES rows at most
    top = sets.where("shared IS NOT NULL").select("shared").mapInArrow(spread_shared, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "shingle").limit(FREQUENT_SHINGLES).toArrow()
    word, often = top.column("shingle").to_numpy().view(np.uint64), top.column("n").to_numpy()
    order = np.argsort(word)
    # texts of a repeated doc_id that don't count must not stand for an equal set of another document
    idle = cut_lineage(known.join(first.select(F.col("doc_id").alias("_i"), F.col("text_hash").alias("_t")), (F.col("doc_id") == F.col("_i")) & (F.col("text_hash") != F.col("_t"))).select("doc_id", "text_hash").distinct())
    packed = given.where("doc_id is not null").join(idle, ["doc_id", "text_hash"], "left_anti").select("doc_id", "text").mapInArrow(signer(width, num, den, buckets, word[order], often[order]), "bucket int, ids binary, sigs binary, rows binary")
    found = packed.groupBy((F.col("bucket") % group_count(buckets)).alias("group")).applyInArrow(stars, "doc long, centre long, asks long, has long")
    of = member.select(F.col("doc_id").alias("_m"), "class_id")
    masks = (F.bit_or("asks").alias("asks"), F.bit_or("has").alias("has"))
    mapped = found.groupBy("doc", "centre").agg(*masks)
    mapped = mapped.join(of, F.col("doc") == F.col("_m")).select(F.col("class_id").alias("a"), "centre", "asks", "has").join(of, F.col("centre") == F.col("_m")).select("a", F.col("class_id").alias("b"), "asks", "has")
    edges = cut_lineage(mapped.where("a <> b").groupBy("a", "b").agg(*masks))

    # a centre meets all members of its star
    joined = edges.select(F.col("b").alias("star"), F.col("a").alias("member"), "asks", "has").union(edges.select("b", "b", F.lit(-1).cast("long"), F.lit(-1).cast("long")).distinct()).groupBy("star", "member").agg(*masks)
    weights = member.groupBy("class_id").agg(F.count("*").alias("weight"))
    memberships = cut_lineage(joined.join(sketches.select(F.col("doc_id").alias("member"), "n"), "member"))
    # no more than the signatures of a set
    lists = memberships.groupBy("member").agg(F.collect_list(F.struct("star", "asks", "has")).alias("_l")).select("member", F.col("_l.star").alias("stars"), F.col("_l.asks").alias("all_asks"), F.col("_l.has").alias("all_has"))
    totals = memberships.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    cells = int(totals[0] // BLOCK_MEMBERS + totals[1] // BLOCK_SHINGLES) + 1
    blocks = memberships.groupBy("star").agg((1 + F.floor(F.count("*") / BLOCK_MEMBERS) + F.floor(F.sum("n") / BLOCK_SHINGLES)).alias("blocks"))
    placed = memberships.join(blocks, "star").withColumn("block", F.pmod(F.xxhash64("member"), F.col("blocks")))
    large = F.col("blocks") > 1
    placed = placed.withColumn("_o", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).withColumn("large", large).withColumn("cell", F.when(large, F.col("star")).otherwise(F.pmod(F.xxhash64("star"), F.lit(cells)))).withColumn("i", F.least("block", "_o")).withColumn("j", F.greatest("block", "_o"))
    rows = placed.select("large", "cell", "i", "j", "star", "block", "member", "asks", "has", "n").join(lists, "member").join(sketches.select(F.col("doc_id").alias("member"), "sketch"), "member").join(weights.withColumnRenamed("class_id", "member"), "member")
    keys = ["large", "cell", "i", "j"]
    wanted = cut_lineage(rows.groupBy(*keys).applyInArrow(lambda g: needed(g, num, den), "star long, i long, j long, member long"))
    hashes = cut_lineage(wanted.select(F.col("member").alias("_w")).distinct().join(member.select(F.col("doc_id").alias("_m"), F.col("text_hash").alias("_h")), F.col("_w") == F.col("_m")).select("_w", "_h"))
    texts = sifted(given, "doc_id", hashes, "_w").join(hashes, (F.col("doc_id") == F.col("_w")) & (F.col("text_hash") == F.col("_h"))).dropDuplicates(["doc_id"]).select(F.col("doc_id").alias("member"), "text")
    work = rows.join(wanted, ["star", "i", "j", "member"], "left_semi").join(cut_lineage(texts), "member")
    counted = cut_lineage(work.groupBy(*keys).applyInArrow(lambda g: count_links(g, width, num, den), "a long, b long, n long"))
    links = work.groupBy(*keys).applyInArrow(lambda g: list_links(g, width, num, den), "a long, b long, common long, united long")

    least = components(counted.where("b is not null").select("a", "b")).select(F.col("node").alias("_n"), "component")
    others = weights.join(counted.where("b is null").groupBy("a").agg(F.sum("n").alias("_links")), F.col("class_id") == F.col("a"), "left").select(F.col("class_id").alias("_c"), (F.col("weight") - 1 + F.coalesce("_links", F.lit(0))).alias("n_links"))
    grouped = member.join(least, F.col("class_id") == F.col("_n"), "left").join(others, F.col("class_id") == F.col("_c")).select(F.col("doc_id").alias("_d"), "class_id", F.coalesce("component", "class_id").alias("component_id"), "n_links")
    out = sets.join(grouped, F.col("doc_id") == F.col("_d"), "left").select("doc_id", F.col("n").alias("n_shingles"), "class_id", "component_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
    return out, links


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """docs without those that link, directly or not, to a document of smaller doc_id; rows that repeat a doc_id stay together."""
    grouped, _ = join_ngrams(docs, **options)
    gone = grouped.where("component_id < doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, F.col("doc_id").cast("long") == F.col("_gone"), "left_anti")


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    grouped, _ = join_ngrams(table(spark, sf_dir, "documents"))
    return grouped.select("doc_id", "n_shingles", "component_id", "n_links")
