"""Substring dedup: passages that recur across documents, found from windows hashed at difference-cover positions only.

The cover holds, for every offset modulo the period, a pair of residues with that difference.  So whenever two documents share a
passage of `width` words, some position of the passage is a cover position in both, and the anchor window there, of
width - period + 1 words, is hashed in both.  Anchors that occur in one document only end the matter for their surroundings; around
the others, the full windows within reach are hashed ("extended") and each looks for a smaller document.

Both exchanges carry packed hashes.  What one batch can tell by itself never travels: an anchor met in two of its documents is live,
and a window met in a smaller document of the batch is removed.  So a passage that a third of the corpus shares sends one
entry for each batch, not for each document.

Defined results: a null text has no words; a document with fewer words than the window keeps all; rows that repeat a doc_id
each lose the words that a smaller doc_id's text covers; a null doc_id neither removes nor loses anything; an empty table gives an
empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import table
from .textkernel import covered, find_words, mix64, run_hashes, segment_hashes, text_slices, window_starts

#: Perfect difference sets, {period: residues whose differences hit every offset}.
COVERS = {7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (0, 1, 4, 14, 16), 31: (0, 1, 3, 8, 12, 18)}
#: Bytes of text whose hashes meet in one exchange bucket; bounds the memory of the task that reads it.
BUCKET_BYTES = 4 << 20
_SECOND = np.uint64(0xC2B2AE3D27D4EB4F)
_PACKED = "bucket int, known boolean, ids binary, keys binary, rows binary"
_FOUND = "_shard int, ids binary, keys binary"
ENTRY = np.dtype([("h", "<u8"), ("c", "<u4")])


def cover_for(width: int) -> tuple[int, np.ndarray]:
    """(period, residues): the longest period that leaves anchors of at least a third of the window, or every position."""
    fit = [p for p in COVERS if width - p + 1 >= max(2, width // 3)]
    return (max(fit), np.array(COVERS[max(fit)])) if fit else (1, np.array([0]))


class Cover:
    def __init__(self, width: int):
        self.width = width
        self.period, residues = cover_for(width)
        self.anchor = width - self.period + 1
        self.member = np.zeros(self.period, dtype=bool)
        self.member[residues] = True

    def anchors(self, words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(hash, row, start) of the anchor windows at cover positions of rows that could hold a full window."""
        long = np.diff(first) >= self.width
        begin, row = window_starts(first, self.anchor)
        use = self.member[(begin - first[row]) % self.period] & long[row]
        begin, row = begin[use], row[use]
        return run_hashes(words, begin, begin + self.anchor), row, begin

    def around(self, starts: np.ndarray, row: np.ndarray, first: np.ndarray, n: int) -> np.ndarray:
        """Starts of the full windows that hold a live anchor."""
        low = np.maximum(starts - (self.width - self.anchor), first[row])
        high = np.minimum(starts, first[row + 1] - self.width)
        edge = np.zeros(n + 1, dtype=np.int64)
        ok = high >= low
        np.add.at(edge, low[ok], 1)
        np.add.at(edge, high[ok] + 1, -1)
        return np.flatnonzero(np.cumsum(edge[:-1]) > 0)


def _deal(keys: np.ndarray, rows: np.ndarray, bucket: np.ndarray, ids: np.ndarray, known: bool = False) -> pa.RecordBatch:
    """One packed row for each bucket: the documents in it, the hashes, and each one's place among the documents."""
    order = np.argsort(bucket, kind="stable")
    bucket, keys, rows = bucket[order], keys[order], rows[order]
    cuts = np.flatnonzero(np.diff(bucket, prepend=-1, append=-1))
    packed: tuple[list, list, list] = ([], [], [])
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        used, place = np.unique(rows[a:b], return_inverse=True)
        for to, x in zip(packed, (ids[used], keys[a:b], place.astype(np.uint16)), strict=True):
            to.append(x.tobytes())
    columns = [pa.array(bucket[cuts[:-1]].astype(np.int32)), pa.array([known] * len(packed[0]), pa.bool_()), *(pa.array(x, pa.binary()) for x in packed)]
    return pa.RecordBatch.from_arrays(columns, names=["bucket", "known", "ids", "keys", "rows"])


def _unpack(group: pa.Table, dtype: np.dtype) -> dict[bool, tuple[np.ndarray, np.ndarray]]:
    """{known: (documents, hashes)} of packed rows."""
    parts: dict[bool, tuple[list, list]] = {True: ([], []), False: ([], [])}
    for known, i, k, r in zip(*(group.column(c).to_pylist() for c in ("known", "ids", "keys", "rows")), strict=True):
        parts[known][0].append(np.frombuffer(i, np.int64)[np.frombuffer(r, np.uint16)])
        parts[known][1].append(np.frombuffer(k, dtype))
    return {f: (np.concatenate(d or [np.zeros(0, np.int64)]), np.concatenate(k or [np.zeros(0, dtype)])) for f, (d, k) in parts.items()}


def shard_of(docs: np.ndarray, shards: int) -> np.ndarray:
    return (mix64(docs.astype(np.int64).view(np.uint64)) % np.uint64(shards)).astype(np.int32)


def _for_shards(docs: np.ndarray, keys: np.ndarray, shards: int) -> pa.Table:
    """Found (document, hash) pairs, one packed row for each shard of the documents."""
    shard = shard_of(docs, shards)
    order = np.argsort(shard, kind="stable")
    shard, docs, keys = shard[order], docs[order], keys[order]
    cuts = np.flatnonzero(np.diff(shard, prepend=-1, append=-1))
    spans = list(zip(cuts[:-1], cuts[1:], strict=True))
    return pa.table({"_shard": pa.array(shard[cuts[:-1]]), "ids": pa.array([docs[a:b].tobytes() for a, b in spans], pa.binary()), "keys": pa.array([keys[a:b].tobytes() for a, b in spans], pa.binary())})


def _keyed(docs: np.ndarray, keys: np.ndarray) -> np.ndarray:
    full = keys if keys.dtype.names is None else keys["h"] + mix64(keys["c"].astype(np.uint64))
    return mix64(full + mix64(docs.astype(np.int64).view(np.uint64) + np.uint64(1)))


def _pool(found: pa.Table, dtype: np.dtype) -> np.ndarray:
    docs = np.frombuffer(b"".join(found.column("ids").to_pylist()), np.int64)
    return np.unique(_keyed(docs, np.frombuffer(b"".join(found.column("keys").to_pylist()), dtype)))


def _among(pool: np.ndarray, docs: np.ndarray, keys: np.ndarray) -> np.ndarray:
    if not len(pool) or not len(keys):
        return np.zeros(len(keys), dtype=bool)
    look = _keyed(docs, keys)
    return pool[np.minimum(np.searchsorted(pool, look), len(pool) - 1)] == look


def _ids(batch: pa.RecordBatch, column: str = "_doc") -> np.ndarray:
    """The row's documents; rows without one are told apart by nothing and never looked up."""
    return np.asarray(batch.column(column).fill_null(0).to_numpy(zero_copy_only=False), dtype=np.int64)


def anchor_hasher(width: int, buckets: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cover = Cover(width)
        for batch, data, offsets in text_slices(batches):
            starts, ends, first = find_words(data, offsets)
            h, row, _ = cover.anchors(segment_hashes(data, starts, ends), first)
            at = np.unique(mix64(h ^ mix64(row.astype(np.uint64) + np.uint64(1))), return_index=True)[1]
            h, row, ids = h[at], row[at], _ids(batch)
            if not len(h):
                continue
            order = np.argsort(h, kind="stable")
            h, row = h[order], row[order]
            head = np.flatnonzero(np.diff(h, prepend=h[:1] + np.uint64(1)))
            size = np.diff(np.append(head, len(h)))
            # copies of one doc_id don't make an anchor live
            low, high = np.minimum.reduceat(ids[row], head), np.maximum.reduceat(ids[row], head)
            twice = low < high
            live = np.repeat(twice, size)
            if live.any():
                yield _deal(h[live], row[live], np.full(int(live.sum()), int(h[0] % np.uint64(buckets))), ids, known=True)
            # a live anchor sends two of its documents, which is what the others need to know
            last = np.append(head[1:], len(h)) - 1
            other = np.array([int(head[i] + np.argmax(ids[row[head[i] : last[i] + 1]] != ids[row[head[i]]])) for i in np.flatnonzero(twice)], dtype=np.int64)
            send = np.concatenate([head, other])
            yield _deal(h[send], row[send], (h[send] >> np.uint64(24)) % np.uint64(buckets), ids)

    return run


def live_anchors(group: pa.Table, shards: int) -> pa.Table:
    """The anchors that occur in two documents, for each document that holds them."""
    parts = _unpack(group, np.dtype("<u8"))
    docs, h = parts[False]
    if len(h):
        order = np.argsort(h, kind="stable")
        docs, h = docs[order], h[order]
        head = np.flatnonzero(np.diff(h, prepend=h[:1] + np.uint64(1)))
        live = np.repeat(np.minimum.reduceat(docs, head) < np.maximum.reduceat(docs, head), np.diff(np.append(head, len(h))))
        docs, h = docs[live], h[live]
    return _for_shards(np.concatenate([docs, parts[True][0]]), np.concatenate([h, parts[True][1]]), shards)


def _window_keys(words: np.ndarray, begin: np.ndarray, width: int) -> np.ndarray:
    out = np.empty(len(begin), dtype=ENTRY)
    out["h"] = run_hashes(words, begin, begin + width)
    out["c"] = (run_hashes(mix64(words ^ _SECOND), begin, begin + width) >> np.uint64(32)).astype(np.uint32)
    return out


def windows_near(width: int, buckets: int) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Packed full windows around the live anchors of one shard of documents."""

    def run(rows: pa.Table, live: pa.Table) -> pa.Table:
        cover, pool = Cover(width), _pool(live, np.dtype("<u8"))
        out = []
        known = rows.filter(pa.compute.is_valid(rows.column("_doc"))) if len(pool) else rows.slice(0, 0)
        for batch, data, offsets in text_slices(iter(known.combine_chunks().to_batches()), "_text"):
            starts, ends, first = find_words(data, offsets)
            words, ids = segment_hashes(data, starts, ends), _ids(batch)
            h, row, begin = cover.anchors(words, first)
            hit = _among(pool, ids[row], h)
            begin = cover.around(begin[hit], row[hit], first, len(words))
            if not len(begin):
                continue
            row, keys = np.searchsorted(first, begin, side="right") - 1, _window_keys(words, begin, width)
            order = np.lexsort((ids[row], keys["c"], keys["h"]))
            keys, row = keys[order], row[order]
            head = np.flatnonzero(_new(keys))
            gone = ids[row] > np.repeat(ids[row[head]], np.diff(np.append(head, len(keys))))
            if gone.any():
                out.append(_deal(keys[gone], row[gone], np.full(int(gone.sum()), int(keys["h"][0] % np.uint64(buckets))), ids, known=True))
            out.append(_deal(keys[head], row[head], (keys["h"][head] >> np.uint64(24)) % np.uint64(buckets), ids))
        empty = _deal(np.zeros(0, ENTRY), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64))
        return pa.Table.from_batches([empty, *out])

    return run


def _new(keys: np.ndarray) -> np.ndarray:
    out = np.ones(len(keys), dtype=bool)
    out[1:] = (keys["h"][1:] != keys["h"][:-1]) | (keys["c"][1:] != keys["c"][:-1])
    return out


def removed_windows(group: pa.Table, shards: int) -> pa.Table:
    """The windows that start in a smaller document too, for each document that loses them."""
    parts = _unpack(group, ENTRY)
    docs, keys = parts[False]
    if len(keys):
        order = np.lexsort((docs, keys["c"], keys["h"]))
        docs, keys = docs[order], keys[order]
        head = np.flatnonzero(_new(keys))
        gone = docs > np.repeat(docs[head], np.diff(np.append(head, len(keys))))
        docs, keys = docs[gone], keys[gone]
    return _for_shards(np.concatenate([docs, parts[True][0]]), np.concatenate([keys, parts[True][1]]), shards)


def remover(width: int, keep: list[str], with_text: bool, schema: pa.Schema) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """One shard of documents to the kept columns with n_words, n_removed, kept_sha256 and, if wanted, kept_text."""

    def run(rows: pa.Table, found: pa.Table) -> pa.Table:
        pool, out = _pool(found, ENTRY), []
        having = np.unique(np.frombuffer(b"".join(found.column("ids").to_pylist()), np.int64))
        for batch, data, offsets in text_slices(iter(rows.combine_chunks().to_batches()), "_text"):
            starts, ends, first = find_words(data, offsets)
            ids = _ids(batch)
            gone = np.zeros(len(starts), dtype=bool)
            pick = np.isin(ids, having) & np.asarray(batch.column("_doc").is_valid())
            if pick.any():
                begin, row = window_starts(first, width)
                begin, row = begin[pick[row]], row[pick[row]]
                gone = covered(len(starts), begin[_among(pool, ids[row], _window_keys(segment_hashes(data, starts, ends), begin, width))], width)
            # the kept words, each with one byte after it, in one buffer
            stay = np.flatnonzero(~gone)
            s, e = starts[stay], ends[stay]
            begin = np.cumsum(e - s + 1) - (e - s + 1)
            text = np.full(int((e - s + 1).sum()), 0x20, dtype=np.uint8)
            at = np.ones(int((e - s).sum()), dtype=np.int64)
            if len(stay):
                jump = np.cumsum(e - s)[:-1]
                at[0] = s[0]
                at[jump] = s[1:] - e[:-1] + 1
                to = np.ones(len(at), dtype=np.int64)
                to[0] = 0
                to[jump] = 2
                text[np.cumsum(to)] = data[np.cumsum(at)]
            bounds = np.append(begin, len(text))[np.searchsorted(stay, first)]
            whole = text.tobytes()
            texts = [whole[a : max(a, b - 1)] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
            lost = np.zeros(len(gone) + 1, dtype=np.int64)
            np.cumsum(gone, out=lost[1:])
            columns = [*(batch.column(c) for c in keep), pa.array(np.diff(first)), pa.array(np.diff(lost[first])), pa.array([hashlib.sha256(t).hexdigest() for t in texts])]
            if with_text:
                columns.append(pa.array(texts, pa.binary()).cast(pa.string()))
            out.append(pa.RecordBatch.from_arrays(columns, names=schema.names))
        return pa.Table.from_batches([b.cast(schema) for b in out], schema)

    return run


def remove_repeats(docs: DataFrame, width: int = 50, keep: list[str] | None = None, with_text: bool = True) -> DataFrame:
    """The `keep` columns of docs (default: all) with n_words, n_removed, kept_sha256 and kept_text (words joined by one space)."""
    keep = [c for c in (docs.columns if keep is None else keep) if c not in ("n_words", "n_removed", "kept_sha256", "kept_text")]
    total = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    buckets = int(total // BUCKET_BYTES) + 1

    def sharded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            # rows without a doc_id are spread by their length
            spread = pa.compute.coalesce(batch.column("_doc"), pa.compute.cast(pa.compute.binary_length(batch.column("_text").fill_null("")), pa.int64()))
            yield batch.append_column("_shard", pa.array(shard_of(spread.to_numpy(zero_copy_only=False), buckets)))

    known = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("_doc"), "text")
    found = known.mapInArrow(anchor_hasher(width, buckets), _PACKED).groupBy("bucket").applyInArrow(lambda g: live_anchors(g, buckets), _FOUND)
    rows = docs.select(*(F.col(f"`{c}`") for c in keep), F.col("text").alias("_text"), F.col("doc_id").cast("long").alias("_doc"))
    rows = rows.mapInArrow(sharded, T.StructType([*rows.schema.fields, T.StructField("_shard", T.IntegerType())]))
    windows = rows.groupBy("_shard").cogroup(found.groupBy("_shard")).applyInArrow(windows_near(width, buckets), _PACKED)
    gone = windows.groupBy("bucket").applyInArrow(lambda g: removed_windows(g, buckets), _FOUND)
    fields = [f for f in rows.schema.fields if f.name in keep] + [T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_sha256", T.StringType())]
    fields += [T.StructField("kept_text", T.StringType())] * with_text
    schema = T.StructType(fields)
    return rows.groupBy("_shard").cogroup(gone.groupBy("_shard")).applyInArrow(remover(width, keep, with_text, to_arrow_schema(schema)), schema)


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"), keep=["doc_id"], with_text=False)
