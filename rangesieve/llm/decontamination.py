"""Benchmark decontamination: multi-pattern search over words with shift tables, suffix buckets and direct comparison.

Every window of a benchmark item is a pattern of word numbers.  Patterns of one length share a table that tells, from the
last few words at a text position, how far the search may jump without missing an occurrence; where it may not jump, the
bucket of patterns that end in these words is compared word by word.  All documents of a slice are searched side by side.

Defined results: a null or wordless text has no words, no hits and is clean; a null or wordless item has no window;
repeated items and items of equal windows all count as occurring; an item without item_id makes hits, but is not listed; repeated rows each give a row; an empty benchmark leaves
every document clean; input columns named like an output column are replaced.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import table
from .textkernel import LOWER, NON_ALNUM, covered, find_words, row_sums, segment_hashes, text_slices

#: Benchmark text that one pass holds in memory; a larger benchmark is searched in several passes over the documents.
BLOCK_BYTES = 16 << 20
LANE = 512


@dataclass
class PatternGroup:
    """Patterns of one length: `shift` of each known word block, and the patterns that end in a block."""

    width: int
    block: int
    patterns: np.ndarray
    owners: list[list[str]]
    keys: np.ndarray = field(init=False)
    shifts: np.ndarray = field(init=False)
    by_end: np.ndarray = field(init=False)
    ends: np.ndarray = field(init=False)

    def build(self, radix: np.uint64) -> PatternGroup:
        m, b = self.width, self.block
        blocks = np.concatenate([self.block_keys(self.patterns, j, radix) for j in range(b - 1, m)])
        moves = np.repeat(np.arange(m - b, -1, -1), len(self.patterns))
        order = np.lexsort((moves, blocks))
        self.keys, first = np.unique(blocks[order], return_index=True)
        self.shifts = moves[order][first]
        last = self.block_keys(self.patterns, m - 1, radix)
        by = np.argsort(last, kind="stable")
        self.patterns, self.owners = self.patterns[by], [self.owners[i] for i in by]
        self.by_end, self.ends = last[by], np.arange(m)
        return self

    def block_keys(self, ids: np.ndarray, j: int, radix: np.uint64) -> np.ndarray:
        key = np.zeros(len(ids), dtype=np.uint64)
        for i in range(self.block):
            key = key * radix + ids[:, j - i].astype(np.uint64)
        return key


class PatternSet:
    """All windows of the given items, compiled for search."""

    def __init__(self, items: list[tuple[str | None, str | None]], width: int = 13):
        texts = [(None if k is None else str(k), LOWER[np.frombuffer((t or "").encode(), dtype=np.uint8)]) for k, t in items]
        hashed = []
        for name, data in texts:
            starts, ends, _ = find_words(data, np.array([0, len(data)]), NON_ALNUM)
            hashed.append((name, segment_hashes(data, starts, ends)))
        self.vocabulary = np.unique(np.concatenate([h for _, h in hashed])) if hashed else np.zeros(0, np.uint64)
        self.radix = np.uint64(len(self.vocabulary) + 1)
        found: dict[int, dict[bytes, list[str]]] = {}
        for name, h in hashed:
            ids = (np.searchsorted(self.vocabulary, h) + 1).astype(np.uint32)
            m = min(width, len(ids))
            for i in range(len(ids) - m + 1 if m else 0):
                found.setdefault(m, {}).setdefault(ids[i : i + m].tobytes(), []).append(name)
        self.groups = [
            PatternGroup(m, min(3, m), np.frombuffer(b"".join(p), dtype=np.uint32).reshape(-1, m), [sorted(set(v) - {None}) for v in p.values()]).build(self.radix)
            for m, p in sorted(found.items())
        ]

    def number(self, hashes: np.ndarray) -> np.ndarray:
        """Word numbers of word hashes, 0 for words of no item."""
        if not len(self.vocabulary):
            return np.zeros(len(hashes), np.uint32)
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, at + 1, 0).astype(np.uint32)

    def occurrences(self, ids: np.ndarray, first: np.ndarray) -> Iterator[tuple[PatternGroup, np.ndarray, np.ndarray]]:
        """(group, last word of an occurrence, its pattern) over rows that begin at word first[i]."""
        for g in self.groups:
            low, high = first[:-1] + g.width - 1, first[1:]
            lanes = np.maximum(-(-(high - low) // LANE), 0)
            row = np.repeat(np.arange(len(lanes)), lanes)
            at = low[row] + (np.arange(len(row)) - (np.cumsum(lanes) - lanes)[row]) * LANE
            stop = np.minimum(at + LANE, high[row])
            where, which = [], []
            while len(at):
                key = np.zeros(len(at), dtype=np.uint64)
                for i in range(g.block):
                    key = key * self.radix + ids[at - i].astype(np.uint64)
                k = np.minimum(np.searchsorted(g.keys, key), len(g.keys) - 1)
                shift = np.where(g.keys[k] == key, g.shifts[k], g.width - g.block + 1)
                halt = np.flatnonzero(shift == 0)
                if len(halt):
                    lo, hi = np.searchsorted(g.by_end, key[halt], "left"), np.searchsorted(g.by_end, key[halt], "right")
                    spread = np.repeat(np.arange(len(halt)), hi - lo)
                    pattern = lo[spread] + np.arange(len(spread)) - (np.cumsum(hi - lo) - (hi - lo))[spread]
                    end = at[halt][spread]
                    for j in range(g.width):
                        same = ids[end - j] == g.patterns[pattern, g.width - 1 - j]
                        end, pattern = end[same], pattern[same]
                    where.append(end)
                    which.append(pattern)
                at = at + np.maximum(shift, 1)
                live = at < stop
                at, stop = at[live], stop[live]
            if where:
                yield g, np.concatenate(where), np.concatenate(which)


def _searcher(patterns: PatternSet, keep: int, more: bool, prior: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, offsets in text_slices(batches, "_text"):
            data = LOWER[raw]
            starts, ends, first = find_words(data, offsets, NON_ALNUM)
            hit = np.zeros(len(starts), dtype=bool)
            pairs: set[tuple[int, str]] = set()
            if prior:
                for i, (bits, names) in enumerate(zip(rows.column("_cover").to_pylist(), rows.column("_items").to_pylist(), strict=True)):
                    n = first[i + 1] - first[i]
                    hit[first[i] : first[i + 1]] = np.unpackbits(np.frombuffer(bits, np.uint8), count=n).astype(bool) if n else False
                    pairs.update((i, x) for x in names)
            for g, end, pattern in patterns.occurrences(patterns.number(segment_hashes(data, starts, ends)), first):
                hit |= covered(len(hit), end - g.width + 1, g.width)
                row = np.searchsorted(first, end, side="right") - 1
                for i, p in set(zip(row.tolist(), pattern.tolist(), strict=True)):
                    pairs.update((i, x) for x in g.owners[p])
            items: list[list[str]] = [[] for _ in range(rows.num_rows)]
            for i, x in sorted(pairs):
                items[i].append(x)
            out = [*rows.columns[:keep], pa.array(np.diff(first)), pa.array(row_sums(hit, first)), pa.array(items, pa.list_(pa.string()))]
            names = [*rows.schema.names[:keep], "n_words", "n_hit", "_items"]
            if more:
                out += [rows.column("_text"), pa.array([np.packbits(hit[a:b]).tobytes() for a, b in zip(first[:-1], first[1:], strict=True)], pa.binary())]
                names += ["_text", "_cover"]
            yield pa.RecordBatch.from_arrays(out, names=names)

    return search


def find_contamination(docs: DataFrame, benchmark: DataFrame, width: int = 13, keep: list[str] | None = None, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The `keep` columns of docs (default: all) with n_words, n_hit, item_ids (sorted strings) and contaminated."""
    results = ("n_words", "n_hit", "item_ids", "contaminated")
    keep = [c for c in (docs.columns if keep is None else keep) if c not in results]
    items = benchmark.select(F.col("item_id").cast("string").alias("k"), F.col("text").alias("t"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0))).first()[0]
    blocks = max(1, -(-int(total) // block_bytes))
    now = docs.select(*(F.col(f"`{c}`") for c in keep), F.col("text").alias("_text"))
    kept = now.schema.fields[:-1]
    for b in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("k"), F.lit(blocks)) == b)
        patterns = PatternSet([(r["k"], r["t"]) for r in part.collect()], width)  # block_bytes of text, give or take the hash
        more = b + 1 < blocks
        fields = [*kept, T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()), T.StructField("_items", T.ArrayType(T.StringType()))]
        if more:
            fields += [T.StructField("_text", T.StringType()), T.StructField("_cover", T.BinaryType())]
        now = now.mapInArrow(_searcher(patterns, len(keep), more, b > 0), T.StructType(fields))
        if more:
            now = now.select(*(F.col(f"`{c}`") for c in keep), "_text", "_cover", "_items")
    return now.select(*(F.col(f"`{c}`") for c in keep), "n_words", "n_hit", F.array_sort(F.array_distinct("_items")).alias("item_ids")).withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), keep=["doc_id"])
    return found.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), "contaminated")
