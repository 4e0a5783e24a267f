"""Quality rules: per-document measures, and lines that recur in too many documents of one host.

Normalised lines (A-Z lower-cased, blanks collapsed) are hashed; each counts once for every distinct text of a host.  A line above
the host's limit is boilerplate: its words count as removed, and a document that keeps too few words is rejected.  Exact copies
count as one text, so that a group of copies doesn't make its own lines boilerplate.  `cleaned` gives the kept documents without
their boilerplate lines; all other columns stay as given.

Defined results: a null or wordless text fails the base rule; the null host is a host of its own; repeated rows each give a row
with the same verdict; an empty table gives an empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, table
from .textkernel import LOWER, covered, find_words, mix64, row_sums, run_hashes, segment_hashes, text_slices, window_starts

#: A line is above the limit in more distinct texts of its host than both of these tell.
MIN_TEXTS = 20
SHARE_OF_HOST = 0.05
#: A document is depleted if it keeps fewer words, or a smaller share of its words.
LEAST_WORDS = 20
LEAST_SHARE = 0.3
#: Bytes of text that are measured at once, and rows that are cleaned at once: workers keep what they once held, and an executor has several.
MEASURED_BYTES, CLEANED_ROWS = 1 << 19, 1000
_SYMBOLS = np.zeros(256, dtype=bool)
_SYMBOLS[np.frombuffer(b"#*$%&|<>", dtype=np.uint8)] = True

STATS = "_id long, _host string, _text_hash long, _row long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, _lines array<long>, _line_words array<int>"


def repeated(keys: np.ndarray) -> np.ndarray:
    """Which keys occur more than once."""
    ordered = np.sort(keys)
    twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
    if not len(twice):
        return np.zeros(len(keys), dtype=bool)
    return twice[np.minimum(np.searchsorted(twice, keys), len(twice) - 1)] == keys


def line_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, head: np.ndarray) -> np.ndarray:
    """Hash of each normalised line; head: the first word of each."""
    return run_hashes(segment_hashes(LOWER[data], starts, ends), head, np.append(head[1:], len(starts))).view(np.int64)


def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(_id, _host, _text_hash, _row, text) to STATS."""
    for rows, data, offsets in text_slices(batches, most=MEASURED_BYTES):
        n = rows.num_rows
        starts, ends, first = find_words(data, offsets)
        of_row = np.repeat(np.arange(n), np.diff(first))
        letters = np.zeros(len(data) + 1, dtype=np.int64)
        np.cumsum((data & 0xC0) != 0x80, out=letters[1:])
        word_chars = row_sums(letters[ends] - letters[starts], first)
        symbols = np.zeros(len(data) + 1, dtype=np.int64)
        np.cumsum(_SYMBOLS[data], out=symbols[1:])

        begin, row = window_starts(first, 8)
        own = run_hashes(segment_hashes(data, starts, ends), begin, begin + 8)
        twice = repeated(mix64(own + row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
        repeats = row_sums(covered(len(starts), begin[twice], 8), first)

        breaks = np.flatnonzero(data == 10)
        line = np.searchsorted(breaks, starts) + of_row
        head = np.flatnonzero(np.diff(line, prepend=-1))
        line_row = of_row[head]
        before = np.searchsorted(breaks, starts[head])
        padded = np.concatenate([[-1], breaks, [len(data)]])
        lo = np.maximum(padded[before] + 1, offsets[line_row])
        hi = np.minimum(padded[before + 1], offsets[line_row + 1])
        raw = mix64(segment_hashes(data, lo, hi) + line_row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        lines_in = np.searchsorted(line_row, np.arange(n + 1))
        distinct = np.bincount(line_row[np.unique(raw, return_index=True)[1]], minlength=n)

        tail = np.append(head[1:], len(starts))
        norm = line_hashes(data, starts, ends, head)
        order = np.lexsort((norm, line_row))
        r, h, words = line_row[order], norm[order], (tail - head)[order]
        new = np.ones(len(order), dtype=bool)
        new[1:] = (r[1:] != r[:-1]) | (h[1:] != h[:-1])
        at = np.flatnonzero(new)
        words = np.add.reduceat(words, at) if len(at) else words
        lists = pa.array(np.searchsorted(r[at], np.arange(n + 1)), pa.int32())
        yield pa.RecordBatch.from_arrays(
            [
                *rows.columns[:4], pa.array(np.diff(first)), pa.array(word_chars), pa.array(np.diff(symbols[offsets])), pa.array(np.diff(lines_in) - distinct), pa.array(repeats),
                pa.ListArray.from_arrays(lists, pa.array(h[at])), pa.ListArray.from_arrays(lists, pa.array(words.astype(np.int32))),
            ],
            names=["_id", "_host", "_text_hash", "_row", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "_lines", "_line_words"],
        )


def without_lines(text: str, gone: list[int]) -> str:
    """The text less the lines whose hashes are in `gone`."""
    data = np.frombuffer(text.encode(), dtype=np.uint8)
    starts, ends, _ = find_words(data, np.array([0, len(data)]))
    line = np.searchsorted(np.flatnonzero(data == 10), starts)
    head = np.flatnonzero(np.diff(line, prepend=-1))
    cut = set(line[head][np.isin(line_hashes(data, starts, ends, head), gone)].tolist())
    return "\n".join(x for k, x in enumerate(text.split("\n")) if k not in cut)


def clean_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with text and, last, the hashes of the lines to take out (or null) to rows without the last column."""
    for whole in batches:
        for batch in (whole.slice(k, CLEANED_ROWS) for k in range(0, whole.num_rows, CLEANED_ROWS)):
            at, gone, columns = batch.schema.get_field_index("text"), batch.column(batch.num_columns - 1), batch.columns[:-1]
            if gone.null_count < len(gone):
                texts = [t if g is None or t is None else without_lines(t, g) for t, g in zip(batch.column(at).to_pylist(), gone.to_pylist(), strict=True)]
                columns[at] = pa.array(texts, batch.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names[:-1])


def judge_quality(docs: DataFrame, host: str = "source", min_texts: int = MIN_TEXTS, share: float = SHARE_OF_HOST, least_words: int = LEAST_WORDS, least_share: float = LEAST_SHARE) -> DataFrame:
    """doc_id, text_hash, host, the measures, base_failed, n_removed_words, kept, removed_lines (hashes, or null): a row for each row of docs."""
    given = docs.select(F.col("doc_id").cast("long").alias("_id"), F.col(f"`{host}`").cast("string").alias("_host"), F.xxhash64("text").alias("_text_hash"), F.monotonically_increasing_id().alias("_row"), "text")
    # the written table fixes the row numbers
    stats = cut_lineage(given.mapInArrow(measure, STATS))

    texts = stats.select("_host", "_text_hash", "_lines").dropDuplicates(["_host", "_text_hash"])
    hosts = texts.groupBy("_host").agg(F.count("*").alias("_texts"))
    counts = texts.select("_host", F.explode("_lines").alias("_line")).groupBy("_host", "_line").agg(F.count("*").alias("_n")).where(F.col("_n") > min_texts)
    above = counts.alias("c").join(hosts.alias("h"), F.col("c._host").eqNullSafe(F.col("h._host"))).where(F.col("_n") > share * F.col("_texts")).select(F.col("c._host").alias("_h"), F.col("_line").alias("_l"))
    held = stats.select("_row", "_host", F.explode(F.arrays_zip("_lines", "_line_words")).alias("e")).select("_row", "_host", F.col("e._lines").alias("_line"), F.col("e._line_words").alias("_w"))
    removed = held.join(above, F.col("_host").eqNullSafe(F.col("_h")) & (F.col("_line") == F.col("_l"))).groupBy("_row").agg(F.sum("_w").alias("n_removed_words"), F.collect_list("_line").alias("removed_lines"))

    judged = stats.drop("_lines", "_line_words").join(removed, "_row", "left").withColumn("n_removed_words", F.coalesce("n_removed_words", F.lit(0)).cast("long"))
    left = F.col("n_words") - F.col("n_removed_words")
    depleted = (F.col("n_removed_words") > 0) & ((left < least_words) | (left < least_share * F.col("n_words")))
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    return judged.select(
        F.col("_id").alias("doc_id"), F.col("_text_hash").alias("text_hash"), F.col("_host").alias("host"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_removed_words", failed.alias("base_failed"), (~failed & ~depleted).alias("kept"), "removed_lines"
    )


def keep_good(docs: DataFrame, **rules) -> DataFrame:
    """The rows of docs that judge_quality keeps."""
    bad = judge_quality(docs, **rules).where("not kept").select(F.col("doc_id").alias("_bad"), F.col("text_hash").alias("_hash"), F.col("host").alias("_on")).distinct()
    host = F.col(f"`{rules.get('host', 'source')}`").cast("string")
    return docs.join(bad, F.col("doc_id").cast("long").eqNullSafe(F.col("_bad")) & (F.xxhash64("text") == F.col("_hash")) & host.eqNullSafe(F.col("_on")), "left_anti")


def cleaned(docs: DataFrame, **rules) -> DataFrame:
    """The rows of docs that judge_quality keeps, their texts without the lines above the limit."""
    judged = judge_quality(docs, **rules).where("NOT kept OR removed_lines IS NOT NULL")
    judged = judged.select(F.col("doc_id").alias("_of"), F.col("text_hash").alias("_hash"), F.col("host").alias("_on"), F.col("kept").alias("_kept"), F.col("removed_lines").alias("_lines")).dropDuplicates(["_of", "_hash", "_on"])
    host = F.col(f"`{rules.get('host', 'source')}`").cast("string")
    joined = docs.join(judged, F.col("doc_id").cast("long").eqNullSafe(F.col("_of")) & (F.xxhash64("text") == F.col("_hash")) & host.eqNullSafe(F.col("_on")), "left")
    kept = joined.where(F.coalesce("_kept", F.lit(True))).select(*(F.col(f"`{c}`") for c in docs.columns), "_lines")
    return kept.mapInArrow(clean_texts, docs.schema)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_quality(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_removed_words")
