"""The enhanced filter: keys in an order-preserving entropy code, and tail tries that tell keys of equal infixes apart.

Either part can be left out, which gives the ablations: neither is the base filter over byte strings.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.entropy import Codebook, encode_columns, plain_bits
from ..functions.geometry import ANCHOR_BITS, Geometry
from ..plans.lineage import written
from .anchors import Ranked, prepare_keys, rank_keys
from .base import BaseFilter
from .tailtrie import Entry, TailTrie

TRIES = "block_id long, infix long, n_keys int, known array<string>, code_bits int, trailing_bits int, format string, t int, n_nodes int, has_prefix boolean, longest_path int"


@dataclass
class CodedKeys:
    """A key set in a book's code, ranked: what filters of one book share."""

    ranked: Ranked
    book: Codebook | None
    n: int

    @classmethod
    def prepare(cls, df: DataFrame, key: str = "key", book: Codebook | None = None) -> CodedKeys:
        keys = prepare_keys(df, key).select(F.col("key").cast("binary").alias("key"))
        coded = rank_keys(keys if book is None else written(encode_columns(keys, ["key"], book).select("key").distinct()))
        return cls(coded, book, coded.n if book is None else keys.count())


@dataclass
class EnhancedFilter:
    base: BaseFilter
    book: Codebook | None
    tries: DataFrame | None
    n: int

    @classmethod
    def build(cls, df: DataFrame | CodedKeys, key: str = "key", t: int = 1024, bpk: float = 16, k: int | None = 2, tries: bool = True, key_bits: int = 160, book: Codebook | None = None) -> EnhancedFilter:
        """k: bytes of context of the code, None for no code; tries: whether equal infixes get one.  Keys that are coded already bring their book."""
        if not isinstance(df, CodedKeys):
            keys = prepare_keys(df, key)
            df = CodedKeys.prepare(keys, book=book or (None if k is None else Codebook.build(keys, k)))
        book = df.book
        base = BaseFilter.build(df.ranked, t=t, bpk=bpk, key_bits=key_bits)
        made = None
        if tries:
            # at most t keys of one block; the bits that a run of n equal infixes frees are those of n - 1 slots
            groups = base.keyed.groupBy("block_id", "infix", "shared", "redundant").agg(F.count("*").alias("n"), F.collect_list("key").alias("keys"))
            m, r = base.m, base.r
            # read by every probe and by the sizes
            made = written(groups.mapInArrow(lambda b: _tries(b, m, r), TRIES))
        return cls(base, book, made, df.n)

    def probe(self, queries: DataFrame) -> DataFrame:
        """(query_id, positive): an infix strictly inside answers at once, one equal to an end asks its trie."""
        coded = encode_columns(queries.select("query_id", F.col("lo").cast("binary").alias("lo"), F.col("hi").cast("binary").alias("hi")), ["lo", "hi"], self.book)
        if self.tries is None:
            return self.base.probe(coded.select("query_id", "lo", "hi")).select("query_id", "positive")
        routed = self.base.route(coded)
        past = F.col("shared") + 1 + F.col("redundant") + self.base.m - 1
        asked = routed.where("route = 'block'").select("query_id", F.col("block_id").alias("_b"), self.base._infix(F.col("lo")).alias("_l"), self.base._infix(F.col("hi")).alias("_h"), *(F.substring(f"{c}_code", (past + 1).cast("int"), F.lit(1 << 20)).alias(f"_{c}") for c in ("lo", "hi")))
        inside = (F.col("infix") > F.col("_l")) & (F.col("infix") < F.col("_h"))
        cut = lambda end, x: F.rpad(F.substring(end, F.lit(1), F.length(x)), F.length(x), F.lit("0"))
        fits = F.exists("known", lambda x: ((F.col("infix") > F.col("_l")) | (x >= cut(F.col("_lo"), x))) & ((F.col("infix") < F.col("_h")) | (x <= cut(F.col("_hi"), x))))
        found = asked.join(self.tries.select("block_id", "infix", "known"), (F.col("_b") == F.col("block_id")) & F.col("infix").between(F.col("_l"), F.col("_h")) & (inside | F.col("known").isNull() | fits), "left_semi")
        hits = routed.where("route = 'anchor'").select("query_id").union(found.select("query_id")).distinct().withColumn("_hit", F.lit(True))
        return queries.select("query_id").join(hits, "query_id", "left").select("query_id", F.coalesce("_hit", F.lit(False)).alias("positive"))

    def bits(self) -> DataFrame:
        """(component, bits); tries live in the slots that equal infixes freed, and `overflow` is what doesn't fit."""
        out = self.base.bits()
        spark = out.sparkSession
        extra = [("codebook", self.book.bits() if self.book else 0)]
        if self.tries is not None:
            free = (F.col("n_keys") - 1) * (self.base.r + 1)
            extra.append(("overflow", self.tries.agg(F.coalesce(F.sum(F.greatest(F.lit(0), F.col("code_bits") + F.col("trailing_bits") - free)), F.lit(0))).first()[0]))
        return out.union(spark.createDataFrame(extra, "component string, bits long"))


def _tries(batches: Iterator[pa.RecordBatch], m: int, r: int) -> Iterator[pa.RecordBatch]:
    names = [f.split()[0] for f in TRIES.split(", ")]
    for b in batches:
        out: dict[str, list] = {c: [] for c in names}
        for block, infix, shared, redundant, n, keys in zip(*(b.column(c).to_pylist() for c in ("block_id", "infix", "shared", "redundant", "n", "keys")), strict=True):
            row = {"block_id": block, "infix": infix, "n_keys": n, "known": None, "code_bits": 0, "trailing_bits": 0, "format": None, "t": 0, "n_nodes": 0, "has_prefix": False, "longest_path": 0}
            if n > 1:
                suffixes = [plain_bits(key)[shared + redundant + m :] for key in keys]
                trie = TailTrie.build(suffixes)
                trie = trie.fit(suffixes, (n - 1) * (r + 1))
                code = trie.encode()
                row |= {"known": [e.path + e.trailing for e in trie.entries], "code_bits": len(code), "trailing_bits": len(trie.trailing()), "format": "gamma" if code[0] == "1" else "unary", "t": trie.t, "n_nodes": trie.nodes(), "has_prefix": trie.has_prefix(), "longest_path": max(trie.path_lengths(), default=0)}
            for c in names:
                out[c].append(row[c])
        types = {"block_id": pa.int64(), "infix": pa.int64(), "known": pa.list_(pa.string()), "format": pa.string(), "has_prefix": pa.bool_()}
        yield pa.RecordBatch.from_arrays([pa.array(out[c], types.get(c, pa.int32())) for c in names], names=names)


class EnhancedBlock:
    """One dynamic block of the enhanced filter: each infix is plain or has a tail trie; keys are integers of geo.width bits."""

    def __init__(self, geo: Geometry, r: int, t: int = 4):
        self.geo, self.r, self.t = geo, r, t
        self.infixes: dict[int, TailTrie | None] = {}
        self.copies: dict[int, int] = {}
        self.cases: dict[str, int] = {"plain": 0, "1": 0, "2": 0, "3": 0, "same": 0}

    def insert(self, key: int) -> str:
        infix, suffix = self.geo.infix(key), self.geo.suffix(key)
        if infix not in self.infixes:
            self.infixes[infix] = None
            case = "plain"
        elif self.infixes[infix] is None:
            # the first key has no bits left: it ends at the root, the new one goes below
            self.infixes[infix] = TailTrie([Entry("", True), Entry(suffix[:1] or "0", False, suffix[1 : 1 + self.t].ljust(self.t, "0"))], self.t)
            case = "3"
        else:
            case = str(self.infixes[infix].insert(suffix))
        self.cases[case] += 1
        return case

    def delete(self, key: int) -> bool:
        infix, suffix = self.geo.infix(key), self.geo.suffix(key)
        if infix not in self.infixes:
            return False
        trie = self.infixes[infix]
        if trie is None or not trie.entries:
            del self.infixes[infix]
            return True
        if not trie.delete(suffix):
            return False
        if not trie.entries:
            del self.infixes[infix]
        elif len(trie.entries) == 1 and not trie.entries[0].path + trie.entries[0].trailing:
            self.infixes[infix] = None
        return True

    def positive(self, lo: int, hi: int) -> bool:
        low, high = self.geo.infix(lo), self.geo.infix(hi)
        # only the ends' infixes have tries to ask, and with neighbouring ends nothing lies between
        for infix, trie in self.infixes.items() if high - low > 1 else [(x, self.infixes[x]) for x in {low, high} if x in self.infixes]:
            if low < infix < high:
                return True
            if infix in (low, high) and (trie is None or trie.positive(self.geo.suffix(lo) if infix == low else None, self.geo.suffix(hi) if infix == high else None)):
                return True
        return False

    def bits(self) -> int:
        """Slots of r bits with delimiter and run end, and the tries' codes with padded trailing strings."""
        quotients = (self.geo.high >> self.r) - (self.geo.low >> self.r) + 1
        return quotients + len(self.infixes) * (self.r + 2) + sum(t.size(padded=True) for t in self.infixes.values() if t is not None) + ANCHOR_BITS
