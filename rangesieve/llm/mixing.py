"""Mixing sources to target weights: whole blocks of equal token counts, apportioned by highest odd-divisor quotients.

Every source gets a token target; seats, each worth one block, go one after another to the source with the highest
quotient target / (2 * seats + 1), and the seats of a source are dealt to the shards in that order: the quotas.  Inside a source the
documents stand in a seeded random order, again and again, and each shard takes its quota of blocks from where the one before it ends.
Only the few documents on such an edge have to be found, by sums over ranges of the order; every other document is told by its place
before or after them, so that texts never travel.  `seats` is the least number of blocks: a block is also small against the smallest target.

Defined results: a null text has size 0 and is never taken; the null source is the last source; rows that are equal in doc_id and text
share what an edge between them gives; an empty table gives an empty result; input columns named like a result are replaced.
"""

from __future__ import annotations

import heapq
import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut_lineage, table

#: Blocks that the source of the smallest positive target gets at least, so that rounding is a few per cent of any target.
LEAST_BLOCKS = 50
WEIGHTS = (3, 1, 2)
RESULTS = ("size", "source_size", "target", "taken", "shard_taken")


def word_count(text: str = "text") -> Column:
    """Number of runs without space or control characters 9 to 13."""
    return F.when(F.col(text).isNull(), 0).otherwise(F.length(F.regexp_replace(F.regexp_replace(F.col(text), "[^\\x20\\x09-\\x0D]+", "a"), "[^a]", ""))).cast("long")


def capped_targets(sizes: dict, share: float = 1.5, cap: float = 2.0, weights: tuple[int, ...] = WEIGHTS) -> dict:
    """Token target of each source, sources in code point order, None last; what a cap cuts off is shared again by weight."""
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [s for s in sizes if s is None]
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    total = share * sum(sizes.values())
    fixed: dict = {}
    while True:
        free = [s for s in order if s not in fixed]
        left, shared = total - sum(fixed.values()), sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / shared > cap * sizes[s]]
        if not over:
            return fixed | {s: left * weight[s] / shared for s in free}
        fixed |= {s: cap * sizes[s] for s in over}


def apportion(targets: dict, seats: int, n_shards: int = 8) -> dict:
    """Seats of each source and shard: {source: [seats in shard 0, 1, ...]}; ties go to the earlier source."""
    names = list(targets)
    out = {s: [0] * n_shards for s in names}
    whole = sum(targets.values())
    if not whole or not seats:
        return out
    # rounding by a divisor that gives away too few seats yields the first part of the sequence, whatever its length
    few = max(0.0, seats - len(names) / 2 - 1)
    held = {s: max(0, math.ceil(few * targets[s] / whole - 0.5)) for s in names}
    given = 0
    for s in names:
        rounds, rest = divmod(held[s], n_shards)
        out[s] = [rounds + ((k - given) % n_shards < rest) for k in range(n_shards)]
        given += held[s]
    heap = [(-targets[s] / (2 * held[s] + 1), i) for i, s in enumerate(names) if targets[s] > 0]
    heapq.heapify(heap)
    while given < seats:
        _, i = heap[0]
        s = names[i]
        out[s][given % n_shards] += 1
        held[s] += 1
        given += 1
        heapq.heapreplace(heap, (-targets[s] / (2 * held[s] + 1), i))
    return out


def shard_edges(quota: list[int], block: int, most: int) -> list[int]:
    """Where each shard's words end in a source's repeated order; none lie beyond `most`."""
    out, at = [], 0
    for n in quota:
        at += n * block
        out.append(min(at, most))
    return out


def mix_sources(docs: DataFrame, n_shards: int = 8, seats: int = 20_000, seed: int = 17, share: float = 1.5, cap: float = 2.0, weights: tuple[int, ...] = WEIGHTS, size: Column | None = None) -> tuple[DataFrame, DataFrame]:
    """(docs with size, source_size, target, taken and shard_taken, what each shard takes of it; quotas: source, shard, blocks, block_tokens).

    The sources of a mixture are a list that the driver holds, some hundred bytes each.
    """
    spark = docs.sparkSession
    names = [c for c in docs.columns if c not in RESULTS]
    sized = docs.select(*(F.col(f"`{c}`") for c in names), (word_count() if size is None else size).cast("long").alias("size"))
    key = F.struct(F.xxhash64(F.lit(seed), "doc_id", "size").alias("at"), F.xxhash64("doc_id", *(["text"] if "text" in names else []), "size").alias("tie"))
    light = cut_lineage(sized.select("source", "size", key.alias("k")))
    totals = light.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("rows")).collect()  # one row for each source
    sizes = {r["source"]: r["n"] for r in totals}
    targets = capped_targets(sizes, share, cap, weights)
    block = max(1, int(min([sum(targets.values()) / seats, *(t / LEAST_BLOCKS for t in targets.values() if t > 0)])))
    blocks = apportion(targets, int(sum(targets.values()) / block), n_shards)
    # a source never gives more than the cap, however its last block falls
    edges = {s: shard_edges(blocks[s], block, int(cap * sizes[s])) for s in sizes}
    quotas = spark.createDataFrame([(s, k, n, block) for s in sizes for k, n in enumerate(blocks[s])], "source string, shard int, blocks long, block_tokens long")

    # an edge lies some words into a pass over the source's order
    # as many ranges of the order as each has rows, so that neither their list nor one of them is long
    bits = max([0, *(r["rows"].bit_length() // 2 for r in totals)])
    part = F.shiftright(F.col("k.at"), 64 - bits) if bits else F.lit(0).cast("long")
    sums = light.groupBy("source", part.alias("part")).agg(F.sum("size").alias("n"))
    before = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select(F.col("source").alias("_s"), F.col("part").alias("_p"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"), "n")
    asked = spark.createDataFrame([(s, k, e // sizes[s], e % sizes[s]) for s in sizes if sizes[s] for k, e in enumerate(edges[s])], "source string, shard int, passes long, offset long")
    found = asked.join(starts, F.col("source").eqNullSafe(F.col("_s")) & (F.col("offset") >= F.col("start")) & (F.col("offset") < F.col("start") + F.col("n")))
    found = cut_lineage(found.select("_s", "_p", "start", "shard", "passes", "offset"))
    # equal rows of the order are one step of it
    near = light.withColumn("part", part).join(found.select("_s", "_p", "start").distinct(), F.col("source").eqNullSafe(F.col("_s")) & (F.col("part") == F.col("_p")))
    steps = near.groupBy("_s", "_p", "start", "k").agg(F.sum("size").alias("words"), F.count("*").alias("copies"))
    upto = F.sum("words").over(Window.partitionBy("_s", "_p").orderBy("k").rowsBetween(Window.unboundedPreceding, 0))
    steps = steps.withColumn("begin", F.col("start") + upto - F.col("words")).drop("start")
    on = found.alias("f").join(steps.alias("t"), F.col("f._s").eqNullSafe(F.col("t._s")) & (F.col("f._p") == F.col("t._p")) & (F.col("offset") >= F.col("begin")) & (F.col("offset") < F.col("begin") + F.col("words")))
    where = {(r["_s"], r["shard"]): r for r in on.select("f._s", "shard", "passes", "k", F.floor((F.col("offset") - F.col("begin")) / F.col("copies")).alias("inside")).collect()}  # n_shards rows for each source at most
    cut = lambda s, k: (lambda r: (r["passes"], (r["k"]["at"], r["k"]["tie"]), r["inside"]))(where[s, k])
    plan = [(s, sizes[s], float(targets[s]), [cut(s, k) for k in range(n_shards)] if sizes[s] else []) for s in sizes]
    plan = spark.createDataFrame(plan, "_p string, source_size long, target double, _cuts array<struct<passes:bigint,k:struct<at:bigint,tie:bigint>,inside:bigint>>")

    joined = sized.withColumn("_k", key).join(F.broadcast(plan) if len(sizes) <= 10_000 else plan, F.col("source").eqNullSafe(F.col("_p")))
    upto = F.transform("_cuts", lambda c: c["passes"] * F.col("size") + F.when(F.col("_k") < c["k"], F.col("size")).when(F.col("_k") == c["k"], c["inside"]).otherwise(0))
    shares = F.transform("_upto", lambda e, i: e - F.when(i > 0, F.get(F.col("_upto"), i - 1)).otherwise(0))
    taken = F.coalesce(F.get(F.col("_upto"), F.lit(n_shards - 1)), F.lit(0)).cast("long")
    return joined.withColumn("_upto", upto).withColumns({"taken": taken, "shard_taken": shares}).select(*(F.col(f"`{c}`") for c in names), *RESULTS), quotas


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs as often as the mix takes them, to the nearest whole document."""
    # the results stand beside columns of the same names
    held = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), *(F.col(f"`{c}`") for c in ("doc_id", "source", "text")))
    taken, _ = mix_sources(held, **options)
    copies = F.when(F.col("size") > 0, F.round(F.col("taken") / F.col("size"))).otherwise(0).cast("int")
    return taken.withColumn("_copy", F.explode(F.sequence(F.lit(0), copies))).where("_copy > 0").select("_row.*")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))[0].select("doc_id", "size", "source_size", "target", "taken", "source", "shard_taken")
