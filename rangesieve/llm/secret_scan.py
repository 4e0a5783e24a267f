"""Secret scans over an incremental ledger of blobs: every version's text is addressed by its content and scanned once per rule version.

The ledger says which (blob, rule, rule version) have been scanned.  A run addresses all versions, keeps the pairs that the ledger
lacks, scans one text of each blob for its missing rules, and joins new and old findings back to every path that holds the blob.

Defined results: a null text is the empty blob; equal texts are one blob; repeated rows each get the blob's findings; an empty table
gives an empty result; a rule version that the ledger doesn't know is scanned anew; further columns pass through, but for those named
like a result (blob, spans).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, joined_to_key, table
from .spans import all_pieces, joined_spans, pieces, placed


@dataclass(frozen=True)
class Rule:
    """name; pattern of all matches; words one of which every match holds (in lower case, any case in the text); place in the order of kinds; version."""

    name: str
    pattern: str
    hints: tuple[str, ...]
    order: int
    version: int = 1


#: The patterns of the base kinds.
ASSIGN = "(?i:password|passwd|secret|token|api_?key)[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
RULES = (
    Rule("assign", ASSIGN, ("password", "passwd", "secret", "token", "api_key", "apikey"), 0),
    # a run that is too short holds no longer one, so the least length can stand in the pattern
    Rule("access", "AKIA[A-Z0-9]{14,}", ("akia",), 1),
    Rule("hex", "[0-9a-f]{16,}", (), 2),
    Rule("pem", "-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----", ("private key",), 3),
)
BASE = ("assign", "access", "hex")
FINDING = "blob string, rule string, version int, start long, end long"


def blob_address(text: str = "text") -> Column:
    return F.sha2(F.coalesce(F.col(text), F.lit("")), 256)


def _gate(rule: Rule) -> Column:
    gate = F.lit(not rule.hints)
    for hint in rule.hints:
        gate = gate | F.contains(F.lower("text"), F.lit(hint))
    return gate


def scan_blobs(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """FINDING rows of (blob, text, due: names of the rules to apply)."""
    parts = [pieces(r.name, r.pattern, F.array_contains("due", r.name) & _gate(r)) for r in rules]
    hits = placed(blobs.select("blob", all_pieces(parts).alias("p")).where(F.size("p") > 0), "blob", "p")
    value = F.length(F.regexp_extract("found", ASSIGN, 1))
    version = F.element_at(F.create_map(*(F.lit(x) for r in rules for x in (r.name, r.version))), F.col("kind"))
    return hits.where((F.col("kind") != "assign") | (value >= 12)).select("blob", F.col("kind").alias("rule"), version.alias("version"), F.col("start").cast("long"), F.col("end").cast("long"))


def scan_versions(versions: DataFrame, ledger: DataFrame | None = None, findings: DataFrame | None = None, rules: tuple[Rule, ...] = RULES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(versions without text, with blob; all findings of the current rules; the (blob, rule, version) that this run adds to the ledger).

    ledger: (blob, rule, version) of earlier runs, findings: their FINDING rows.  Append the third result and the new findings to both.
    """
    paths = versions.withColumn("blob", blob_address()).select(*(f"`{c}`" for c in versions.columns if c not in ("text", "blob", "spans")), "blob")
    names = F.array(*(F.lit(r.name) for r in rules))
    # one text of each blob; equal texts meet in the partial aggregation of their own task first
    texts = versions.select(blob_address().alias("blob"), F.coalesce("text", F.lit("")).alias("text")).dropDuplicates(["blob"])
    if ledger is None:
        due = texts.withColumn("due", names)
    else:
        current = F.create_map(*(F.lit(x) for r in rules for x in (r.name, r.version)))
        done = ledger.where(F.element_at(current, F.col("rule")) == F.col("version")).groupBy("blob").agg(F.collect_set("rule").alias("done"))
        due = texts.join(done, "blob", "left").withColumn("due", F.array_except(names, F.coalesce("done", F.array().cast("array<string>")))).where(F.size("due") > 0).drop("done")
    found = cut_lineage(scan_blobs(due, rules))
    version = F.element_at(F.create_map(*(F.lit(x) for r in rules for x in (r.name, r.version))), F.col("rule"))
    added = due.select("blob", F.explode("due").alias("rule")).withColumn("version", version)
    everything = found
    if findings is not None:
        everything = found.union(findings.where(version == F.col("version")).select("blob", "rule", "version", "start", "end")).distinct()
    return paths, everything, added


def findings_by_path(paths: DataFrame, findings: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """paths with spans: an array of (start, order, kind, end), by start and then by the order of kinds."""
    order = F.element_at(F.create_map(*(F.lit(x) for r in rules for x in (r.name, r.order))), F.col("rule"))
    # a blob has no more findings than its text has words
    per_blob = findings.groupBy("blob").agg(F.array_sort(F.collect_list(F.struct("start", order.alias("order"), F.col("rule").alias("kind"), "end"))).alias("spans"))
    # a blob may have any number of paths
    joined = joined_to_key(paths, "blob", per_blob)
    return joined.withColumn("spans", F.coalesce("spans", F.array().cast("array<struct<start:bigint,order:int,kind:string,end:bigint>>")))


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    paths, findings, _ = scan_versions(table(spark, sf_dir, "documents").select("doc_id", "text"))
    full = findings_by_path(paths, findings)
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = joined_spans(F.filter("spans", lambda s: s["kind"].isin(*BASE)))
    return full.select("doc_id", *(count(k) for k in BASE), F.sha2(base, 256).alias("base_sha256"), joined_spans(F.col("spans")).alias("spans"))
