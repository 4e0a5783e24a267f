"""Personal data: generators propose overlapping candidate spans, boosted trees judge them, a calibrated threshold selects redactions.

Strict patterns give the base spans, which always stay.  Loose generators propose more: digit groups, spelled-out addresses, account
numbers.  Trees over format and context learn on all candidates that evidence apart from their features labels: check sums, number
ranges, words before them.  They are counted by their feature values, which have fixed greatest values, and the counts are what is
fitted; strict and loose ones weigh the same.  A loose candidate without evidence is unlabelled, not negative.  The threshold is the
lowest score at which the loose ones of a held-out half reach the wanted precision, and never below even odds.  The fitted trees become
one SQL expression, so that scoring all candidates needs no Python.

Defined results: a null text is empty; equal texts get equal spans and are searched once; repeated rows each give a row; without
candidates of both labels nothing is added to the base spans; an empty table gives an empty result; further columns pass through.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, joined_to_key, table
from .secret_scan import blob_address
from .spans import all_pieces, joined_spans, pieces, placed

ROUNDS, RATE, LEAF, PRECISION = 30, 0.3, 8, 0.97
CONTEXT = 24

#: The strict patterns.  Lookbehinds let a match begin at the start of a run or where the last match ended, as the plain pattern would.
EMAIL = "(?:\\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\\.[A-Za-z0-9-]++)++"
IP = "(?<![0-9])[0-9]++\\.[0-9]++\\.[0-9]++\\.[0-9]++"
CARD = "[0-9](?:[\\x20-]?[0-9]){15,}+"
PHONE = "\\+[0-9][\\x20().0-9-]+[0-9]"
OCTET = "0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
BASE = ("email", "ip", "card", "phone")
#: The loose generators.
LOOSE = {
    "digits": "(?<![0-9+.])\\(?[0-9][0-9\\x20().-]{7,30}[0-9](?![0-9])",
    "spelled": "(?:\\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++\\x20?[\\[(]at[\\])]\\x20?[A-Za-z0-9-]++(?:\\x20?(?:\\.|[\\[(]dot[\\])])\\x20?[A-Za-z0-9-]++)++",
    "account": "\\b[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}\\b",
    "ident": "(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    # what a strict match runs past, as it takes the numbers beside in
    "run": "(?<![0-9A-Za-z])(?:(?:[0-9]{4}[\\x20-]){3}[0-9]{4}|[0-9]{16,19})(?![0-9A-Za-z])",
    "dialled": "\\+1[\\x20.-]?\\(?[0-9]{3}\\)?[\\x20.-]{0,2}[0-9]{3}[\\x20.-]?[0-9]{4}(?![0-9])",
}
KINDS = (*BASE, *LOOSE)
KEYWORDS = "(?i)(tel|phone|call|mobile|fax|mail|contact|card|visa|credit|account|iban|ssn|id)[^A-Za-z0-9]*$"
#: Words that tell of another kind of number.
OTHER = "(?i)(order|invoice|item|page|version|total|count|year|build|line|lot|serial)[^A-Za-z0-9]*$"
#: The trees do not see the keywords that labels rest on.
MASKED = ("keyword",)
#: Greater lengths and numbers count as these, so that the counts by feature values do not grow with the candidates.
GREATEST = {"n_chars": 40, "n_digits": 24, "n_groups": 8, "n_marks": 8, "longest": 24}
FEATURES = ("n_chars", "n_digits", "n_groups", "n_marks", "longest", "luhn", "keyword", "after_letter", "before_letter", "kind_no")


def candidates(text: str = "text") -> Column:
    """All candidates of a text, strict and loose."""
    has = lambda s: F.contains(F.col(text), F.lit(s))
    gates = {"email": has("@"), "phone": has("+"), "spelled": has("[at]") | has("(at)"), "dialled": has("+"), "ip": has("."), "ident": has("-")}
    patterns = dict(zip(BASE, (EMAIL, IP, CARD, PHONE), strict=True)) | LOOSE
    return all_pieces(pieces(k, p, gates.get(k, F.lit(True)), text, CONTEXT) for k, p in patterns.items())


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of up to 40 digits passes the check sum."""
    backward = F.reverse(digits)
    # a second digit d adds 2d, less 9 beyond 9
    add = lambda i: F.when(i % 2 == 1, F.substring(backward, i, F.lit(1)).cast("int")).otherwise(F.element_at(F.array(*map(F.lit, (0, 2, 4, 6, 8, 1, 3, 5, 7, 9))), F.substring(backward, i, F.lit(1)).cast("int") + 1))
    places = F.sequence(F.lit(1), F.length(digits))
    return F.when(F.length(digits).between(1, 40), F.aggregate(places, F.lit(0), lambda total, i: total + add(i)) % 10 == 0).otherwise(False)


def valid(kind: Column, found: Column) -> Column:
    """Whether a strict match is a base span."""
    digits = _digits(found)
    return (
        F.when(kind == "email", True)
        .when(kind == "ip", found.rlike(f"^{OCTET}(?:\\.{OCTET}){{3}}$"))
        .when(kind == "card", F.length(digits).between(16, 19) & luhn(digits))
        .when(kind == "phone", F.length(digits).between(8, 15))
        .otherwise(False)
    )


def mod97(found: Column) -> Column:
    """Whether an account number passes its check sum."""
    turned = F.concat(F.substring(found, 5, 1 << 20), F.left(found, F.lit(4)))
    value = lambda ch: F.conv(ch, 36, 10).cast("int")
    return F.aggregate(F.regexp_extract_all(turned, F.lit("[0-9A-Z]"), F.lit(0)), F.lit(0), lambda total, ch: (total * F.when(value(ch) > 9, 100).otherwise(10) + value(ch)) % 97) == 1


def evidence(kind: Column, found: Column, before: Column) -> Column:
    """1 for personal data, 0 for other text, null where nothing tells; a candidate's place beside base spans plays no part."""
    said, other = before.rlike(KEYWORDS), before.rlike(OTHER)
    area, group, serial = F.substring(found, 1, 3), F.substring(found, 5, 2), F.substring(found, 8, 4)
    issued = ~area.isin("000", "666") & (area < "900") & (group != "00") & (serial != "0000")
    count = F.length(_digits(found))
    dated = found.rlike("^\\(?(?:[12][0-9]{3}[.-][0-9]{1,2}[.-][0-9]{1,2}|[0-9]{1,2}[.-][0-9]{1,2}[.-][12][0-9]{3})(?![0-9])")
    return (
        F.when(kind == "account", mod97(found).cast("int"))
        .when(kind == "ident", F.when(~issued | other, 0).when(said, 1))
        .when(kind == "spelled", F.when(found.rlike("[A-Za-z]{2,}$"), 1).otherwise(0))
        .when(kind == "run", luhn(_digits(found)).cast("int"))
        .when(kind == "dialled", F.when(other, 0).otherwise(1))
        .when(kind == "digits", F.when(dated | other | ~count.between(8, 19), 0).when(said, 1).when((count > 15) & ~luhn(_digits(found)), 0))
        # what looks strict and isn't valid
        .when(~valid(kind, found), 0)
        .otherwise(1)
    )


def with_features(spans: DataFrame) -> DataFrame:
    digits = _digits(F.col("found"))
    groups = F.regexp_extract_all("found", F.lit("[A-Za-z0-9]+"), F.lit(0))
    letter = "[^\\W\\d_]"
    values = {
        "n_chars": F.length("found"), "n_digits": F.length(digits), "n_groups": F.size(groups), "n_marks": F.length(F.regexp_replace("found", "[A-Za-z0-9\\x20]", "")),
        "longest": F.array_max(F.transform(groups, lambda g: F.length(g))), "luhn": luhn(digits).cast("int"), "keyword": F.col("before").rlike(KEYWORDS).cast("int"),
        "after_letter": F.col("after").rlike(letter).cast("int"), "before_letter": F.right("before", F.lit(1)).rlike(letter).cast("int"), "kind_no": F.array_position(F.array(*map(F.lit, KINDS)), F.col("kind")),
    }
    most = lambda k, v: F.least(v, F.lit(GREATEST[k])) if k in GREATEST else v
    return spans.withColumns({k: most(k, F.coalesce(v, F.lit(0))).cast("double") for k, v in values.items()})


@dataclass(frozen=True)
class Stump:
    """A tree of depth two: a first split, and a split and two values on either side."""

    feature: int
    cut: float
    sides: tuple[tuple[int, float, float, float], tuple[int, float, float, float]]

    def column(self, columns: list[Column]) -> Column:
        leaf = lambda s: F.when(columns[s[0]] <= s[1], s[2]).otherwise(s[3])
        return F.when(columns[self.feature] <= self.cut, leaf(self.sides[0])).otherwise(leaf(self.sides[1]))

    def value(self, x: list[float]) -> float:
        f, cut, low, high = self.sides[0 if x[self.feature] <= self.cut else 1]
        return low if x[f] <= cut else high

    def values(self, x: np.ndarray) -> np.ndarray:
        f, g = self.sides
        low, high = np.where(x[:, f[0]] <= f[1], f[2], f[3]), np.where(x[:, g[0]] <= g[1], g[2], g[3])
        return np.where(x[:, self.feature] <= self.cut, low, high)


def _best_cut(part: np.ndarray, x: np.ndarray, grad: np.ndarray, hess: np.ndarray, count: np.ndarray) -> tuple[float, int, float, float, float]:
    """(gain, feature, cut, value at most cut, value above) of the best split of the rows of `part` by second-order gain."""
    x, grad, hess, count = x[part], grad[part], hess[part], count[part]
    g, h, n = grad.sum(), hess.sum(), count.sum()
    best = (0.0, 0, math.inf, float(g / (h + 1)), float(g / (h + 1)))
    for f in range(x.shape[1]):
        value, at = np.unique(x[:, f], return_inverse=True)
        gl, hl, nl = (np.cumsum(np.bincount(at, c, len(value)))[:-1] for c in (grad, hess, count))
        if not len(gl):
            continue
        gain = np.where((nl >= LEAF) & (n - nl >= LEAF), gl**2 / (hl + 1) + (g - gl) ** 2 / (h - hl + 1) - g * g / (h + 1), 0.0)
        i = int(gain.argmax())
        if gain[i] > best[0] + 1e-12:
            best = (float(gain[i]), f, float(value[i] + value[i + 1]) / 2, float(gl[i] / (hl[i] + 1)), float((g - gl[i]) / (h - hl[i] + 1)))
    return best


def boost(x: list[list[float]], y: list[int], rounds: int = ROUNDS, rate: float = RATE, count: list[int] | None = None, weight: list[float] | None = None) -> tuple[float, list[Stump]]:
    """Logistic boosting with trees of depth two: (first score, trees).  A row stands for `count` candidates of a weight each."""
    x, y = np.array(x, dtype=float), np.array(y, dtype=float)
    count = np.ones(len(y)) if count is None else np.array(count, dtype=float)
    mass = count if weight is None else count * np.array(weight, dtype=float)
    mean = ((mass * y).sum() + 1) / (mass.sum() + 2)
    start = math.log(mean / (1 - mean))
    score, trees, every = np.full(len(y), start), [], np.ones(len(y), dtype=bool)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(score, -30, 30)))
        grad, hess = mass * (y - p), mass * p * (1 - p)
        gain, f, cut, _, _ = _best_cut(every, x, grad, hess, count)
        if gain <= 1e-9:
            break
        sides = []
        for part in (x[:, f] <= cut, x[:, f] > cut):
            _, g, c, low, high = _best_cut(part, x, grad, hess, count)
            sides.append((g, c, rate * low, rate * high))
        trees.append(Stump(f, cut, (sides[0], sides[1])))
        score = score + trees[-1].values(x)
    return start, trees


def calibrated(scores: list[float], y: list[int], precision: float = PRECISION, count: list[int] | None = None) -> float:
    """The lowest score from which on at least this share of the held-out candidates are positive; infinite if none is."""
    out, hit, n = math.inf, 0, 0
    order = sorted(zip(scores, y, count or [1] * len(y), strict=True), reverse=True)
    for k, (s, label, c) in enumerate(order, 1):
        hit, n = hit + label * c, n + c
        # equal scores pass together
        if hit >= precision * n and (k == len(order) or order[k][0] < s):
            out = s
    return out


def fitted(cells: list[tuple]) -> tuple[float, list[Stump], float] | None:
    """(first score, trees, threshold) from (held out, loose, label, values of the features, number of candidates); None without both labels."""
    cells = sorted(cells)
    seen = [i for i, f in enumerate(FEATURES) if f not in MASKED]
    x = [[c[3][i] for i in seen] for c in cells]
    learn = [i for i, c in enumerate(cells) if not c[0]]
    rest = [i for i, c in enumerate(cells) if c[0] and c[1]]
    if not rest or len({cells[i][2] for i in learn}) < 2:
        return None
    total = {side: sum(cells[i][4] for i in learn if cells[i][1] == side) for side in (False, True)}
    weight = {side: sum(total.values()) / (2 * n) if n and all(total.values()) else 1.0 for side, n in total.items()}
    start, trees = boost([x[i] for i in learn], [cells[i][2] for i in learn], count=[cells[i][4] for i in learn], weight=[weight[cells[i][1]] for i in learn])
    score = start + sum(t.values(np.array([x[i] for i in rest])) for t in trees) if trees else np.full(len(rest), start)
    return start, trees, calibrated(score.tolist(), [cells[i][2] for i in rest], count=[cells[i][4] for i in rest])


def find_personal_data(docs: DataFrame) -> DataFrame:
    """docs without text, with base and extra: arrays of (order, start, end, kind), by kind and then by start."""
    rows = docs.withColumn("_blob", blob_address())
    keep = [c for c in docs.columns if c not in ("text", "base", "extra")]
    held = cut_lineage(rows.select("_blob", "text").withColumn("_c", candidates()).where(F.size("_c") > 0).select("_blob", "_c").dropDuplicates(["_blob"]))
    spans = placed(held, "_blob", "_c").withColumn("strict", valid(F.col("kind"), F.col("found")))
    spans = spans.withColumn("label", evidence(F.col("kind"), F.col("found"), F.col("before")))
    spans = cut_lineage(with_features(spans).drop("before", "after"))

    # only loose candidates that no base span touches can be added; a text's candidates lie in one partition
    base = spans.where("strict").select(F.col("_blob").alias("_b"), F.col("start").alias("_s"), F.col("end").alias("_e"))
    loose = spans.where(~F.col("kind").isin(*BASE))
    # least and greatest pass over nulls
    shared = F.when(F.col("_s").isNotNull(), F.least("end", "_e") - F.greatest("start", "_s"))
    labelled = loose.join(base, (F.col("_blob") == F.col("_b")) & (F.col("start") < F.col("_e")) & (F.col("end") > F.col("_s")), "left")
    labelled = labelled.groupBy("_blob", "kind", "start", "end", "label", *FEATURES).agg(F.coalesce(F.max(shared / (F.col("end") - F.col("start"))), F.lit(0.0)).alias("cover"))
    labelled = cut_lineage(labelled)
    told = spans.where(F.col("kind").isin(*BASE))
    apart = (F.pmod(F.xxhash64("_blob", "kind", "start"), F.lit(2)) == 1).alias("held_out")
    both = labelled.where("label IS NOT NULL").select(apart, F.lit(True).alias("loose"), "label", *FEATURES).union(told.select(apart, F.lit(False), "label", *FEATURES))
    # as many rows as there are combinations of feature values
    cells = both.groupBy("held_out", "loose", "label", *FEATURES).agg(F.count("*").alias("n")).collect()
    model = fitted([(r["held_out"], r["loose"], r["label"], tuple(r[f] for f in FEATURES), r["n"]) for r in cells])
    chosen = labelled.where("false")
    if model is not None and math.isfinite(model[2]):
        columns = [F.col(f) for f in FEATURES if f not in MASKED]
        score = F.lit(model[0])
        for t in model[1]:
            score = score + t.column(columns)
        chosen = labelled.where((score >= max(model[2], 0.0)) & (F.col("cover") == 0))
    order = F.array_position(F.array(*map(F.lit, KINDS)), F.col("kind"))
    span = F.struct(order.alias("order"), F.col("start").cast("long").alias("start"), F.col("end").cast("long").alias("end"), "kind")
    both = spans.where("strict").select("_blob", F.lit(True).alias("_base"), span.alias("s")).union(chosen.select("_blob", F.lit(False), span))
    listed = lambda at: F.array_sort(F.collect_list(F.when(at, F.col("s"))))  # noqa: E731  no more than the text's matches
    found = both.groupBy("_blob").agg(listed(F.col("_base")).alias("base"), listed(~F.col("_base")).alias("extra"))
    out = joined_to_key(rows.select(*(F.col(f"`{c}`") for c in keep), "_blob"), "_blob", found)
    empty = F.array().cast("array<struct<order:bigint,start:bigint,end:bigint,kind:string>>")
    return out.drop("_blob").withColumns({c: F.coalesce(c, empty) for c in ("base", "extra")})


def redacted(docs: DataFrame, mark: str = "█") -> DataFrame:
    """docs with the characters of every base and extra span replaced by `mark`; rows are told apart by their text."""
    found = find_personal_data(docs.select("text").distinct().withColumn("_key", F.col("text")))
    spans = found.select("_key", F.concat("base", "extra").alias("_spans")).where(F.size("_spans") > 0)
    covered = F.array_distinct(F.flatten(F.transform("_spans", lambda s: F.sequence(s["start"] + 1, s["end"]))))
    cut = F.array_join(F.transform(F.split("text", ""), lambda ch, i: F.when(F.array_contains(covered, (i + 1).cast("long")), mark).otherwise(ch)), "")
    return docs.join(spans, F.col("text") == F.col("_key"), "left").withColumn("text", F.when(F.col("_spans").isNotNull(), cut).otherwise(F.col("text"))).drop("_key", "_spans")


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_personal_data(table(spark, sf_dir, "documents").select("doc_id", "text"))
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    # base kinds come first in the order of kinds
    return found.select("doc_id", *(count(k) for k in BASE), F.sha2(joined_spans(F.col("base")), 256).alias("base_sha256"), joined_spans(F.concat("base", "extra")).alias("spans"))
